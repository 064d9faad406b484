"""What is known before a join runs: statistics, classes, placement, cost, measures."""
