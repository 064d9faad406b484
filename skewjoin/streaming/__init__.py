"""Streams: skew that is kept up to date, and joins per micro-batch."""
