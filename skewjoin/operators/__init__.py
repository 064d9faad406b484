"""Operators that change or join rows."""
