"""Registered queries, training loops and comparisons."""
