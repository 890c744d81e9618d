"""Streams of completions."""
