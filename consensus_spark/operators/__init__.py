"""Operators of the schedule, the mixing and the measures."""
