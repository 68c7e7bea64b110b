"""Answers that arrive over time."""
