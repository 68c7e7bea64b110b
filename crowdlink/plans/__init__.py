"""Whole runs: question loops and experiments."""
