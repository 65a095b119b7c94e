"""Continuous monitoring over the events stream."""
