"""Streams: the solver with state by part, and loads by event time."""
