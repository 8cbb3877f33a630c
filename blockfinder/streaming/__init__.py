"""Graphs that grow: updates of all stages, and jobs on Structured Streaming."""
