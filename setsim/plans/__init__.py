"""Choices before a run (planner), figures of a run (metrics), and the experiment series."""
