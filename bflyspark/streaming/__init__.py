"""Edges that arrive: window counts, delta points, stateful increments."""
