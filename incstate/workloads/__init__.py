"""Circuits, states and experiment queries derived from the given tables."""
