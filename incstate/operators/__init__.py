"""Operators over circuits, graphs and states."""
