"""Execution plans: many small circuits, one wide state, incremental updates, baselines."""
