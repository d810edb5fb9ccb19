"""Edit streams."""
