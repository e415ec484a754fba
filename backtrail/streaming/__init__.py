"""Labels, windows and state over streams."""
