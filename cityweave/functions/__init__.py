"""Column functions: geometry, text forms, coordinate systems."""
