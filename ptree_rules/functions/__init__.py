"""Column functions, driver arithmetic and measures."""
