"""Column functions: patterns, detection, text preparation, MIME types, formulas."""
