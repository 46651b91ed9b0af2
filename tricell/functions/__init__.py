"""Column functions: colour families, bits and roles."""
