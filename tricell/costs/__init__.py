"""Cost and balance measures of the methods."""
