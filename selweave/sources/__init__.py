"""Sources of the estimation library."""
