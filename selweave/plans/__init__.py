"""Plans of the estimation library."""
