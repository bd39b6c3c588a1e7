"""Functions of the estimation library."""
