"""Operators of the estimation library."""
