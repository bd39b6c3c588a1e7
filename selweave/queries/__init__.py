"""Queries of the estimation library."""
