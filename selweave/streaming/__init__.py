"""Streaming of the estimation library."""
