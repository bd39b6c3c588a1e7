"""Learned and classical selectivity estimation on Spark."""
