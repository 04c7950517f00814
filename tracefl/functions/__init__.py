"""Scalar functions, and user functions for SQL."""
