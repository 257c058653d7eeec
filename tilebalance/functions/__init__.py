"""Scalar expressions, SQL functions and table functions."""
