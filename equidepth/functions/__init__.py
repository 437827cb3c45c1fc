"""Scalar, pandas and table functions."""
