"""Scalar, grouped and table functions."""
