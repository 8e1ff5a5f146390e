"""Scalar, nested and user-defined functions."""
