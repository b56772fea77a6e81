"""Scalar, array and random functions."""
