"""Arrivals as a stream."""
