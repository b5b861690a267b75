"""Arrivals as streams."""
