"""Intersection kernels and measures."""
