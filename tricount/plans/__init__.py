"""Choosing, timing and comparing plans."""
