"""Preparation, counting, listing and splitting of graphs."""
