"""Triangles of edge streams."""
