"""Placement of edges and vertices on parts, and what a placement costs."""
