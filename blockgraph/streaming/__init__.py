"""Edges and events that arrive as streams."""
