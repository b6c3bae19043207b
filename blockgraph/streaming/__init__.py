"""Edges as streams."""
