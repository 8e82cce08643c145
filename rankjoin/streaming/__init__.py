"""Ranked joins over streams."""
