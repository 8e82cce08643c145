"""Ranking functions and their laws."""
