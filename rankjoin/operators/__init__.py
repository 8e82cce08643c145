"""Sweeps, enumerators, baselines and relational helpers."""
