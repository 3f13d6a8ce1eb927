"""Seed-feature mining over knowledge graphs, written for DataFrames and restartable state."""

__version__ = "0.1.0"
