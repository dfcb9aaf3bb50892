"""Spectral field engine on Spark."""
