"""Versioned replay of long interaction histories on Spark."""
