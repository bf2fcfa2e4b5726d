"""Coordinated samples of keys that carry several weights, on Spark."""
