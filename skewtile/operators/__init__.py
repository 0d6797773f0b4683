"""Spatial operators over tiled tables, their baselines, and the relational surroundings."""
