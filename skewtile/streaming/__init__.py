"""Structured Streaming: queries arriving against a tiled table, and windowed loads. Each stream has a batch twin."""
