"""Choices of plan: engine, width, join strategy, layout."""
