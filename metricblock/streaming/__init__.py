"""Structured Streaming forms of matching and of the window and join operators."""
