"""Sketches of streams in event-time panes."""
