"""Sketches of streams and what is asked of them."""
