"""Where (label, item) pairs come from."""
