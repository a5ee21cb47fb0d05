"""One-pass searches over streams."""
