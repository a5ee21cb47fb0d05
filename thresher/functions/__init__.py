"""Column functions: encodings of attributes and labels, and losses of splits."""
