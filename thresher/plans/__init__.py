"""Choice of a method by the sizes at hand, and the SQL surface."""
