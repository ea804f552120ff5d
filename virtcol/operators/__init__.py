"""The relational surface around the methods."""
