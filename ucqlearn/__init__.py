"""Training models over a union of joins of relational tables without building the join."""
