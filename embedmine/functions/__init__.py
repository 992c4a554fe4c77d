"""Column expressions of canonicality and the forms of patterns."""
