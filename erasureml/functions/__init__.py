"""Column expressions and array transforms."""
