"""Column expressions over canonical terms."""
