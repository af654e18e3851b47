"""Column expressions: keyed noise, closed forms, text features."""
