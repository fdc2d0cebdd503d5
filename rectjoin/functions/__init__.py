"""Column expressions and SQL functions on rectangles."""
