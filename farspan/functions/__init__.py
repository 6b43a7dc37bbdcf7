"""Column expressions: tokens, window starts, hashed orders."""
