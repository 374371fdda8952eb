"""Column builders: text, months."""
