"""Column functions: text, samples, answer parsers."""
