"""Column functions: text, LaTeX answers, numbers, statistics."""
