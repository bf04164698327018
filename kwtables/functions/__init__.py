"""Column expressions: text, path and tree patterns, scores, measures."""
