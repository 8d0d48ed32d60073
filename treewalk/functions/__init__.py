"""Column functions: deterministic uniforms, hash families, identifiers."""
