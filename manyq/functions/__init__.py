"""Column expressions and small numeric rules that the engine and its queries share."""
