"""Column expressions and Python functions of the engine."""
