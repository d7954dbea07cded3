"""Column functions: cost model and vector arithmetic."""
