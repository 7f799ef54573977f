"""Column expressions and small sequential kernels."""
