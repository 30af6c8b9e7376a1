"""SQL functions, table functions and small-graph kernels."""
