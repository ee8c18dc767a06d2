"""SQL functions, table functions and numeric kernels."""
