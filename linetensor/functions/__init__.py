"""Column functions: bit plans, encoders, scalar and SQL functions."""
