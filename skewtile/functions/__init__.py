"""Column expressions and numpy kernels of plane geometry and space-filling curves."""
