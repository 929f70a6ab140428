"""Column functions: grids, curves, slices, reproducible uniforms."""
