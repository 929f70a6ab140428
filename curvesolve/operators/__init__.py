"""Operators on frames: matrices, orders, slices, coarse pieces, local solves, faults, combinations."""
