"""Solvers, spectra, bounds, measures and parameter sweeps."""
