"""Numerical kernels, layouts and the two-phase greedy fits."""
