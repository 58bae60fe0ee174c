"""Solvers for generalised linear models: coordinate steps, orders, dealing, epochs, baselines and measures."""
