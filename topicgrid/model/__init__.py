"""Collapsed Gibbs samplers on the grid, what they estimate, and how good it is."""
