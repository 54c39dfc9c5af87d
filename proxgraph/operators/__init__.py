"""Graphs, walks, pushes and solvers."""
