"""Kernels, merges, layouts, vectors, coarsening, graph functions and cost measures."""
