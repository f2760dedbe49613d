"""Graphs, batches, marking, rank kernels and the methods built from them."""
