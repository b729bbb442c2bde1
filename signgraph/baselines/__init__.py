"""Baselines with the index's result schema: layered graphs, product codes, inverted lists, rotated one-bit codes, hyperplanes."""
