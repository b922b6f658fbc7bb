"""Tensor kernels, decompositions, baselines and measures."""
