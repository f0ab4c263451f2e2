"""Kernels and distributed operators: summaries, projections, clustering, baselines."""
