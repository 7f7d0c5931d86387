"""Reconstructions, baselines, measures and workloads."""
