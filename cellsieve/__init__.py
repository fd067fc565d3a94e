"""Constrained pattern sampling on Spark: cells of random parity constraints, oracles, baselines, measures."""
