"""Graphs, exact kernels, costs, blocks, exchange schemes, tasks, baselines, estimators, measures and derived quantities."""
