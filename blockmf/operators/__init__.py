"""Factorisation operators: model, kernels, executor, baselines, measures, recommendation."""
