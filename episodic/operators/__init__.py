"""Counting operators: chains, selection, segments, measures, baselines."""
