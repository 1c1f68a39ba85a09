"""Distributed operators: candidates, bounded paths, exploration, pruning, baselines and models."""
