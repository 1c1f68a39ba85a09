"""Scalar building blocks: membership degrees and path aggregates."""
