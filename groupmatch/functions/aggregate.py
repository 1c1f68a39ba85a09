"""Aggregates of scores along a path, folded left to right over arrays."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def product(values: Column) -> Column:
    return F.aggregate(values, F.lit(1.0), lambda acc, x: acc * x)


def product_decay(values: Column, weight: float) -> Column:
    """Product, divided by the number of hops to the power of `weight`."""
    return product(values) / F.pow(F.size(values).cast("double"), F.lit(float(weight)))


def mean(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda acc, x: acc + x) / F.size(values)


def least(values: Column) -> Column:
    return F.array_min(values)


def fold(name: str, values: Column, weight: float = 0.5) -> Column:
    """A named fold of any attribute over a path."""
    if name == "product_decay":
        return product_decay(values, weight)
    return {"product": product, "mean": mean, "min": least}[name](values)


def influence(values: Column, span: str) -> Column:
    """Mean influence of the path's vertices: all, the inner ones (all of a one-hop path) or all but the first."""
    if span == "inner":
        return mean(F.when(F.size(values) > 2, F.slice(values, F.lit(2), F.greatest(F.size(values) - 2, F.lit(1)))).otherwise(values))
    return mean(F.slice(values, F.lit(2), F.size(values)) if span == "no_source" else values)
