"""Membership degrees of constrained values, as column expressions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType

from groupmatch.model.pattern import MembershipRule


def ratio(value: Column, minimum: float) -> Column:
    """value / minimum, at most 1; a minimum of 0 is always reached."""
    return F.when(value >= F.lit(float(minimum)), F.lit(1.0)).otherwise(value / F.lit(float(minimum))) if minimum else F.when(value.isNotNull(), F.lit(1.0))


def step(value: Column, minimum: float) -> Column:
    return F.when(value.isNotNull(), (value >= F.lit(float(minimum))).cast("double"))


def linear(value: Column, low: float, high: float) -> Column:
    """0 up to `low`, 1 from `high`, straight between."""
    return F.when(value.isNotNull(), F.least(F.greatest((value - F.lit(float(low))) / F.lit(float(high) - float(low)), F.lit(0.0)), F.lit(1.0)))


def sigmoid(value: Column, middle: float, slope: float) -> Column:
    return F.lit(1.0) / (F.lit(1.0) + F.exp(F.lit(-float(slope)) * (value - F.lit(float(middle)))))


def custom(function):
    """A degree from a Python function of a pandas series; the only shape that leaves the JVM."""

    @pandas_udf(DoubleType())
    def degree(value: pd.Series) -> pd.Series:
        return function(value)

    return degree


def degree(value: Column, minimum: float, rule: MembershipRule) -> Column:
    if rule.kind == "ratio":
        return ratio(value, minimum)
    if rule.kind == "step":
        return step(value, minimum)
    if rule.kind == "linear":
        return linear(value, *rule.params)
    if rule.kind == "sigmoid":
        return sigmoid(value, *rule.params)
    if rule.kind == "custom":
        return custom(rule.params[0])(value)
    raise ValueError(f"unknown membership kind {rule.kind}")


def least_value(minimum: float, rule: MembershipRule | None) -> float | None:
    """The least passing value where the test is a plain comparison (which scans can push down)."""
    if rule is None or rule.kind == "step":
        return float(minimum)
    return rule.cut * minimum if rule.kind == "ratio" else None


def passes(value: Column, minimum: float | None, rule: MembershipRule | None) -> Column:
    """Whether the constraint holds; no constraint always does, a null value never does."""
    if minimum is None:
        return F.lit(True)
    least = least_value(minimum, rule)
    test = value >= F.lit(least) if least is not None else degree(value, minimum, rule) >= F.lit(rule.cut)
    return F.coalesce(test, F.lit(False))
