"""Functions in Python where columns don't suffice: custom folds, explanations."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, StringType, StructField, StructType


@pandas_udf(DoubleType())
def worst_fold(values: pd.Series) -> float:
    """A grouped fold: the least value of a group (stands for any custom fold)."""
    return float(values.min())


@udtf(returnType=StructType([StructField("node", StringType()), StructField("missing", StringType())]))
class ExplainGroup:
    """Rows (node, missing edges) of a leader's group: eval(node, mask, required, names of bits)."""

    def eval(self, node: str, mask: int, required: int, names: list[str]):
        lacking = [n for k, n in enumerate(names) if required >> k & 1 and not mask >> k & 1]
        if lacking:
            yield node, ",".join(lacking)


def worst_of_edge(batches):
    """For mapInPandas: each edge with the lesser of its scores."""
    for rows in batches:
        yield pd.DataFrame({"src": rows.src, "dst": rows.dst, "worst": rows[["trust", "intimacy"]].min(axis=1)})
