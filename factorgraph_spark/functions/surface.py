"""Functions for users of SQL: ``bp_lse``, ``bp_norm`` and ``bp_l1`` of log values as SQL functions, ``bp_product`` as an aggregate and
``bp_assignments`` as a table function."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bodies in SQL, so that calls become plain expressions of the plan.
SCALARS = {
    "bp_lse": ("x ARRAY<DOUBLE>", "DOUBLE", "array_max(x) + ln(aggregate(transform(x, v -> exp(v - array_max(x))), 0.0D, (a, v) -> a + v))"),
    "bp_norm": ("x ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "transform(x, v -> greatest(v - (array_max(x) + ln(aggregate(transform(x, w -> exp(w - array_max(x))), 0.0D, (a, w) -> a + w))), -700.0D))"),
    "bp_l1": ("x ARRAY<DOUBLE>, y ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(x, y, (a, b) -> abs(exp(a) - exp(b))), 0.0D, (s, d) -> s + d)"),
}


def _product(messages: pd.Series) -> list:
    import numpy as np

    total = np.sum(np.stack(list(messages)), axis=0)
    p = np.exp(total - total.max())
    return (p / p.sum()).tolist()


#: Normalised product of a group's log messages, all of one length.
product_of_messages = F.pandas_udf(_product, T.ArrayType(T.DoubleType()), F.PandasUDFType.GROUPED_AGG)


@F.udtf(returnType=T.StructType([T.StructField(c, T.IntegerType()) for c in ("cell", "slot", "state")]))
class Assignments:
    """A row for every cell of a table over variables with these domains, and every slot: the slot's state there, the last slot fastest."""

    def eval(self, cards: list):
        cells = 1
        for c in cards:
            cells *= c
        for cell in range(cells):
            rest = cell
            for slot in range(len(cards) - 1, -1, -1):
                rest, state = divmod(rest, cards[slot])
                yield cell, slot, state


def register(spark: SparkSession) -> None:
    """Makes the functions known to the session's SQL."""
    for name, (given, returns, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({given}) RETURNS {returns} RETURN {body}")
    spark.udf.register("bp_product", product_of_messages)
    spark.udtf.register("bp_assignments", Assignments)
