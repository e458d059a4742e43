"""Names for SQL users: scalar functions, vectorised entropy, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf


def entropy_of():
    """Entropy in bits of an array of counts."""

    def run(counts: pd.Series) -> pd.Series:
        def one(c):
            c = np.asarray(c, float)
            c = c[c > 0]
            return float(np.log2(c.sum()) - (c * np.log2(c)).sum() / c.sum()) if len(c) else 0.0

        return counts.map(one)

    run.__annotations__ = {"counts": pd.Series, "return": pd.Series}
    return pandas_udf(run, "double")


def entropy_agg():
    """The same as a grouped aggregate over a column of counts."""

    def run(c: pd.Series) -> float:
        c = c[c > 0].astype(float)
        return float(np.log2(c.sum()) - (c * np.log2(c)).sum() / c.sum()) if len(c) else 0.0

    run.__annotations__ = {"c": pd.Series, "return": float}  # the kind of function is read from resolved hints
    return pandas_udf(run, "double")


class Neighbours:
    """In-lattice neighbours of a set among ``n`` features."""

    def eval(self, mask: int, n: int):
        on, off = [j for j in range(n) if mask >> j & 1], [j for j in range(n) if not mask >> j & 1]
        for j in range(n):
            if mask ^ 1 << j:
                yield (mask ^ 1 << j, "inter")
        if len(on) > 1:
            for a in on:
                for b in off:
                    yield (mask ^ (1 << a | 1 << b), "intra")


class Nodes:
    """Nodes of a level band."""

    def eval(self, n: int, low: int, high: int):
        for m in range(1, 1 << n):
            if low <= m.bit_count() <= high:
                yield (m, m.bit_count())


def register(spark: SparkSession) -> None:
    """Temporary functions: SQL expressions stay in code generation, table functions do not."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_level(m BIGINT) RETURNS INT RETURN CAST(bit_count(m) AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION mask_part(m BIGINT, w BIGINT) RETURNS BIGINT RETURN m & w")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION set_of(m BIGINT, names ARRAY<STRING>) RETURNS ARRAY<STRING> RETURN filter(names, (x, i) -> (shiftright(m, i) & 1L) = 1L)")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION mask_of(chosen ARRAY<STRING>, names ARRAY<STRING>) RETURNS BIGINT "
        "RETURN aggregate(transform(names, (x, i) -> if(array_contains(chosen, x), shiftleft(1L, i), 0L)), 0L, (a, b) -> a | b)"
    )
    total = "aggregate(flatten(t), 0L, (a, x) -> a + x)"
    part = "CAST(aggregate({}, 0D, (a, x) -> a + if(x > 0, x * log2(x), 0D)) AS DOUBLE)"
    by_row = "transform(t, r -> aggregate(r, 0L, (a, x) -> a + x))"
    by_column = "transform(sequence(0, size(t[0]) - 1), k -> aggregate(t, 0L, (a, r) -> a + r[k]))"
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION joint_mi(t ARRAY<ARRAY<BIGINT>>) RETURNS DOUBLE "
        f"RETURN log2({total}) + ({part.format('flatten(t)')} - {part.format(by_row)} - {part.format(by_column)}) / {total}"
    )
    spark.udtf.register("lattice_neighbours", udtf(Neighbours, returnType="neighbour: long, kind: string"))
    spark.udtf.register("lattice_nodes", udtf(Nodes, returnType="mask: long, level: int"))
