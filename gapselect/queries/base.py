"""Registration of queries with their SQL twins, and SQL fragments that many share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gapselect.operators.prep import encode, hide, pack
from gapselect.plans.durable import durable
from gapselect.spec import FeatureSpec, band
from gapselect.views import SPECS, duck_view, view

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


def r6(x: Column | str) -> Column:
    return F.round(F.col(x) if isinstance(x, str) else x, 6) + F.lit(0.0)


def prepared(spark: SparkSession, sf_dir: str, name: str, n: int | None = None, groups: int | None = None, target: str = "y") -> tuple[DataFrame, FeatureSpec]:
    spec = SPECS[name] if n is None else SPECS[name].head(n)
    spec = FeatureSpec(spec.features, spec.group, target)
    return durable(pack(encode(view(spark, sf_dir, name, groups), spec), spec)), spec


def masked(packed: DataFrame, missing: dict[int, int]) -> DataFrame:
    return hide(packed, missing)


def level(n: int, low: int, high: int) -> list[int]:
    return band(n, low, high)


def mask_sql(features, names: str = "gid") -> str:
    n = len(features)
    return " + ".join(f"CASE WHEN ({names} >> {n - 1 - j}) & 1 = 0 THEN {1 << j} ELSE 0 END" for j in range(n))


def duck_sets(source: str, features: tuple[str, ...], masks: list[int], target: str = "y") -> str:
    """CTEs v, g, s: sums of c log2 c per (sg, mask, gy); gy = 0 with the target, 1 without."""
    sets = ["(sg)", f"(sg, {target})"]
    for m in masks:
        cols = ", ".join(f for j, f in enumerate(features) if m >> j & 1)
        sets += [f"(sg, {cols})", f"(sg, {target}, {cols})"]
    return f"""v AS ({source}),
    g AS (SELECT sg, GROUPING_ID({", ".join(features)}) AS gid, GROUPING({target}) AS gy, count(*) AS c FROM v GROUP BY GROUPING SETS ({", ".join(sets)})),
    s AS (SELECT sg, CAST({mask_sql(features)} AS BIGINT) AS mask, gy, sum(c * log2(c)) AS s, CAST(sum(c) AS BIGINT) AS n, count(*) AS cells FROM g GROUP BY sg, gid, gy)"""


def duck_mi(source: str, features: tuple[str, ...], masks: list[int], target: str = "y") -> str:
    """The same and m (sg, mask, level, mi, n, ...)."""
    return duck_sets(source, features, masks, target) + """,
    m AS (SELECT f.sg, f.mask, CAST(bit_count(f.mask) AS INTEGER) AS level, greatest(0.0, log2(f.n) + (b.s - f.s - y.s) / f.n) AS mi, f.n, f.s AS s_f, b.s AS s_fy, y.s AS s_y,
                 f.cells AS cells_f, b.cells AS cells_fy, y.cells AS cells_y
          FROM s f JOIN s b ON f.sg = b.sg AND f.mask = b.mask AND b.gy = 0 JOIN s y ON f.sg = y.sg AND y.mask = 0 AND y.gy = 0
          WHERE f.gy = 1 AND f.mask > 0)"""


def duck_hidden(name: str, missing: dict[int, int], features: tuple[str, ...], groups: int | None = None) -> str:
    """The view with planted missing features as nulls."""
    cols = []
    for j, f in enumerate(features):
        gone = [str(g) for g, m in missing.items() if m >> j & 1]
        cols.append(f"CASE WHEN sg IN ({', '.join(gone)}) THEN NULL ELSE {f} END AS {f}" if gone else f)
    return f"SELECT sg, y, {', '.join(cols)} FROM ({duck_view(name, groups)})"


def lacking_sql(missing: dict[int, int]) -> str:
    return "CASE " + " ".join(f"WHEN sg = {g} THEN {m}" for g, m in missing.items()) + " ELSE 0 END"


def duck_topk(k: int, score: str = "mi", source: str = "m", where: str = "true") -> str:
    return f"""SELECT sg, CAST(rank AS INTEGER) AS rank, mask, round({score}, 6) + 0.0 AS score FROM (
        SELECT *, row_number() OVER (PARTITION BY sg ORDER BY round({score}, 9) DESC, mask) AS rank FROM {source} WHERE {where}) WHERE rank <= {k}"""


def shown_topk(df: DataFrame) -> DataFrame:
    return df.select("sg", F.col("rank").cast("int").alias("rank"), "mask", r6("score").alias("score"))
