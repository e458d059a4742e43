"""Binning, coding, packing and subgroup assignment: all map-side expressions; what has to
be learned from the data (edges, dictionaries) is at most nine values a feature."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.spec import MAX_STATES, PER_WORD, FeatureSpec, widen


def bin_edges(x: Column, edges: list[float], right_closed: bool = True) -> Column:
    """0 below the first edge up to ``len(edges)`` above the last; null stays null."""
    out = F.lit(len(edges))
    for k in range(len(edges) - 1, -1, -1):
        out = F.when((x <= edges[k]) if right_closed else (x < edges[k]), k).otherwise(out)
    return F.when(x.isNotNull(), out)


def bin_width(df: DataFrame, col: str, k: int) -> DataFrame:
    """Adds ``<col>_bin``: one of ``k`` equal widths of the column's range."""
    low, high = df.agg(F.min(col), F.max(col)).first()
    if low is None or low == high:
        return df.withColumn(f"{col}_bin", F.when(F.col(col).isNotNull(), 0))
    place = F.floor((F.col(col) - F.lit(low)) * k / F.lit(high - low)).cast("int")
    return df.withColumn(f"{col}_bin", F.least(place, F.lit(k - 1)))


def bin_depth(df: DataFrame, col: str, k: int, exact: bool = False, order: str | None = None) -> DataFrame:
    """Adds ``<col>_bin``: equally full bins. The default takes sketched quantiles in one
    pass; ``exact`` ranks all rows (a sort by ``col`` and ``order``) by a range sort and
    offsets of its partitions, not in one task."""
    if not exact:
        cuts = df.agg(F.percentile_approx(col, [i / k for i in range(1, k)], 10_000)).first()[0] or []
        return df.withColumn(f"{col}_bin", bin_edges(F.col(col), [float(c) for c in cuts]))
    return ranked(df, [F.col(col), *([F.col(order)] if order else [])], "__r", "__n").withColumn(f"{col}_bin", tile("__r", "__n", k)).drop("__r", "__n")


def tile(rank: str, total: str, k: int) -> Column:
    """ntile(k) - 1 of a 0-based rank: the first ``total % k`` tiles hold one row more."""
    size, more = F.floor(F.col(total) / k), F.col(total) % k
    head = more * (size + 1)
    return F.when(F.col(rank) < head, F.floor(F.col(rank) / (size + 1))).otherwise(more + F.floor((F.col(rank) - head) / F.greatest(size, F.lit(1)))).cast("int")


def ranked(df: DataFrame, order: list[Column], rank: str, total: str) -> DataFrame:
    """0-based global rank and row count, without a one-task window: a range sort, one
    count per partition, and the offsets of these."""
    from gapselect.plans.durable import durable

    keys = {f"__k{i}": c for i, c in enumerate(order)}
    placed = durable(df.withColumns(keys).repartitionByRange(*[F.col(x) for x in keys]).sortWithinPartitions(*keys).withColumn("__row", F.monotonically_increasing_id()))
    part = F.shiftright("__row", 33)
    sizes = {r[0]: r[1] for r in placed.groupBy(part).count().collect()}  # one number per partition
    start, at = {}, 0
    for p in sorted(sizes):
        start[p], at = at, at + sizes[p]
    offsets = [start.get(p, 0) for p in range(max(sizes, default=0) + 1)]
    out = placed.withColumn(rank, F.get(F.lit(offsets), part.cast("int")) + F.col("__row").bitwiseAND(F.lit((1 << 33) - 1)))
    return out.withColumn(total, F.lit(at)).drop(*keys, "__row")


def cap_categories(df: DataFrame, col: str, max_states: int = MAX_STATES, how: str = "top+rest") -> DataFrame:
    """Adds ``<col>_cap``: at most ``max_states`` codes 1, 2, ...: the most frequent values
    in order (ties by value) and one code for the rest, or bins of values by their rank."""
    counts = df.filter(F.col(col).isNotNull()).groupBy(col).agg(F.count(F.lit(1)).alias("n"))
    if how == "top+rest":
        top = [r[col] for r in counts.orderBy(F.desc("n"), col).limit(max_states).collect()]
        if len(top) == max_states and counts.limit(max_states + 1).count() > max_states:
            top = top[:-1]
        code = F.array_position(F.array(*[F.lit(v) for v in top]), F.col(col)).cast("int")
        return df.withColumn(f"{col}_cap", F.when(F.col(col).isNotNull(), F.when(code > 0, code).otherwise(len(top) + 1)))
    if how != "rank_bins":
        raise ValueError(f"unknown way {how}")
    order = ranked(counts.select(col), [F.col(col)], "__r", "__n")
    few = F.least(F.lit(max_states), F.col("__n"))
    bins = order.select(col, (F.floor(F.col("__r") * few / F.col("__n")) + 1).cast("int").alias(f"{col}_cap"))
    return df.join(bins, col, "left")


#: Values of a column that the sketch of its dictionary tracks.
SKETCH = 160


def dictionaries(df: DataFrame, cols: list[str]) -> dict[str, list]:
    """Sorted distinct values of every column in one pass; more than nine raise. Values are
    kept in a sketch of fixed size, exact while there are few, so a column of many values
    fills neither a task nor the driver before it raises."""
    tops = df.agg(*[F.expr(f"approx_top_k(`{c}`, {SKETCH}, {SKETCH})").alias(c) for c in cols]).first()
    sets = {c: {x["item"] for x in tops[c] or () if x["item"] is not None} for c in cols}
    for c in cols:
        if len(sets[c]) > MAX_STATES:
            raise ValueError(f"{c} has {len(sets[c])}{' or more' * (len(sets[c]) >= SKETCH)} states; bin it to {MAX_STATES} or fewer first")
    return {c: sorted(sets[c]) for c in cols}


def encode(df: DataFrame, spec: FeatureSpec, words: dict[str, list] | None = None) -> DataFrame:
    """sg, features as 1..9 (0 for null) and y as 1..9, other columns dropped."""
    cols = [*spec.features, spec.target]
    words = words or dictionaries(df, cols)

    def code(c: str) -> Column:
        values = F.array(*[F.lit(v) for v in words[c]]) if words[c] else None
        return (F.coalesce(F.array_position(values, F.col(c)), F.lit(0)) if words[c] else F.lit(0)).cast("tinyint")

    return df.select(F.col(spec.group).cast("int").alias("sg"), *[code(c).alias(c) for c in spec.features], code(spec.target).alias("y"))


def pack(coded: DataFrame, spec: FeatureSpec) -> DataFrame:
    """sg, y and the features in two words, four bits each: marginals are one AND."""

    def word(k: int) -> Column:
        mine = spec.features[k * PER_WORD : (k + 1) * PER_WORD]
        shifted = [F.shiftleft(F.col(f).cast("long"), 4 * j) for j, f in enumerate(mine)]
        return reduce(lambda a, b: a.bitwiseOR(b), shifted) if shifted else F.lit(0).cast("long")

    return coded.select("sg", "y", word(0).alias("c0"), word(1).alias("c1"))


def unpack(packed: DataFrame, spec: FeatureSpec) -> DataFrame:
    def code(j: int) -> Column:
        return F.shiftright(F.col(f"c{j // PER_WORD}"), 4 * (j % PER_WORD)).bitwiseAND(F.lit(0xF)).cast("int")

    return packed.select("sg", "y", *[code(j).alias(f) for j, f in enumerate(spec.features)], *[c for c in packed.columns if c not in ("sg", "y", "c0", "c1")])


def hide(packed: DataFrame, missing: dict[int, int]) -> DataFrame:
    """Features of ``missing[sg]`` become null (code 0) in that subgroup."""
    out = packed
    for k in (0, 1):
        keep = F.col(f"c{k}")
        for sg, mask in missing.items():
            keep = F.when(F.col("sg") == sg, F.col(f"c{k}").bitwiseAND(F.lit(~widen(mask)[k]))).otherwise(keep)
        out = out.withColumn(f"c{k}", keep)
    return out


def minterms(df: DataFrame, predicates: list[Column]) -> DataFrame:
    """Adds ``term``: bit i says whether predicate i holds (null counts as not)."""
    bits = [F.when(p, 1 << i).otherwise(0) for i, p in enumerate(predicates)]
    return df.withColumn("term", reduce(lambda a, b: a + b, bits))


def assign_subgroups(df: DataFrame, predicates: list[Column]) -> DataFrame:
    """Adds ``sg``: dense numbers of the minterms that occur (at most ``2**q``)."""
    termed = minterms(df, predicates)
    seen = sorted(r[0] for r in termed.select("term").distinct().collect())
    return termed.withColumn("sg", F.array_position(F.lit(seen), F.col("term")).cast("int") - 1)


def assign_subgroups_by(df: DataFrame, cols: list[str]) -> DataFrame:
    """Adds ``sg``: dense rank of the combinations of grouping columns."""
    combos = ranked(df.select(*cols).distinct(), [F.col(c) for c in cols], "sg", "__n").select(*cols, F.col("sg").cast("int").alias("sg"))
    cond = reduce(lambda a, b: a & b, [df[c].eqNullSafe(combos[c]) for c in cols])
    return df.join(combos, cond, "left").select(df["*"], combos["sg"])


def check_partition(df: DataFrame, predicates: list[Column]) -> DataFrame:
    """rows, rows in no subgroup, rows in several: a partition has 0 and 0."""
    hits = reduce(lambda a, b: a + b, [F.when(p, 1).otherwise(0) for p in predicates])
    return df.select(hits.alias("h")).agg(
        F.count(F.lit(1)).alias("n_rows"), F.count_if(F.col("h") == 0).alias("uncovered"), F.count_if(F.col("h") > 1).alias("overlapping")
    )
