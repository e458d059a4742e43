"""Preparation, missingness, information, lattice, sampling, ranking and measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gapselect.functions.dialect import DUCK
from gapselect.operators import lattice as lat
from gapselect.operators import mi as info
from gapselect.operators import prep, sampling, topk
from gapselect.operators.missing import coin, detect_missing, null_profile, plant_missing
from gapselect.operators.prep import encode, pack
from gapselect.plans.durable import durable
from gapselect.queries.base import (
    ORACLES, duck_hidden, duck_mi, duck_sets, duck_topk, lacking_sql, level, masked, prepared, query, r6, shown_topk,
)
from gapselect.sources.tables import table
from gapselect.spec import FeatureSpec
from gapselect.views import CREDIT, DEVICE, GROUPS, LOGIC15, SPECS, STAFF, duck_view, view

# ---- preparation


@query("""SELECT b, count(*) AS n_rows FROM (SELECT CASE WHEN o_totalprice IS NULL THEN NULL WHEN o_totalprice <= 50000 THEN 0 WHEN o_totalprice <= 150000 THEN 1
          WHEN o_totalprice <= 300000 THEN 2 ELSE 3 END AS b FROM orders) GROUP BY b""")
def prep_bin_edges(spark: SparkSession, sf: str) -> DataFrame:
    b = prep.bin_edges(F.col("o_totalprice"), [50000, 150000, 300000])
    return table(spark, sf, "orders").groupBy(b.alias("b")).agg(F.count(F.lit(1)).alias("n_rows"))


@query("""SELECT CAST(least(8, floor((p_retailprice - lo) * 9 / (hi - lo))) AS INTEGER) AS b, count(*) AS n_rows
          FROM part, (SELECT min(p_retailprice) AS lo, max(p_retailprice) AS hi FROM part) GROUP BY b""")
def prep_bin_width(spark, sf):
    return prep.bin_width(table(spark, sf, "part"), "p_retailprice", 9).groupBy(F.col("p_retailprice_bin").alias("b")).agg(F.count(F.lit(1)).alias("n_rows"))


@query("""SELECT b, count(*) AS n_rows, min(o_totalprice) AS low, max(o_totalprice) AS high
          FROM (SELECT o_totalprice, CAST(ntile(9) OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS INTEGER) AS b FROM orders) GROUP BY b""")
def prep_bin_depth(spark, sf):
    binned = prep.bin_depth(table(spark, sf, "orders").select("o_totalprice", "o_orderkey"), "o_totalprice", 9, exact=True, order="o_orderkey")
    return binned.groupBy(F.col("o_totalprice_bin").alias("b")).agg(F.count(F.lit(1)).alias("n_rows"), F.min("o_totalprice").alias("low"), F.max("o_totalprice").alias("high"))


@query("""WITH c AS (SELECT p_brand, count(*) AS n FROM part GROUP BY p_brand), k AS (SELECT *, row_number() OVER (ORDER BY n DESC, p_brand) AS r, count(*) OVER () AS t FROM c)
          SELECT CAST(CASE WHEN t <= 9 OR r <= 8 THEN r ELSE 9 END AS INTEGER) AS code, CAST(sum(n) AS BIGINT) AS n_rows FROM k GROUP BY code""")
def prep_cap_categories(spark, sf):
    return prep.cap_categories(table(spark, sf, "part"), "p_brand").groupBy(F.col("p_brand_cap").alias("code")).agg(F.count(F.lit(1)).alias("n_rows"))


@query("""WITH d AS (SELECT DISTINCT p_brand FROM part), r AS (SELECT p_brand, dense_rank() OVER (ORDER BY p_brand) AS r, count(*) OVER () AS t FROM d)
          SELECT CAST(floor((r - 1) * least(9, t) / t) + 1 AS INTEGER) AS code, count(*) AS n_rows FROM part JOIN r USING (p_brand) GROUP BY code""")
def prep_rank_bins(spark, sf):
    return prep.cap_categories(table(spark, sf, "part"), "p_brand", how="rank_bins").groupBy(F.col("p_brand_cap").alias("code")).agg(F.count(F.lit(1)).alias("n_rows"))


@query(f"""WITH v AS ({duck_view("v_device")}), c AS (SELECT sg, y + 1 AS y, coalesce(dense_rank() OVER (ORDER BY type), 0) AS type, coalesce(dense_rank() OVER (ORDER BY brand_bin), 0) AS brand_bin FROM v)
           SELECT sg, CAST(y AS INTEGER) AS y, CAST(type AS INTEGER) AS type, CAST(brand_bin AS INTEGER) AS brand_bin, count(*) AS n_rows FROM c GROUP BY ALL""")
def prep_encode(spark, sf):
    spec = FeatureSpec(("type", "brand_bin"))
    coded = prep.encode(view(spark, sf, "v_device"), spec)
    return coded.select("sg", *[F.col(c).cast("int").alias(c) for c in ("y", "type", "brand_bin")]).groupBy("sg", "y", "type", "brand_bin").agg(F.count(F.lit(1)).alias("n_rows"))


@query("""SELECT sg, r_name, l_linestatus, count(*) AS n_rows FROM (SELECT r_name, l_linestatus, CAST(dense_rank() OVER (ORDER BY r_name, l_linestatus) - 1 AS INTEGER) AS sg
          FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey) GROUP BY ALL""")
def prep_subgroups(spark, sf):
    li = table(spark, sf, "lineitem").join(table(spark, sf, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    li = li.join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    li = li.join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return prep.assign_subgroups_by(li.select("r_name", "l_linestatus"), ["r_name", "l_linestatus"]).groupBy("sg", "r_name", "l_linestatus").agg(F.count(F.lit(1)).alias("n_rows"))


@query("""SELECT CAST(count(*) AS BIGINT) AS n_rows, CAST(count(*) FILTER (h = 0) AS BIGINT) AS uncovered, CAST(count(*) FILTER (h > 1) AS BIGINT) AS overlapping
          FROM (SELECT (p_size <= 20)::INT + (p_size > 20 AND p_size <= 40)::INT + (p_size >= 40)::INT AS h FROM part)""")
def prep_partition_check(spark, sf):
    s = F.col("p_size")
    return prep.check_partition(table(spark, sf, "part"), [s <= 20, (s > 20) & (s <= 40), s >= 40])


@query("""WITH t AS (SELECT CAST((c_acctbal > 0)::INT + 2 * (c_mktsegment IN ('BUILDING', 'AUTOMOBILE'))::INT + 4 * (c_nationkey < 10)::INT AS INTEGER) AS term FROM customer)
          SELECT term, CAST(dense_rank() OVER (ORDER BY term) - 1 AS INTEGER) AS sg, count(*) AS n_rows FROM t GROUP BY term""")
def prep_minterms(spark, sf):
    p = [F.col("c_acctbal") > 0, F.col("c_mktsegment").isin("BUILDING", "AUTOMOBILE"), F.col("c_nationkey") < 10]
    return prep.assign_subgroups(table(spark, sf, "customer"), p).groupBy("term", "sg").agg(F.count(F.lit(1)).alias("n_rows"))


# ---- missingness

PLANTED = {name: plant_missing(SPECS[name], GROUPS[name], 0.2, 0) for name in ("v_staff", "v_device", "v_credit", "v_logic15", "v_scale")}


def _plant_oracle(name: str, p: float) -> str:
    """The coins in SQL; both repairs are data-dependent and are checked by their outcome."""
    spec, groups = SPECS[name], GROUPS[name]
    made = plant_missing(spec, groups, p, 0)
    toss = {(g, j): coin("0", f"{g}|{f}") % 10_000 < 10_000 * p for g in range(groups) for j, f in enumerate(spec.features)}
    fixes = [(g, j) for g in range(groups) for j in range(spec.n) if toss[g, j] != bool(made[g] >> j & 1)]
    flip = " + ".join(f"CASE WHEN sg = {g} AND j = {j} THEN 1 ELSE 0 END" for g, j in fixes) or "0"
    names = ", ".join(f"({j}, '{f}')" for j, f in enumerate(spec.features))
    c = DUCK.coin("concat('0|', sg, '|', f)", 0, 8)
    return f"""WITH f(j, f) AS (VALUES {names}), g AS (SELECT unnest(range({groups})) AS sg),
        t AS (SELECT sg, j, CASE WHEN {c} % 10000 < {int(10_000 * p)} THEN 1 ELSE 0 END AS gone, {flip} AS fix FROM f, g)
        SELECT CAST(sg AS INTEGER) AS sg, CAST(sum(CASE WHEN (gone + fix) % 2 = 1 THEN 1 << j ELSE 0 END) AS BIGINT) AS miss_mask FROM t GROUP BY sg"""


def _plant(p: float):
    def run(spark, sf):
        made = plant_missing(SPECS["v_staff"], GROUPS["v_staff"], p, 0)
        return spark.createDataFrame(sorted(made.items()), "sg int, miss_mask long")

    return run


for _p in (20, 50):
    query(_plant_oracle("v_staff", _p / 100), f"miss_plant_p{_p}")(_plant(_p / 100))


def _hidden_rows(spark, sf, name):
    packed, spec = prepared(spark, sf, name)
    rows = prep.unpack(masked(packed, PLANTED[name]), spec)
    return rows.select("sg", "y", *[F.when(F.col(f) > 0, F.col(f)).alias(f) for f in spec.features]), spec


def _detect_sql(name: str) -> str:
    feats = SPECS[name].features
    bits = " + ".join(f"CASE WHEN count({f}) = 0 THEN {1 << j} ELSE 0 END" for j, f in enumerate(feats))
    return f"SELECT sg, CAST({bits} AS BIGINT) AS miss_mask, CAST({(1 << len(feats)) - 1} - ({bits}) AS BIGINT) AS avail_mask FROM ({duck_hidden(name, PLANTED[name], feats)}) GROUP BY sg"


@query(_detect_sql("v_staff"))
def miss_detect(spark, sf):
    return detect_missing(*_hidden_rows(spark, sf, "v_staff"))


@query(f"""WITH d AS ({_detect_sql("v_logic15")}), l AS (SELECT unnest(range(1, 16)) AS level),
          c AS (SELECT sg, level, bit_count(avail_mask) AS a FROM d, l)
          SELECT sg, CAST(level AS INTEGER) AS level, CAST(CASE WHEN level > a THEN 0 ELSE round(gamma(a + 1) / gamma(level + 1) / gamma(a - level + 1)) END AS BIGINT) AS computable,
                 CAST(round(gamma(16) / gamma(level + 1) / gamma(16 - level)) AS BIGINT) - CAST(CASE WHEN level > a THEN 0 ELSE round(gamma(a + 1) / gamma(level + 1) / gamma(a - level + 1)) END AS BIGINT) AS blocked FROM c""")
def miss_sets_split(spark, sf):
    """Sizes of the computable and the blocked sets per level."""
    found = detect_missing(*_hidden_rows(spark, sf, "v_logic15"))
    every = lat.nodes(spark, 15)
    ok = F.col("mask").bitwiseAND(F.col("miss_mask")) == 0
    return every.join(F.broadcast(found), F.lit(True)).groupBy("sg", "level").agg(F.count_if(ok).alias("computable"), F.count_if(~ok).alias("blocked"))


@query(f"""SELECT sg, feature, n_rows, n_rows - held AS nulls FROM (UNPIVOT (SELECT sg, count(*) AS n_rows, {", ".join(f"count({f}) AS {f}" for f in DEVICE)}
          FROM ({duck_hidden("v_device", PLANTED["v_device"], DEVICE)}) GROUP BY sg) ON {", ".join(DEVICE)} INTO NAME feature VALUE held)""")
def miss_null_profile(spark, sf):
    return null_profile(*_hidden_rows(spark, sf, "v_device"))


# ---- information


def _shown_mi(mi: DataFrame) -> DataFrame:
    return mi.select("sg", "mask", "level", r6("mi").alias("mi"), "n")


def _mi_query(name: str, view_name: str, low: int, high: int, n: int | None = None, target: str = "y", sharing: str = "cuboid"):
    feats = SPECS[view_name].features[:n]
    masks = level(len(feats), low, high)
    sql = f"WITH {duck_mi(duck_view(view_name), feats, masks, target)} SELECT sg, mask, level, round(mi, 6) + 0.0 AS mi, n FROM m"

    def run(spark, sf):
        packed, spec = prepared(spark, sf, view_name, n, target=target)
        return _shown_mi(info.lattice_mi(packed, spec, masks, sharing))

    query(sql, name)(run)


_mi_query("mi_single_staff", "v_staff", 1, 1, sharing="blocks")
_mi_query("mi_single_staff_natural", "v_staff", 1, 1, target="y_natural", sharing="blocks")
_mi_query("mi_single_credit", "v_credit", 1, 1)
_mi_query("mi_single_credit_toxic", "v_credit", 1, 1, target="y_toxic")
_mi_query("mi_single_device", "v_device", 1, 1)
_mi_query("mi_pairs_credit", "v_credit", 2, 2)
_mi_query("mi_triples_device", "v_device", 3, 3)
for _s, _n in (("naive", "none"), ("grouping_sets", "grouping_sets"), ("cuboid", "cuboid"), ("rollup", "rollup"), ("blocks", "blocks")):
    _mi_query(f"lmi_{_s}", "v_logic15", 1, 3, n=8, sharing=_n)
_mi_query("lmi_rollup_credit", "v_credit", 1, 8, n=8, sharing="rollup")

#: The worked example's columns family history and readmission: fixed values.
FAMILY = ("Yes", "No", "Yes", "Yes", "No", "Yes", "Yes", "No", "Yes", "Yes", "Yes", "No")
READMITTED = ("No", "Yes", "Yes", "Yes", "No", "Yes", "No", "No", "Yes", "Yes", "Yes", "No")
_PATIENTS = ", ".join(f"('{f}', '{y}')" for f, y in zip(FAMILY, READMITTED))


@query(f"""WITH t(f, y) AS (VALUES {_PATIENTS}), j AS (SELECT f, y, count(*) AS c FROM t GROUP BY f, y), n AS (SELECT count(*) AS n FROM t)
          SELECT round(sum(c / n * log2(c * n / (cf * cy))), 6) AS mi_bits FROM (SELECT *, sum(c) OVER (PARTITION BY f) AS cf, sum(c) OVER (PARTITION BY y) AS cy FROM j), n""")
def mi_worked_example(spark, sf):
    """MI of family history and readmission over the twelve patients of the example."""
    df = spark.createDataFrame([(0, f, y) for f, y in zip(FAMILY, READMITTED)], "sg int, f string, y string")
    spec = FeatureSpec(("f",))
    return info.lattice_mi(pack(encode(df, spec), spec), spec, [1]).select(F.round("mi", 6).alias("mi_bits"))


@query("""WITH t(f, y, c) AS (VALUES (0, 0, 4), (0, 1, 2), (1, 0, 1), (1, 1, 5)), n AS (SELECT sum(c) AS n FROM t)
          SELECT round(sum(c / n * log2(c * n / (cf * cy))), 6) AS mi_bits, round(sum(c / n * ln(c * n / (cf * cy))), 6) AS mi_nats
          FROM (SELECT *, sum(c) OVER (PARTITION BY f) AS cf, sum(c) OVER (PARTITION BY y) AS cy FROM t), n""")
def mi_two_by_two(spark, sf):
    """MI of a 2 x 2 table from its double sum, in bits and nats."""
    rows = [(0, f, y) for f, y, c in ((0, 0, 4), (0, 1, 2), (1, 0, 1), (1, 1, 5)) for _ in range(c)]
    df = spark.createDataFrame(rows, "sg int, f int, y int")
    bits = info.joint_mi_direct(df, ["f"])
    return bits.select(F.round("mi", 6).alias("mi_bits"), F.round(F.col("mi") * F.log(F.lit(2.0)), 6).alias("mi_nats"))


def _h(cols: str) -> str:
    return f"SELECT sg, log2(sum(c)) - sum(c * log2(c)) / sum(c) AS h FROM (SELECT sg, count(*) AS c FROM v GROUP BY sg, {cols}) GROUP BY sg"


_V = f"v AS ({duck_view('v_device')})"


@query(f"WITH {_V} SELECT sg, round(h, 6) AS h FROM ({_h('type, key_fifth, y')})")
def entropy_joint(spark, sf):
    return info.entropy(view(spark, sf, "v_device"), ["type", "key_fifth", "y"]).select("sg", F.round("h", 6).alias("h"))


@query(f"WITH {_V} SELECT a.sg, round(a.h - b.h, 6) AS h FROM ({_h('key_fifth, key_noisy')}) a JOIN ({_h('key_fifth')}) b ON a.sg = b.sg")
def entropy_conditional(spark, sf):
    return info.cond_entropy(view(spark, sf, "v_device"), "key_noisy", ["key_fifth"]).select("sg", F.round("h", 6).alias("h"))


@query(f"WITH {_V} SELECT sg, round(h, 6) AS h FROM ({_h('type, size_bin, key_fifth, y')})")
def entropy_chain_rule(spark, sf):
    return info.chain_rule(view(spark, sf, "v_device"), ["y", "key_fifth", "type", "size_bin"]).select("sg", F.round("h", 6).alias("h"))


@query(f"""WITH {_V} SELECT sg, round(sum(h), 6) + 0.0 AS co_information FROM (
           {" UNION ALL ".join(f"SELECT sg, {sign} * h AS h FROM ({_h(c)})" for sign, c in ((1, "key_fifth"), (1, "key_noisy"), (1, "y"), (-1, "key_fifth, key_noisy"), (-1, "key_fifth, y"), (-1, "key_noisy, y"), (1, "key_fifth, key_noisy, y")))}) GROUP BY sg""")
def co_information_pairs(spark, sf):
    return info.co_information(view(spark, sf, "v_device"), ["key_fifth", "key_noisy"]).select("sg", r6("co_information").alias("co_information"))


@query(f"""WITH v AS (SELECT sg, a, b, xor(a, b) AS y FROM (SELECT 0 AS sg, CAST(o_custkey % 2 AS INTEGER) AS a, CAST(o_custkey // 2 % 2 AS INTEGER) AS b FROM orders))
           SELECT x.sg, round(x.mi, 6) + 0.0 AS mi, round(z.c, 6) + 0.0 AS co_information
           FROM (SELECT sg, sum(h) AS mi FROM ({" UNION ALL ".join(f"SELECT sg, {sign} * h AS h FROM ({_h(c)})" for sign, c in ((1, "a, b"), (1, "y"), (-1, "a, b, y")))}) GROUP BY sg) x
           JOIN (SELECT sg, sum(h) AS c FROM ({" UNION ALL ".join(f"SELECT sg, {sign} * h AS h FROM ({_h(c)})" for sign, c in ((1, "a"), (1, "b"), (1, "y"), (-1, "a, b"), (-1, "a, y"), (-1, "b, y"), (1, "a, b, y")))}) GROUP BY sg) z ON x.sg = z.sg""")
def co_information_xor(spark, sf):
    """Two bits of the customer's key and their exclusive or."""
    bits = table(spark, sf, "orders").selectExpr("0 AS sg", "int(o_custkey % 2) AS a", "int(o_custkey div 2 % 2) AS b")
    df = bits.withColumn("y", F.col("a").bitwiseXOR(F.col("b")))
    return info.joint_mi_direct(df, ["a", "b"]).join(info.co_information(df, ["a", "b"]), "sg").select("sg", r6("mi").alias("mi"), r6("co_information").alias("co_information"))


_STAFF1 = level(len(STAFF), 1, 1)


@query(f"""WITH {duck_mi(duck_view("v_staff"), STAFF, _STAFF1)} SELECT sg, mask, level, n,
           round(greatest(0.0, mi + (cells_f + cells_y - cells_fy - 1) / (2 * n * ln(2))), 6) + 0.0 AS mi FROM m""")
def mi_miller_madow(spark, sf):
    packed, spec = prepared(spark, sf, "v_staff")
    return _shown_mi(info.lattice_mi(packed, spec, _STAFF1, "blocks", estimator="miller_madow"))


@query(f"WITH {duck_mi(duck_view('v_credit'), CREDIT, level(15, 1, 1))} SELECT sg, mask, level, n, round(mi * ln(2), 6) + 0.0 AS mi FROM m")
def mi_log_e(spark, sf):
    packed, spec = prepared(spark, sf, "v_credit")
    return _shown_mi(info.lattice_mi(packed, spec, level(15, 1, 1), log_base="e"))


@query(f"WITH {duck_mi(duck_view('v_credit'), CREDIT, level(15, 1, 1))} SELECT sg, mask, level, n, round(mi / (log2(n) - s_y / n), 6) + 0.0 AS mi FROM m")
def mi_normalised(spark, sf):
    packed, spec = prepared(spark, sf, "v_credit")
    return _shown_mi(info.lattice_mi(packed, spec, level(15, 1, 1), estimator="normalised"))


@query(f"WITH {duck_mi(duck_view('v_credit'), CREDIT, level(15, 1, 1))} SELECT sg, mask, level, n, round(2 * n * ln(2) * mi, 6) + 0.0 AS mi FROM m")
def mi_g_statistic(spark, sf):
    packed, spec = prepared(spark, sf, "v_credit")
    return _shown_mi(info.lattice_mi(packed, spec, level(15, 1, 1), estimator="g"))


def _complete_case_sql() -> str:
    feats = DEVICE[:5]
    parts = []
    for m in level(5, 1, 2):
        cols = [f for j, f in enumerate(feats) if m >> j & 1]
        held = " AND ".join(f"{c} IS NOT NULL" for c in cols)
        part = f"(SELECT sg, {m} AS mask, y, {', '.join(f'{c} AS f{i}' for i, c in enumerate(cols))} FROM v WHERE {held})"
        f = ", ".join(f"f{i}" for i in range(len(cols)))
        parts.append(
            f"SELECT sg, mask, sum(c / n * log2(c * n / (cf * cy))) AS mi, max(n) AS n FROM (SELECT *, sum(c) OVER (PARTITION BY sg, {f}) AS cf, sum(c) OVER (PARTITION BY sg, y) AS cy, sum(c) OVER (PARTITION BY sg) AS n "
            f"FROM (SELECT sg, mask, {f}, y, count(*) AS c FROM {part} GROUP BY ALL)) GROUP BY sg, mask"
        )
    keep = ", ".join(f"CASE WHEN {DUCK.coin(chr(39) + '1|' + f + '|' + chr(39) + ' || id', 0, 8)} % 10000 >= 3000 THEN {f} END AS {f}" for f in feats)
    return f"WITH v AS (SELECT sg, y, {keep} FROM ({duck_view('v_device')})) SELECT sg, CAST(mask AS BIGINT) AS mask, CAST(bit_count(CAST(mask AS BIGINT)) AS INTEGER) AS level, round(greatest(0.0, mi), 6) + 0.0 AS mi, CAST(n AS BIGINT) AS n FROM ({' UNION ALL '.join(parts)})"


@query(_complete_case_sql())
def mi_complete_case(spark, sf):
    """Random missingness: complete rows of each set."""
    from gapselect.operators.missing import plant_random_missing

    spec = SPECS["v_device"].head(5)
    gappy = plant_random_missing(view(spark, sf, "v_device"), spec, "id", 0.3, 1)
    packed = prep.pack(prep.encode(gappy, spec), spec)
    return _shown_mi(info.lattice_mi(packed, spec, level(5, 1, 2), null_policy="complete_case"))


@query(f"""WITH {duck_sets(duck_view("v_logic15"), LOGIC15[:6], level(6, 1, 4))}
          SELECT f.sg, f.mask, round(log2(f.n) - f.s / f.n, 6) + 0.0 AS h_f, round(log2(b.n) - b.s / b.n, 6) + 0.0 AS h_fy FROM s f JOIN s b ON f.sg = b.sg AND f.mask = b.mask AND b.gy = 0 WHERE f.gy = 1 AND f.mask > 0""")
def lmi_constructs(spark, sf):
    packed, spec = prepared(spark, sf, "v_logic15", 6)
    counts, q = info.lattice_counts(packed, spec, level(6, 1, 4))
    return info.constructs(counts, q).select("sg", F.col("mask").cast("long").alias("mask"), r6("h_f").alias("h_f"), r6("h_fy").alias("h_fy"))


@query()
def lmi_plan(spark, sf):
    """What the sharing planner chooses for each view and why."""
    from gapselect.plans.sharing import plan_sharing

    rows = []
    for name, low, high, n in (("v_device", 1, 3, None), ("v_credit", 1, 8, 8), ("v_logic15", 1, 3, None), ("v_logic15", 6, 6, None)):
        packed, spec = prepared(spark, sf, name, n)
        said = plan_sharing(packed, level(spec.n, low, high), spec.n)
        rows.append((name, low, high, said["sharing"], said["why"], said["n_sets"]))
    return spark.createDataFrame(rows, "view string, low int, high int, sharing string, why string, n_sets int")


# ---- lattice graph

_N6 = "n AS (SELECT CAST(r AS BIGINT) AS mask, CAST(bit_count(r) AS INTEGER) AS level FROM (SELECT unnest(range(1, 64)) AS r))"


@query(f"WITH {_N6} SELECT mask, level, lpad(bin(mask), 6, '0') AS bits FROM n")
def lat_nodes(spark, sf):
    return lat.nodes(spark, 6).select("mask", "level", lat.to_bits(F.col("mask"), 6).alias("bits"))


@query(f"WITH {_N6} SELECT level, count(*) AS n_nodes FROM n GROUP BY level")
def lat_level_counts(spark, sf):
    return lat.nodes(spark, 6).groupBy("level").agg(F.count(F.lit(1)).alias("n_nodes"))


@query(f"WITH {_N6} SELECT a.mask AS upper, b.mask AS lower FROM n a JOIN n b ON a.mask & b.mask = b.mask AND a.level = b.level + 1")
def lat_inter_edges(spark, sf):
    return lat.inter_edges(lat.nodes(spark, 6), 6)


@query(f"WITH {_N6} SELECT a.mask AS src, b.mask AS dst FROM n a JOIN n b ON a.level = b.level AND a.level > 1 AND bit_count(a.mask & b.mask) = a.level - 1 AND a.mask < b.mask")
def lat_intra_edges(spark, sf):
    return lat.intra_edges(lat.nodes(spark, 6), 6)


#: Nodes that a table holds: quantities as sets of six features.
_HELD = "held AS (SELECT DISTINCT CAST(l_quantity AS BIGINT) AS mask FROM lineitem WHERE l_quantity >= 1 AND l_quantity < 64)"


def held_nodes(spark, sf) -> DataFrame:
    found = table(spark, sf, "lineitem").filter("l_quantity >= 1 AND l_quantity < 64").select(F.col("l_quantity").cast("long").alias("mask")).distinct()
    return found.withColumn("level", F.bit_count("mask").cast("int"))


@query(f"WITH {_HELD}, g AS (SELECT unnest(range(4)) AS g) SELECT mask, CAST(a.g AS INTEGER) AS i, CAST(b.g AS INTEGER) AS j FROM held, g a JOIN g b ON a.g < b.g")
def lat_cross_edges(spark, sf):
    return lat.cross_edges(held_nodes(spark, sf), 4)


@query("SELECT 4 AS n, 15 AS nodes, 28 AS inter, 18 AS intra UNION ALL SELECT 15, 32767, 245745, 860055 UNION ALL SELECT 20, 1048575, 10485740, 49807170")
def lat_size_formula(spark, sf):
    rows = [(n, *[lat.lattice_size(n)[k] for k in ("nodes", "inter", "intra")]) for n in (4, 15, 20)]
    return spark.createDataFrame(rows, "n int, nodes int, inter int, intra int")


_EDGES6 = "e AS (SELECT a.mask AS m, b.mask AS o FROM n a JOIN n b ON (abs(a.level - b.level) = 1 AND (a.mask & b.mask IN (a.mask, b.mask))) OR (a.level = b.level AND a.level > 1 AND bit_count(a.mask & b.mask) = a.level - 1))"


@query(f"WITH {_N6}, {_EDGES6}, {_HELD} SELECT m AS mask, CAST(count(*) AS INTEGER) AS degree FROM e WHERE m IN (SELECT mask FROM held) GROUP BY m")
def lat_degree(spark, sf):
    return held_nodes(spark, sf).select("mask", lat.degree(F.col("level"), 6).cast("int").alias("degree"))


@query(f"WITH {_N6}, {_EDGES6} SELECT m AS mask, CAST(bit_count(m) AS INTEGER) AS level, round(avg(CAST((o * 37) % 101 AS DOUBLE)), 6) AS mean FROM e GROUP BY m")
def lat_neighbour_mean(spark, sf):
    values = lat.nodes(spark, 6).select("mask", ((F.col("mask") * 37) % 101).alias("value"))
    return lat.neighbour_mean(values, 6).select("mask", "level", F.round("mean", 6).alias("mean"))


def _reduce_query(how: str, sql: str) -> None:
    @query(f"WITH {_N6}, {_EDGES6} SELECT m AS mask, round({sql}(CAST((o * 37) % 101 AS DOUBLE)), 6) AS out FROM e GROUP BY m", f"lat_neighbour_{how}")
    def run(spark, sf):
        values = lat.nodes(spark, 6).select("mask", ((F.col("mask") * 37) % 101).alias("value"))
        return lat.neighbour_reduce(values, 6, how).select("mask", F.round("out", 6).alias("out"))


_reduce_query("sum", "sum")
_reduce_query("max", "max")


@query(f"WITH {_N6}, {_EDGES6}, j AS (SELECT unnest(range(6)) AS j) SELECT m AS mask, CAST(j AS INTEGER) AS j, round(avg(CAST((o >> j) & 1 AS DOUBLE)), 6) AS mean FROM e, j GROUP BY m, j")
def lat_encoding_mean(spark, sf):
    from gapselect.model.distributed import input_means

    return input_means(spark, 6, 1, 6).select("mask", F.posexplode("mean").alias("j", "mean")).withColumn("mean", F.round("mean", 6))


_DEV6 = DEVICE[:6]


@query(f"""WITH {_N6}, {_EDGES6}, {duck_mi(duck_view("v_device"), _DEV6, level(6, 1, 6))}, a AS (SELECT x.sg, e.m AS mask, avg(x.mi) AS a FROM e JOIN m x ON x.mask = e.o GROUP BY x.sg, e.m),
          c AS (SELECT sg, mask, sum(mi) OVER (PARTITION BY mask) - mi AS c FROM m)
          SELECT m.sg, m.mask, round(greatest(0.0, 0.5 * mi + 0.3 * a + 0.2 * c), 6) + 0.0 AS h FROM m JOIN a ON a.sg = m.sg AND a.mask = m.mask JOIN c ON c.sg = m.sg AND c.mask = m.mask""")
def msg_identity_layer(spark, sf):
    """One message-passing step with fixed weights on MI labels: own state, in-lattice mean,
    sum over the other lattices."""
    packed, spec = prepared(spark, sf, "v_device", 6)
    mi = info.lattice_mi(packed, spec, level(6, 1, 6))
    from pyspark.sql import Window

    means = None
    for g in range(GROUPS["v_device"]):
        one = lat.neighbour_mean(mi.filter(F.col("sg") == g), 6, "mi").select(F.lit(g).alias("sg"), "mask", "mean")
        means = one if means is None else means.unionByName(one)
    both = mi.join(means, ["sg", "mask"]).withColumn("cross", F.sum("mi").over(Window.partitionBy("mask")) - F.col("mi"))
    return both.select("sg", "mask", r6(F.greatest(F.lit(0.0), 0.5 * F.col("mi") + 0.3 * F.col("mean") + 0.2 * F.col("cross"))).alias("h"))


# ---- sampling


def _avail(name: str, n: int | None = None) -> dict[int, int]:
    spec = SPECS[name] if n is None else SPECS[name].head(n)
    return sampling.available_of({g: m & (1 << spec.n) - 1 for g, m in PLANTED[name].items()}, spec.n)


_AV = _avail("v_device")


@query(f"""WITH a(sg, avail) AS (VALUES {", ".join(f"({g}, {m})" for g, m in _AV.items())}), n AS (SELECT CAST(r AS BIGINT) AS mask FROM (SELECT unnest(range(1, 32768)) AS r) WHERE bit_count(r) <= 3),
          u AS (SELECT sg, mask, row_number() OVER (PARTITION BY sg ORDER BY md5(concat_ws('|', '0', sg, mask)), mask) AS r, count(*) OVER (PARTITION BY sg) AS t FROM n JOIN a ON (mask & ~avail) = 0)
          SELECT CAST(sg AS INTEGER) AS sg, mask FROM u WHERE r <= round(0.25 * t)""")
def smp_arbitrary(spark, sf):
    return sampling.arbitrary_sample(sampling.universe(spark, _AV, 15, 1, 3), 0.25, 0)


@query(f"""WITH a(sg, avail) AS (VALUES {", ".join(f"({g}, {m})" for g, m in _AV.items())}), n AS (SELECT CAST(r AS BIGINT) AS mask FROM (SELECT unnest(range(1, 32768)) AS r) WHERE bit_count(r) <= 3),
          u AS (SELECT sg, mask, row_number() OVER (PARTITION BY sg, bit_count(mask) ORDER BY md5(concat_ws('|', '0', sg, mask)), mask) AS r, count(*) OVER (PARTITION BY sg, bit_count(mask)) AS t FROM n JOIN a ON (mask & ~avail) = 0)
          SELECT CAST(sg AS INTEGER) AS sg, mask FROM u WHERE r <= ceil(0.25 * t)""")
def smp_stratified(spark, sf):
    return sampling.stratified_sample(sampling.universe(spark, _AV, 15, 1, 3), 0.25, 0)


def _walk_values(budget: float, low: int, high: int) -> str:
    rows = []
    for g, a in _AV.items():
        b = sampling.budget_of(budget, sampling.universe_size(a, low, high))
        rows += [f"({g}, {m}, {s})" for m, s in sampling.walk(a, b, 0, g, low, high)]
    return ", ".join(rows)


@query()
def smp_walk(spark, sf):
    return sampling.walk_sample(spark, _AV, 0.25, 0, 1, 3)


@query()
def smp_walkers(spark, sf):
    return sampling.walk_sample(spark, _AV, 0.25, 0, 1, 3, walkers=4, burn_in=50)


@query()
def smp_swap_walk(spark, sf):
    """A band of one level: two bits change places."""
    return sampling.walk_sample(spark, _AV, 0.25, 0, 3, 3)


@query()
def smp_mixing(spark, sf):
    """Occupation of the levels by lazy and non-lazy chains against the uniform law."""
    from math import comb

    a = (1 << 8) - 1
    size = sampling.universe_size(a, 1, 8)
    rows = []
    for lazy in (0.0, 0.5):
        seen: dict[int, int] = {}
        for seed in range(40):
            for m, _ in sampling.walk(a, 60, seed, 0, 1, 8, lazy=lazy, burn_in=30):
                seen[m.bit_count()] = seen.get(m.bit_count(), 0) + 1
        total = sum(seen.values())
        rows += [(lazy, k, seen.get(k, 0) / total, comb(8, k) / size) for k in range(1, 9)]
    return spark.createDataFrame(rows, "lazy double, level int, share double, uniform double")


_TRIPLES = level(15, 1, 3)


def _device_mi(spark, sf, masks=_TRIPLES):
    packed, spec = prepared(spark, sf, "v_device")
    return info.lattice_mi(packed, spec, masks)


_HIST = """e AS (SELECT sg, min(round(mi, 9)) AS lo, max(round(mi, 9)) AS hi FROM m GROUP BY sg)"""
_BIN = "CAST(CASE WHEN round(hi - lo, 9) > 0 THEN greatest(0, least(floor(round((round(mi, 9) - lo) * 20 / round(hi - lo, 9), 6)), 19)) ELSE 0 END AS INTEGER)"


@query(f"""WITH {duck_mi(duck_view("v_device"), DEVICE, _TRIPLES)}, {_HIST} SELECT sg, {_BIN} AS bin, round(count(*) / sum(count(*)) OVER (PARTITION BY sg), 6) AS p FROM m JOIN e USING (sg) GROUP BY sg, bin""")
def smp_hist_population(spark, sf):
    mi = _device_mi(spark, sf)
    return topk.histogram(mi, topk.mi_range(mi)).select("sg", "bin", F.round("p", 6).alias("p"))


def _tv_sql(sample: str) -> str:
    return f"""WITH {duck_mi(duck_view("v_device"), DEVICE, _TRIPLES)}, {_HIST}, b AS (SELECT m.*, {_BIN} AS bin FROM m JOIN e USING (sg)), w AS ({sample}),
        pp AS (SELECT sg, bin, count(*) / sum(count(*)) OVER (PARTITION BY sg) AS p FROM b GROUP BY sg, bin),
        ps AS (SELECT b.sg, bin, count(*) / sum(count(*)) OVER (PARTITION BY b.sg) AS p FROM b JOIN w ON w.sg = b.sg AND w.mask = b.mask GROUP BY b.sg, bin)
        SELECT coalesce(pp.sg, ps.sg) AS sg, round(sum(abs(coalesce(pp.p, 0) - coalesce(ps.p, 0))), 6) AS tv FROM pp FULL JOIN ps ON pp.sg = ps.sg AND pp.bin = ps.bin GROUP BY 1"""


@query(_tv_sql(f"SELECT sg, CAST(mask AS BIGINT) AS mask FROM (VALUES {_walk_values(0.25, 1, 3)}) t(sg, mask, step)"))
def smp_tv_walk(spark, sf):
    mi = _device_mi(spark, sf)
    sample = mi.join(sampling.walk_sample(spark, _AV, 0.25, 0, 1, 3).select("sg", "mask"), ["sg", "mask"], "left_semi")
    return topk.tv_l1(sample, mi).select("sg", F.round("tv", 6).alias("tv"))


@query(_tv_sql(ORACLES["smp_arbitrary"]))
def smp_tv_arbitrary(spark, sf):
    mi = _device_mi(spark, sf)
    sample = mi.join(smp_arbitrary(spark, sf), ["sg", "mask"], "left_semi")
    return topk.tv_l1(sample, mi).select("sg", F.round("tv", 6).alias("tv"))


# ---- top-K


def _topk_query(name: str, view_name: str, n: int | None = None, m: int = 3, k: int = 10, sharing: str = "cuboid"):
    feats = SPECS[view_name].features[:n]
    masks = level(len(feats), m, m)

    def run(spark, sf):
        packed, spec = prepared(spark, sf, view_name, n)
        return shown_topk(topk.topk(info.lattice_mi(packed, spec, masks, sharing), m, k))

    query(f"WITH {duck_mi(duck_view(view_name), feats, masks)} {duck_topk(k)}", name)(run)


_topk_query("topk_exact_device", "v_device")
_topk_query("topk_exact_credit", "v_credit")
_topk_query("topk_exact_logic15", "v_logic15", sharing="blocks")

_LEVEL3 = level(15, 3, 3)


@query(f"WITH {duck_mi(duck_hidden('v_device', PLANTED['v_device'], DEVICE), DEVICE, _LEVEL3)} {duck_topk(10, where=f'mask & ({lacking_sql(PLANTED["v_device"])}) = 0')}")
def topk_computable_only(spark, sf):
    packed, spec = prepared(spark, sf, "v_device")
    mi = info.lattice_mi(masked(packed, PLANTED["v_device"]), spec, _LEVEL3)
    return shown_topk(topk.topk(info.computable(mi, PLANTED["v_device"]), 3, 10))


_SINGLES = level(15, 1, 1)
#: A fixed prediction rule that needs no training: the sum of single-feature MI.
_RULE = """p AS (SELECT t.sg, t.mask, sum(x.mi) AS p FROM (SELECT DISTINCT sg, mask FROM m WHERE level = 3) t JOIN m x ON x.sg = t.sg AND x.level = 1 AND t.mask & x.mask = x.mask GROUP BY t.sg, t.mask)"""


def _rule(mi: DataFrame) -> DataFrame:
    singles = mi.filter("level = 1").select("sg", F.col("mask").alias("bit"), F.col("mi").alias("one"))
    sets = mi.filter("level = 3").select("sg", "mask")
    each = sets.select("sg", "mask", F.explode(F.sequence(F.lit(0), F.lit(14))).alias("j"))
    held = each.withColumn("bit", F.call_function("shiftleft", F.lit(1).cast("long"), F.col("j"))).filter(F.col("mask").bitwiseAND(F.col("bit")) != 0)
    return held.join(singles, ["sg", "bit"]).groupBy("sg", "mask").agg(F.sum("one").alias("mi"))


_BOTH = level(15, 1, 1) + _LEVEL3


@query(f"""WITH {duck_mi(duck_view("v_device"), DEVICE, _BOTH)}, {_RULE}, h AS (SELECT p.sg, p.mask, CASE WHEN p.mask & ({lacking_sql(PLANTED["v_device"]).replace("sg", "p.sg")}) = 0 THEN m.mi ELSE p END AS mi
           FROM p JOIN m ON m.sg = p.sg AND m.mask = p.mask) {duck_topk(10, source="h")}""")
def topk_hybrid(spark, sf):
    """Exact MI where it is computable, the rule's prediction elsewhere."""
    mi = _device_mi(spark, sf, _BOTH)
    exact = info.computable(mi.filter("level = 3"), PLANTED["v_device"])
    return shown_topk(topk.topk(topk.hybrid(_rule(mi), exact), 3, 10))


@query(ORACLES["topk_exact_device"])
def topk_bound_pruned(spark, sf):
    """The same ranking with closure bounds from counted supersets of four features."""
    packed, spec = prepared(spark, sf, "v_device")
    over = info.lattice_mi(packed, spec, level(15, 4, 4))
    down = over.select("sg", F.col("mask").alias("up"), "mi", F.explode(F.sequence(F.lit(0), F.lit(14))).alias("j"))
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.col("j"))
    upper = down.filter(F.col("up").bitwiseAND(bit) != 0).groupBy("sg", F.col("up").bitwiseXOR(bit).alias("mask")).agg(F.min("mi").alias("bound"))

    def scores(wanted: DataFrame) -> DataFrame:
        masks = sorted(r[0] for r in wanted.select("mask").distinct().collect())
        return info.lattice_mi(packed, spec, masks).join(wanted, ["sg", "mask"], "left_semi")

    return shown_topk(topk.bounded_topk(upper, scores, 3, 10))


# ---- measures


def _ranked_pair(spark, sf, view_name="v_device"):
    packed, spec = prepared(spark, sf, view_name)
    mi = durable(info.lattice_mi(packed, spec, _BOTH, "blocks" if view_name == "v_logic15" else "auto"))
    return topk.topk(_rule(mi), 3, 10), topk.topk(mi, 3, 10)


def _pair_sql(view_name: str) -> str:
    return f"""WITH {duck_mi(duck_view(view_name), SPECS[view_name].features, _BOTH)}, {_RULE},
        a AS (SELECT sg, mask, row_number() OVER (PARTITION BY sg ORDER BY round(p, 9) DESC, mask) AS r FROM p),
        t AS (SELECT sg, mask, row_number() OVER (PARTITION BY sg ORDER BY round(mi, 9) DESC, mask) AS r FROM m WHERE level = 3),
        j AS (SELECT t.sg, t.r AS ideal, a.r AS got FROM t LEFT JOIN a ON a.sg = t.sg AND a.mask = t.mask AND a.r <= 10 WHERE t.r <= 10)"""


@query(f"{_pair_sql('v_device')} SELECT sg, round(coalesce(sum(1 / log2(got + 1)), 0) / sum(1 / log2(ideal + 1)), 6) + 0.0 AS value FROM j GROUP BY sg")
def msr_ndcg(spark, sf):
    pred, true = _ranked_pair(spark, sf)
    return topk.ndcg_at_k(pred, true, 10).select("sg", r6("value").alias("value"))


@query(f"{_pair_sql('v_device')} SELECT sg, round(count(got) / 10, 6) + 0.0 AS value FROM j GROUP BY sg")
def msr_precision(spark, sf):
    pred, true = _ranked_pair(spark, sf)
    return topk.precision_at_k(pred, true, 10).select("sg", r6("value").alias("value"))


@query(f"{_pair_sql('v_logic15')} SELECT sg, round(coalesce(sum(1 / log2(got + 1)), 0) / sum(1 / log2(ideal + 1)), 6) + 0.0 AS value FROM j GROUP BY sg")
def msr_ndcg_logic15(spark, sf):
    pred, true = _ranked_pair(spark, sf, "v_logic15")
    return topk.ndcg_at_k(pred, true, 10).select("sg", r6("value").alias("value"))


query(ORACLES["smp_tv_arbitrary"], "msr_tv")(smp_tv_arbitrary)


@query(f"""WITH {duck_mi(duck_view("v_device"), DEVICE[:6], level(6, 1, 6))}, b AS (SELECT sg, round(round(mi, 6) * (50 + (mask * 31) % 50), 9) AS p, round(mi, 9) AS t FROM m),
          r AS (SELECT *, rank() OVER (PARTITION BY sg ORDER BY p) + (count(*) OVER (PARTITION BY sg, p) - 1) / 2 AS rp, rank() OVER (PARTITION BY sg ORDER BY t) + (count(*) OVER (PARTITION BY sg, t) - 1) / 2 AS rt FROM b)
          SELECT sg, round(avg((p - t) ** 2), 4) AS mse, round(avg(abs(p - t)), 4) AS mae, round(corr(p, t), 4) AS corr, round(corr(rp, rt), 4) AS spearman FROM r GROUP BY sg""")
def msr_regression_error(spark, sf):
    packed, spec = prepared(spark, sf, "v_device", 6)
    mi = durable(info.lattice_mi(packed, spec, level(6, 1, 6)))
    pred = mi.select("sg", "mask", (F.round("mi", 6) * (50 + (F.col("mask") * 31) % 50)).alias("mi"))
    return topk.regression_error(pred, mi).select("sg", *[F.round(c, 4).alias(c) for c in ("mse", "mae", "corr", "spearman")])


@query("""WITH r(view, algorithm, k, seed, ndcg, precision) AS (VALUES ('a', 'x', 5, 0, 0.5, 0.4), ('a', 'x', 5, 1, 0.7, 0.6), ('a', 'x', 5, 2, 0.9, 0.2), ('a', 'y', 5, 0, 0.1, 0.0)),
          l AS (SELECT view, algorithm, k, 'ndcg' AS measure, ndcg AS v FROM r UNION ALL SELECT view, algorithm, k, 'precision', precision FROM r)
          SELECT view, algorithm, k, measure, round(avg(v), 6) AS mean, round(stddev_samp(v), 6) AS stddev, count(*) AS runs FROM l GROUP BY ALL""")
def msr_seed_summary(spark, sf):
    """Mean and deviation over seeds, as of the rows of the accuracy experiment."""
    from gapselect.experiments import summary

    runs = spark.createDataFrame([("a", "x", 5, 0, 0.5, 0.4), ("a", "x", 5, 1, 0.7, 0.6), ("a", "x", 5, 2, 0.9, 0.2), ("a", "y", 5, 0, 0.1, 0.0)], "view string, algorithm string, k int, seed int, ndcg double, precision double")
    return summary(runs).withColumns({"mean": F.round("mean", 6), "stddev": F.round("stddev", 6)})


@query("""WITH v(alg, p, value) AS (VALUES ('a', 0.2, 0.8), ('a', 0.3, 0.6), ('a', 0.4, 0.6), ('a', 0.5, 0.3), ('b', 0.2, 0.0), ('b', 0.3, 0.5), ('b', 0.4, 0.25), ('b', 0.5, 0.2)),
          l AS (SELECT *, lag(value) OVER (PARTITION BY alg ORDER BY p) AS b FROM v)
          SELECT alg, round(avg((b - value) / nullif(b, 0)), 6) AS delta, count(*) FILTER (b = 0) AS skipped FROM l WHERE b IS NOT NULL GROUP BY alg""")
def msr_delta(spark, sf):
    rows = [("a", 0.2, 0.8), ("a", 0.3, 0.6), ("a", 0.4, 0.6), ("a", 0.5, 0.3), ("b", 0.2, 0.0), ("b", 0.3, 0.5), ("b", 0.4, 0.25), ("b", 0.5, 0.2)]
    return topk.relative_drop(spark.createDataFrame(rows, "alg string, p double, value double"), ["alg"]).withColumn("delta", F.round("delta", 6))


_DEVICE_ALL = level(6, 1, 6)


@query(f"""WITH {duck_mi(duck_view("v_device"), _DEV6, _DEVICE_ALL)} SELECT a.sg, round(avg(CASE WHEN a.mi >= b.mi - 1e-9 THEN 1.0 ELSE 0.0 END), 6) AS accuracy, count(*) AS edges
          FROM m a JOIN m b ON a.sg = b.sg AND a.level = b.level + 1 AND a.mask & b.mask = b.mask GROUP BY a.sg""")
def msr_closure_exact(spark, sf):
    packed, spec = prepared(spark, sf, "v_device", 6)
    return topk.closure_accuracy(info.lattice_mi(packed, spec, _DEVICE_ALL), 6, by_level=False)


@query(f"""WITH {duck_mi(duck_view("v_device"), _DEV6, _DEVICE_ALL)}, p AS (SELECT sg, mask, level, round(mi, 6) * (50 + (mask * 31) % 50) AS mi FROM m)
          SELECT a.sg, a.level, round(avg(CASE WHEN a.mi >= b.mi - 1e-9 THEN 1.0 ELSE 0.0 END), 6) AS accuracy, count(*) AS edges
          FROM p a JOIN p b ON a.sg = b.sg AND a.level = b.level + 1 AND a.mask & b.mask = b.mask GROUP BY a.sg, a.level""")
def msr_closure_by_level(spark, sf):
    packed, spec = prepared(spark, sf, "v_device", 6)
    mi = info.lattice_mi(packed, spec, _DEVICE_ALL)
    shaken = mi.select("sg", "mask", (F.round("mi", 6) * (50 + (F.col("mask") * 31) % 50)).alias("mi"))
    return topk.closure_accuracy(shaken, 6).select("sg", "level", F.round("accuracy", 6).alias("accuracy"), "edges")


@query(f"""WITH s AS ({ORACLES["smp_arbitrary"]}), n AS (SELECT CAST(r AS BIGINT) AS mask FROM (SELECT unnest(range(1, 32768)) AS r) WHERE bit_count(r) <= 3), g AS (SELECT unnest(range(2)) AS sg)
          SELECT CAST(g.sg AS INTEGER) AS sg, CAST(count(*) AS BIGINT) AS n_test, CAST(sum(mask) AS BIGINT) AS mask_sum FROM g, n WHERE NOT EXISTS (SELECT 1 FROM s WHERE s.sg = g.sg AND s.mask = n.mask) GROUP BY g.sg""")
def msr_test_set(spark, sf):
    every = lat.nodes(spark, 15, 1, 3).select("mask").join(F.broadcast(spark.range(2).select(F.col("id").cast("int").alias("sg"))), F.lit(True))
    return topk.test_masks(every, smp_arbitrary(spark, sf)).groupBy("sg").agg(F.count(F.lit(1)).alias("n_test"), F.sum("mask").alias("mask_sum"))
