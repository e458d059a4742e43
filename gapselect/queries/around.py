"""Relational operators, functions, sources and sinks around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gapselect.operators import joins
from gapselect.operators import mi as info
from gapselect.queries.base import duck_hidden, duck_mi, level, prepared, query, r6
from gapselect.queries.methods import _AV, _BIN, _HELD, _HIST, _TRIPLES, FAMILY, PLANTED, READMITTED, _device_mi, _hidden_rows, _walk_values, held_nodes
from gapselect.sources import formats
from gapselect.sources.tables import sql, table
from gapselect.views import DEVICE, STAFF, duck_view, view

def n_rows_of():
    """count(*); made when asked for, since a column needs a session."""
    return F.count(F.lit(1))


# ---- sources and sinks


@query("SELECT l_orderkey, l_quantity, l_returnflag FROM lineitem WHERE l_quantity >= 45")
def scan_parquet_pruned(spark, sf) -> DataFrame:
    return table(spark, sf, "lineitem").filter("l_quantity >= 45").select("l_orderkey", "l_quantity", "l_returnflag")


for _fmt in ("csv", "json", "orc"):
    query("SELECT n_nationkey, n_name, n_regionkey FROM nation", f"scan_{_fmt}_roundtrip")(
        lambda spark, sf, fmt=_fmt: formats.roundtrip(table(spark, sf, "nation").select("n_nationkey", "n_name", "n_regionkey"), fmt)
    )


@query("SELECT CAST(r AS BIGINT) AS mask, CAST(bit_count(r) AS INTEGER) AS level FROM (SELECT unnest(range(1, 64)) AS r)")
def scan_lattice_source(spark, sf):
    from gapselect.sources.lattice_source import register

    register(spark)
    return spark.read.format("lattice").option("n", 6).option("low", 1).option("high", 6).load()


@query(f"WITH {duck_mi(duck_view('v_device'), DEVICE[:6], level(6, 1, 3))} SELECT sg, mask, level, round(mi, 6) + 0.0 AS mi FROM m WHERE sg = 1 AND level = 2")
def sink_roundtrip(spark, sf):
    """Constructs written by subgroup and level, read back with both partitions pruned."""
    packed, spec = prepared(spark, sf, "v_device", 6)
    folder = formats.scratch(spark, "constructs")
    info.lattice_mi(packed, spec, level(6, 1, 3)).repartition("sg", "level").write.partitionBy("sg", "level").parquet(folder)
    return spark.read.parquet(folder).filter("sg = 1 AND level = 2").select(F.col("sg").cast("int"), "mask", F.col("level").cast("int"), r6("mi").alias("mi"))


# ---- projection and filters


@query(f"SELECT sg, key_fifth, type, tax_max, y FROM ({duck_view('v_device')})")
def proj_vertical(spark, sf):
    return view(spark, sf, "v_device").select("sg", "key_fifth", "type", "tax_max", "y")


@query("SELECT l_orderkey, l_linenumber, CAST(year(l_shipdate) AS INTEGER) AS y, CAST(quarter(l_shipdate) AS INTEGER) AS q, CAST(floor((l_quantity - 1) / 6) AS INTEGER) AS b FROM lineitem")
def proj_derived(spark, sf):
    return table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", F.year("l_shipdate").alias("y"), F.quarter("l_shipdate").alias("q"), F.floor((F.col("l_quantity") - 1) / 6).cast("int").alias("b"))


@query("SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_linestatus = 'O' AND l_quantity > 30 AND NOT (l_returnflag = 'N')")
def flt_minterm(spark, sf):
    a, b, c = F.col("l_linestatus") == "O", F.col("l_quantity") > 30, F.col("l_returnflag") == "N"
    return table(spark, sf, "lineitem").filter(a & b & ~c).select("l_orderkey", "l_linenumber", "l_quantity")


@query(f"""SELECT sg, count(*) AS n_rows, CAST(count(*) FILTER ({" OR ".join(f"{f} IS NULL" for f in STAFF)}) AS BIGINT) AS with_null, CAST(count(*) FILTER (qty_bin IS NOT DISTINCT FROM NULL) AS BIGINT) AS no_qty
          FROM ({duck_hidden("v_staff", PLANTED["v_staff"], STAFF)}) GROUP BY sg""")
def flt_null(spark, sf):
    rows, spec = _hidden_rows(spark, sf, "v_staff")
    some = F.lit(False)
    for f in spec.features:
        some = some | F.col(f).isNull()
    return rows.groupBy("sg").agg(n_rows_of().alias("n_rows"), F.count_if(some).alias("with_null"), F.count_if(F.col("qty_bin").eqNullSafe(F.lit(None))).alias("no_qty"))


@query("SELECT p_partkey, p_name, p_brand, p_size FROM part WHERE p_name LIKE 'b%' AND p_brand IN ('Brand#11', 'Brand#22', 'Brand#33') AND p_size BETWEEN 5 AND 40")
def flt_like_in_between(spark, sf):
    p = table(spark, sf, "part")
    return p.filter(p.p_name.like("b%") & p.p_brand.isin("Brand#11", "Brand#22", "Brand#33") & p.p_size.between(5, 40)).select("p_partkey", "p_name", "p_brand", "p_size")


# ---- joins

_PER_BRAND = "SELECT p_brand, count(*) AS n_rows FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand"
for _name, _hint in (("broadcast", "broadcast"), ("merge", "merge"), ("hash", "shuffle_hash")):
    query(_PER_BRAND, f"join_inner_{_name}")(
        lambda spark, sf, hint=_hint: table(spark, sf, "lineitem").join(table(spark, sf, "part").select("p_partkey", "p_brand").hint(hint), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(n_rows_of().alias("n_rows"))
    )


@query("SELECT p_partkey, coalesce(c, 0) AS n_lines FROM part LEFT JOIN (SELECT l_partkey, count(*) AS c FROM lineitem WHERE l_quantity > 45 GROUP BY l_partkey) ON p_partkey = l_partkey")
def join_left_counts(spark, sf):
    c = table(spark, sf, "lineitem").filter("l_quantity > 45").groupBy("l_partkey").agg(n_rows_of().alias("c"))
    return table(spark, sf, "part").join(c, F.col("p_partkey") == F.col("l_partkey"), "left").select("p_partkey", F.coalesce("c", F.lit(0)).alias("n_lines"))


@query("SELECT r_name, n_name FROM (SELECT * FROM nation WHERE n_name < 'J') RIGHT JOIN region ON n_regionkey = r_regionkey")
def join_right(spark, sf):
    n = table(spark, sf, "nation").filter("n_name < 'J'")
    return n.join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"), "right").select("r_name", "n_name")


@query(f"""WITH {duck_mi(duck_view("v_device"), DEVICE, _TRIPLES)}, {_HIST}, b AS (SELECT m.sg, level, {_BIN} AS bin FROM m JOIN e USING (sg)),
          x AS (SELECT sg, bin, count(*) AS c FROM b GROUP BY sg, bin), z AS (SELECT sg, bin, count(*) AS c FROM b WHERE level <= 2 GROUP BY sg, bin)
          SELECT coalesce(x.sg, z.sg) AS sg, coalesce(x.bin, z.bin) AS bin, coalesce(x.c, 0) AS all_sets, coalesce(z.c, 0) AS small_sets FROM x FULL JOIN z ON x.sg = z.sg AND x.bin = z.bin""")
def join_full_hist(spark, sf):
    mi = _device_mi(spark, sf)
    e = mi.groupBy("sg").agg(F.min("mi").alias("low"), F.max("mi").alias("high"))
    place = F.when(F.col("high") > F.col("low"), F.least(F.floor((F.col("mi") - F.col("low")) * 20 / (F.col("high") - F.col("low"))), F.lit(19))).otherwise(0).cast("int")
    b = mi.join(e, "sg").select("sg", "level", place.alias("bin"))
    x, z = b.groupBy("sg", "bin").agg(n_rows_of().alias("all_sets")), b.filter("level <= 2").groupBy("sg", "bin").agg(n_rows_of().alias("small_sets"))
    return x.join(z, ["sg", "bin"], "full").fillna(0, ["all_sets", "small_sets"])


_AVAIL = ", ".join(f"({g}, CAST({m} AS BIGINT))" for g, m in _AV.items())
_N15 = "n AS (SELECT CAST(r AS BIGINT) AS mask FROM (SELECT unnest(range(1, 32768)) AS r) WHERE bit_count(r) = 2)"


def _available(spark, sf) -> DataFrame:
    """What each subgroup of the device view has, found from its rows."""
    from gapselect.operators.missing import detect_missing

    return detect_missing(*_hidden_rows(spark, sf, "v_device"))


@query(f"WITH {_N15}, a(sg, avail) AS (VALUES {_AVAIL}) SELECT mask FROM n WHERE EXISTS (SELECT 1 FROM a WHERE n.mask & avail = n.mask)")
def join_semi_avail(spark, sf):
    from gapselect.operators.lattice import nodes

    a = _available(spark, sf).select("sg", F.col("avail_mask").alias("avail"))
    return nodes(spark, 15, 2, 2).select("mask").join(F.broadcast(a), F.col("mask").bitwiseAND(F.col("avail")) == F.col("mask"), "left_semi")


@query(f"""WITH n AS (SELECT CAST(r AS BIGINT) AS mask FROM (SELECT unnest(range(1, 32768)) AS r) WHERE bit_count(r) <= 3), g(sg) AS (VALUES {", ".join(f"({g})" for g in _AV)}),
          w(sg, mask, step) AS (VALUES {_walk_values(0.25, 1, 3)})
          SELECT CAST(g.sg AS INTEGER) AS sg, n.mask FROM g, n WHERE NOT EXISTS (SELECT 1 FROM w WHERE w.sg = g.sg AND w.mask = n.mask)""")
def join_anti_unsampled(spark, sf):
    """Computable sets that were not sampled, and blocked ones."""
    from gapselect.operators import sampling
    from gapselect.operators.lattice import nodes

    available = {r["sg"]: r["avail_mask"] for r in _available(spark, sf).collect()}  # a row a subgroup
    every = nodes(spark, 15, 1, 3).select("mask").join(F.broadcast(spark.createDataFrame([(g,) for g in available], "sg int")), F.lit(True))
    walk = sampling.walk_sample(spark, available, 0.25, 0, 1, 3)
    computable = sampling.universe(spark, available, 15, 1, 3)
    blocked = every.join(computable, ["sg", "mask"], "left_anti")
    return computable.join(walk, ["sg", "mask"], "left_anti").unionByName(blocked)


@query(f"""WITH c AS (SELECT DISTINCT sg, type, size_bin FROM ({duck_view("v_device")})), m AS (SELECT CAST(r AS BIGINT) AS mask FROM (SELECT unnest(range(1, 4)) AS r))
          SELECT sg, mask, count(DISTINCT coalesce(CASE WHEN mask & 1 > 0 THEN type END, '') || '|' || coalesce(CAST(CASE WHEN mask & 2 > 0 THEN size_bin END AS STRING), '')) AS n_cells FROM c, m GROUP BY sg, mask""")
def join_cross_masks(spark, sf):
    c = view(spark, sf, "v_device").select("sg", "type", "size_bin").distinct()
    wide = c.crossJoin(F.broadcast(spark.range(1, 4).withColumnRenamed("id", "mask")))
    key = F.concat_ws("|", F.when(F.col("mask").bitwiseAND(F.lit(1)) > 0, F.col("type")).otherwise(""), F.when(F.col("mask").bitwiseAND(F.lit(2)) > 0, F.col("size_bin").cast("string")).otherwise(""))
    return wide.groupBy("sg", "mask").agg(F.countDistinct(key).alias("n_cells"))


@query(f"""WITH v AS (SELECT id, sg, type, size_bin, key_fifth, brand_bin FROM ({duck_view("v_device")}))
          SELECT a.id AS a, b.id AS b FROM v a JOIN v b ON a.sg = 0 AND b.sg = 1 AND (a.type <> b.type)::INT + (a.size_bin <> b.size_bin)::INT + (a.key_fifth <> b.key_fifth)::INT + (a.brand_bin <> b.brand_bin)::INT <= 1""")
def join_theta_dist(spark, sf):
    """Pairs that differ in one of four features at most, across subgroups. The three others
    are an equi-join key: no nested loop, and no pair is made in vain."""
    v = view(spark, sf, "v_device").select("id", "sg", "type", "size_bin", "key_fifth", "brand_bin")
    return joins.near_pairs(v.filter("sg = 0"), v.filter("sg = 1"), [["type"], ["size_bin"], ["key_fifth"], ["brand_bin"]], "id", 1)


@query("""SELECT b, count(*) AS n_rows FROM orders JOIN (VALUES (0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, 1e9)) t(b, lo, hi) ON o_totalprice > lo AND o_totalprice <= hi GROUP BY b""")
def join_range_bins(spark, sf):
    bins = spark.createDataFrame([(0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 300000.0), (3, 300000.0, 1e9)], "b int, lo double, hi double")
    return joins.range_join(table(spark, sf, "orders"), bins, "o_totalprice", "lo", "hi").groupBy("b").agg(n_rows_of().alias("n_rows"))


@query("""SELECT e.event_id, p.value AS last_value FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY user_id, ts) p
          ON e.user_id = p.user_id AND e.ts >= p.ts""")
def join_asof_events(spark, sf):
    e = table(spark, sf, "events")
    right = e.filter("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value"))
    return joins.asof(e.filter("event_type = 'error'").select("event_id", "user_id", "ts"), right, "user_id", "ts", ["value"]).select("event_id", F.col("value").alias("last_value"))


@query("""SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR""")
def join_interval_events(spark, sf):
    e = table(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    return joins.interval_join(e.filter("event_type = 'click'"), e.filter("event_type = 'purchase'"), "user_id", "ts", 3600).select(F.col("l_event_id").alias("click"), F.col("r_event_id").alias("purchase"))


@query(f"WITH {_HELD}, j AS (SELECT unnest(range(6)) AS j) SELECT a.mask AS upper, b.mask AS lower FROM held a, j JOIN held b ON b.mask = a.mask - (1 << j) AND (a.mask >> j) & 1 = 1")
def join_self_xor(spark, sf):
    from gapselect.operators.lattice import inter_edges

    return inter_edges(held_nodes(spark, sf), 6)


# ---- aggregation


@query("SELECT l_returnflag, l_linestatus, count(*) AS n_rows, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, round(avg(l_extendedprice), 4) AS avg_price, min(l_discount) AS lo, max(l_discount) AS hi FROM lineitem GROUP BY ALL")
def agg_basic(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        n_rows_of().alias("n_rows"), F.sum(F.col("l_quantity").cast("long")).alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("avg_price"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi")
    )


@query("SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_discount), 6) + 0.0 AS r FROM lineitem GROUP BY l_returnflag")
def agg_stats(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev("l_quantity"), 6).alias("sd"), r6(F.corr("l_quantity", "l_discount")).alias("r"))


@query("SELECT s_nationkey, count(DISTINCT l_partkey) AS parts FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_nationkey")
def agg_distinct(spark, sf):
    return table(spark, sf, "lineitem").join(table(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_nationkey").agg(F.countDistinct("l_partkey").alias("parts"))


@query()
def agg_approx_distinct(spark, sf):
    return table(spark, sf, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("sketch"), F.countDistinct("l_orderkey").alias("exact"))


@query("SELECT l_linenumber, CAST(count(*) FILTER (l_returnflag = 'A') AS BIGINT) AS a, CAST(count(*) FILTER (l_returnflag = 'N') AS BIGINT) AS n, CAST(count(*) FILTER (l_returnflag = 'R') AS BIGINT) AS r FROM lineitem GROUP BY l_linenumber")
def agg_filter(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_linenumber").agg(*[F.count_if(F.col("l_returnflag") == s).alias(s.lower()) for s in "ANR"])


@query(f"""WITH j AS (SELECT sg, key_fifth, y, count(*) AS c FROM ({duck_view("v_device")}) GROUP BY ALL)
          SELECT *, CAST(sum(c) OVER (PARTITION BY sg, key_fifth) AS BIGINT) AS c_f, CAST(sum(c) OVER (PARTITION BY sg, y) AS BIGINT) AS c_y FROM j""")
def agg_contingency(spark, sf):
    j = view(spark, sf, "v_device").groupBy("sg", "key_fifth", "y").agg(n_rows_of().alias("c"))
    return j.withColumns({"c_f": F.sum("c").over(Window.partitionBy("sg", "key_fifth")), "c_y": F.sum("c").over(Window.partitionBy("sg", "y"))})


@query("SELECT l_returnflag, l_linestatus, CAST(GROUPING_ID(l_returnflag, l_linestatus) AS BIGINT) AS gid, count(*) AS n_rows FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), (l_returnflag, l_linestatus))")
def agg_grouping_sets(spark, sf):
    a, b = F.col("l_returnflag"), F.col("l_linestatus")
    return table(spark, sf, "lineitem").groupingSets([[a], [b], [a, b]], a, b).agg(F.grouping_id().alias("gid"), n_rows_of().alias("n_rows"))


@query("SELECT l_returnflag, l_linestatus, CAST(GROUPING_ID(l_returnflag, l_linestatus) AS BIGINT) AS gid, count(*) AS n_rows FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube2(spark, sf):
    return table(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("gid"), n_rows_of().alias("n_rows"))


@query("SELECT r_name, n_name, CAST(GROUPING_ID(r_name, n_name) AS BIGINT) AS gid, count(*) AS n_rows FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(spark, sf):
    c = table(spark, sf, "customer").join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.rollup("r_name", "n_name").agg(F.grouping_id().alias("gid"), n_rows_of().alias("n_rows"))


@query("SELECT l_linenumber, CAST(count(*) FILTER (l_linestatus = 'F') AS BIGINT) AS F, CAST(count(*) FILTER (l_linestatus = 'O') AS BIGINT) AS O FROM lineitem GROUP BY l_linenumber")
def agg_pivot(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_linenumber").pivot("l_linestatus", ["F", "O"]).agg(n_rows_of()).fillna(0)


@query("SELECT feature, code, count(*) AS n_rows FROM (UNPIVOT (SELECT l_linenumber AS line_no, CAST(floor((l_quantity - 1) / 6) AS INTEGER) AS qty FROM lineitem) ON line_no, qty INTO NAME feature VALUE code) GROUP BY ALL")
def agg_unpivot(spark, sf):
    wide = table(spark, sf, "lineitem").select(F.col("l_linenumber").alias("line_no"), F.floor((F.col("l_quantity") - 1) / 6).cast("int").alias("qty"))
    return wide.unpivot([], ["line_no", "qty"], "feature", "code").groupBy("feature", "code").agg(n_rows_of().alias("n_rows"))


@query(f"SELECT sg, type FROM (SELECT sg, type, row_number() OVER (PARTITION BY sg ORDER BY count(*) DESC, type) AS r FROM ({duck_view('v_device')}) GROUP BY sg, type) WHERE r = 1")
def agg_mode(spark, sf):
    c = view(spark, sf, "v_device").groupBy("sg", "type").agg(n_rows_of().alias("c"))
    return c.withColumn("r", F.row_number().over(Window.partitionBy("sg").orderBy(F.desc("c"), "type"))).filter("r = 1").select("sg", "type")


@query("SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS median, round(quantile_cont(o_totalprice, 0.9), 4) AS p90 FROM orders GROUP BY o_orderpriority")
def agg_percentile(spark, sf):
    return table(spark, sf, "orders").groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


# ---- windows, ranking, sets

_W = "PARTITION BY p_brand ORDER BY p_retailprice, p_partkey"


@query(f"""SELECT p_partkey, CAST(row_number() OVER ({_W}) AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice) AS INTEGER) AS dr,
          round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_retailprice), 6) AS pr, CAST(ntile(4) OVER ({_W}) AS INTEGER) AS nt FROM part""")
def win_rank_family(spark, sf):
    one, w = Window.partitionBy("p_brand").orderBy("p_retailprice"), Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")
    return table(spark, sf, "part").select("p_partkey", F.row_number().over(w).alias("rn"), F.rank().over(one).alias("rk"), F.dense_rank().over(one).alias("dr"), F.round(F.percent_rank().over(one), 6).alias("pr"), F.ntile(4).over(w).alias("nt"))


@query("SELECT o_custkey, o_orderkey, round(p - o_totalprice, 4) AS fall FROM (SELECT *, lag(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS p FROM orders) WHERE p > o_totalprice")
def win_lag_drop(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, sf, "orders").withColumn("p", F.lag("o_totalprice").over(w)).filter("p > o_totalprice").select("o_custkey", "o_orderkey", F.round(F.col("p") - F.col("o_totalprice"), 4).alias("fall"))


@query(f"WITH {duck_mi(duck_view('v_credit'), ('len_band', 'words_band', 'vocab_ratio', 'upper_ratio', 'punct_ratio', 'digit_ratio'), level(6, 1, 3))} SELECT sg, mask, round(row_number() OVER (PARTITION BY sg ORDER BY round(mi, 9), mask) / count(*) OVER (PARTITION BY sg), 6) AS cdf FROM m")
def win_running(spark, sf):
    packed, spec = prepared(spark, sf, "v_credit", 6)
    w = Window.partitionBy("sg").orderBy(F.round("mi", 9), "mask").rowsBetween(Window.unboundedPreceding, 0)
    mi = info.lattice_mi(packed, spec, level(6, 1, 3))
    return mi.select("sg", "mask", F.round(n_rows_of().over(w) / n_rows_of().over(Window.partitionBy("sg")), 6).alias("cdf"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW), 4) + 0.0 AS v FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS t FROM events)")
def win_range_frame(spark, sf):
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-3600, 0)
    return table(spark, sf, "events").withColumn("t", F.unix_timestamp("ts")).select("event_id", (F.round(F.sum("value").over(w), 4) + 0.0).alias("v"))


@query("SELECT DISTINCT user_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_first_last(spark, sf):
    e = table(spark, sf, "events")
    return e.groupBy("user_id").agg(F.min_by("event_type", F.struct("ts", "event_id")).alias("first_type"), F.max_by("event_type", F.struct("ts", "event_id")).alias("last_type"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk_orders(spark, sf):
    return table(spark, sf, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@query("SELECT o_orderpriority, o_orderkey, CAST(r AS INTEGER) AS r FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def topk_per_group(spark, sf):
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf, "orders").withColumn("r", F.row_number().over(w)).filter("r <= 3").select("o_orderpriority", "o_orderkey", "r")


@query("""SELECT n_name, CAST(row_number() OVER (ORDER BY CASE WHEN n_regionkey = 2 THEN NULL ELSE n_regionkey END DESC NULLS LAST, n_name) AS INTEGER) AS place FROM nation""")
def sort_multi(spark, sf):
    from gapselect.operators.prep import ranked

    key = F.when(F.col("n_regionkey") != 2, F.col("n_regionkey"))
    out = ranked(table(spark, sf, "nation"), [key.isNull(), -key, F.col("n_name")], "r", "t")
    return out.select("n_name", (F.col("r") + 1).cast("int").alias("place"))


def _sets(spark):
    from gapselect.operators import sampling
    from gapselect.operators.lattice import nodes

    return nodes(spark, 15, 2, 2).select("mask"), sampling.universe(spark, {0: _AV[0]}, 15, 2, 2).select("mask"), sampling.universe(spark, {1: _AV[1]}, 15, 2, 2).select("mask")


_A, _B = (f"SELECT mask FROM n WHERE mask & {_AV[g]} = mask" for g in (0, 1))


@query(f"WITH {_N15} {_A} UNION {_B}")
def set_union(spark, sf):
    _, a, b = _sets(spark)
    return a.union(b).distinct()


@query(f"WITH {_N15} {_A} INTERSECT {_B}")
def set_intersect(spark, sf):
    _, a, b = _sets(spark)
    return a.intersect(b)


@query("SELECT l_returnflag, l_linenumber FROM (SELECT l_returnflag, l_linenumber FROM lineitem WHERE l_quantity > 25) EXCEPT ALL SELECT l_returnflag, l_linenumber FROM lineitem WHERE l_quantity > 30")
def set_except(spark, sf):
    li = table(spark, sf, "lineitem").select("l_returnflag", "l_linenumber", "l_quantity")
    return li.filter("l_quantity > 25").drop("l_quantity").exceptAll(li.filter("l_quantity > 30").drop("l_quantity"))


# ---- functions


@query("SELECT o_orderkey, m, CAST(bit_count(m) AS INTEGER) AS pop, m & 12 AS a, m | 12 AS o, xor(m, 12) AS x, m << 2 AS l, bin(m) AS b FROM (SELECT o_orderkey, CAST(o_custkey AS BIGINT) AS m FROM orders)")
def fn_bits(spark, sf):
    m = F.col("o_custkey").cast("long")
    return table(spark, sf, "orders").select("o_orderkey", m.alias("m"), F.bit_count(m).cast("int").alias("pop"), m.bitwiseAND(F.lit(12)).alias("a"), m.bitwiseOR(F.lit(12)).alias("o"), m.bitwiseXOR(F.lit(12)).alias("x"), F.shiftleft(m, 2).alias("l"), F.bin(m).alias("b"))


@query("""SELECT p_partkey, upper(p_name) AS u, trim('  ' || p_type || ' ') AS t, lpad(CAST(p_size AS STRING), 4, '0') AS l, split_part(p_name, ' ', 2) AS s, regexp_replace(p_name, '[aeiou]', '_', 'g') AS r, replace(p_brand, '#', '-') AS b, md5(p_name) AS m FROM part""")
def fn_string(spark, sf):
    return table(spark, sf, "part").select(
        "p_partkey", F.upper("p_name").alias("u"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("t"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("l"),
        F.split_part("p_name", F.lit(" "), F.lit(2)).alias("s"), F.regexp_replace("p_name", "[aeiou]", "_").alias("r"), F.replace("p_brand", F.lit("#"), F.lit("-")).alias("b"), F.md5("p_name").alias("m"),
    )


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS d, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS n, strftime(o_orderdate, '%Y-%m-01') AS t FROM orders")
def fn_date(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.quarter(d).alias("q"), F.dayofweek(d).alias("d"), F.datediff(d, F.lit("1995-01-01").cast("date")).alias("n"), F.date_format(F.trunc(d, "month"), "yyyy-MM-dd").alias("t"))


@query("SELECT p_partkey, round(log2(p_retailprice), 6) AS l, round(pow(p_size, 1.5), 6) AS p, CAST(floor(p_retailprice / 7) AS BIGINT) AS f, greatest(p_size, 25) AS g, CAST(greatest(0, least(6, floor((p_retailprice - 900) / 20) + 1)) AS BIGINT) AS w FROM part")
def fn_math(spark, sf):
    x = F.col("p_retailprice")
    return table(spark, sf, "part").select("p_partkey", F.round(F.log2(x), 6).alias("l"), F.round(F.pow("p_size", F.lit(1.5)), 6).alias("p"), F.floor(x / 7).alias("f"), F.greatest("p_size", F.lit(25)).alias("g"), F.width_bucket(x, F.lit(900.0), F.lit(1000.0), F.lit(5)).alias("w"))


@query("SELECT p_partkey, CAST(len(list_filter(range(0, r + 1), lambda x: x % 3 = 0)) AS INTEGER) AS thirds, CAST(list_sum(list_transform(range(0, r + 1), lambda x: x * x)) AS BIGINT) AS squares FROM (SELECT p_partkey, CAST(p_size AS BIGINT) AS r FROM part)")
def fn_array(spark, sf):
    s = F.sequence(F.lit(0).cast("long"), F.col("p_size").cast("long"))
    return table(spark, sf, "part").select("p_partkey", F.size(F.filter(s, lambda x: x % 3 == 0)).alias("thirds"), F.aggregate(F.transform(s, lambda x: x * x), F.lit(0).cast("long"), lambda a, b: a + b).alias("squares"))


@query("SELECT o_orderstatus AS k, count(*) AS v FROM orders GROUP BY o_orderstatus")
def fn_map(spark, sf):
    c = table(spark, sf, "orders").groupBy("o_orderstatus").agg(n_rows_of().alias("c"))
    m = c.agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "c"))).alias("m"))
    return m.select(F.explode("m").alias("k", "v"))


@query("SELECT n_nationkey, n_name AS name, n_regionkey AS region FROM nation")
def fn_struct(spark, sf):
    return table(spark, sf, "nation").select("n_nationkey", F.struct(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region")).alias("s")).select("n_nationkey", "s.name", "s.region")


@query("SELECT CAST(floor(CAST(json_extract_string(props, '$.k') AS INTEGER) / 10) AS INTEGER) AS band, count(*) AS n_rows FROM events GROUP BY band")
def fn_json(spark, sf):
    return table(spark, sf, "events").groupBy(F.floor(F.get_json_object("props", "$.k").cast("int") / 10).cast("int").alias("band")).agg(n_rows_of().alias("n_rows"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 4) AS norm2 FROM embeddings")
def fn_vector(spark, sf):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, sf, "embeddings").select("vec_id", F.round(F.aggregate(F.zip_with(e, e, lambda a, b: a * b), F.lit(0.0), lambda a, b: a + b), 4).alias("norm2"))


@query("SELECT l_returnflag, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem GROUP BY l_returnflag")
def fn_decimal(spark, sf):
    total = F.sum(F.col("l_extendedprice").cast("decimal(18,2)"))
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg((total * 100).cast("long").alias("cents"))


@query("SELECT o_orderkey, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '2002-01-01') AS INTEGER) AS age FROM orders")
def fn_interval(spark, sf):
    gap = F.lit("2002-01-01").cast("date") - F.col("o_orderdate").cast("date")
    return table(spark, sf, "orders").select("o_orderkey", F.extract(F.lit("DAY"), gap).cast("int").alias("age"))


# ---- subqueries, CTE, user functions


@query("SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM orders)")
def sub_scalar(spark, sf):
    return sql(spark, sf, "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM {orders})")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)")
def sub_exists(spark, sf):
    return sql(spark, sf, "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 300000)")


@query("WITH a AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), b AS (SELECT n, count(*) AS c FROM a GROUP BY n) SELECT n, c FROM b")
def cte_chain(spark, sf):
    return sql(spark, sf, "WITH a AS (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey), b AS (SELECT n, count(*) AS c FROM a GROUP BY n) SELECT n, c FROM b")


def _walk_cte(orders, coin, xor) -> str:
    lazy, move = coin("concat('7|z|', walker, '|', CAST(step + 1 AS STRING))"), coin("concat('7|m|', walker, '|', CAST(step + 1 AS STRING))")
    flip = xor("mask", f"CAST(1 AS BIGINT) << CAST({move} % 6 AS INT)")
    return f"""
        SELECT o_orderpriority AS walker, 0 AS step, CAST(1 + sum(CAST(o_custkey AS BIGINT)) % 63 AS BIGINT) AS mask FROM {orders} GROUP BY o_orderpriority
        UNION ALL
        SELECT walker, step + 1, CASE WHEN {lazy} % 2 = 0 THEN mask WHEN {flip} = 0 THEN mask ELSE {flip} END FROM w WHERE step < 60"""


_DUCK_WALK = _walk_cte("orders", lambda t: f"CAST('0x' || substr(md5({t}), 1, 8) AS BIGINT)", lambda a, b: f"xor({a}, {b})")


@query(f"WITH RECURSIVE w AS ({_DUCK_WALK}) SELECT walker, CAST(step AS INTEGER) AS step, mask FROM w")
def cte_walk(spark, sf):
    """Lazy walks on six bits by recursion, one for each priority of orders, from where its
    customers' keys send it; coins by md5; the empty set is held."""
    body = _walk_cte("{orders}", lambda t: f"CAST(conv(substr(md5({t}), 1, 8), 16, 10) AS BIGINT)", lambda a, b: f"(({a}) ^ ({b}))")
    return sql(spark, sf, f"WITH RECURSIVE w(walker, step, mask) AS ({body}) SELECT walker, step, mask FROM w")


@query("SELECT CAST(r AS BIGINT) AS mask, CAST(bit_count(r) AS INTEGER) AS level, CAST((r & 1) + (r >> 1 & 1) * 2 AS BIGINT) AS low_bits FROM (SELECT unnest(range(1, 16)) AS r)")
def udf_sql_mask(spark, sf):
    from gapselect.functions.sql_functions import register

    register(spark)
    return spark.sql("SELECT id AS mask, set_level(id) AS level, mask_part(id, 3L) AS low_bits FROM range(1, 16)")


@query("SELECT CAST(r AS BIGINT) AS mask, list_filter(['a', 'b', 'c', 'd'], lambda x, i: (r >> (i - 1)) & 1 = 1) AS names, CAST(r AS BIGINT) AS again FROM (SELECT unnest(range(1, 16)) AS r)")
def udf_sql_sets(spark, sf):
    from gapselect.functions.sql_functions import register

    register(spark)
    named = spark.sql("SELECT id AS mask, set_of(id, array('a', 'b', 'c', 'd')) AS names FROM range(1, 16)")
    return named.selectExpr("mask", "names", "mask_of(names, array('a', 'b', 'c', 'd')) AS again")


@query(f"""WITH t(f, y) AS (VALUES {", ".join(f"('{f}', '{y}')" for f, y in zip(FAMILY, READMITTED))}), j AS (SELECT f, y, count(*) AS c FROM t GROUP BY f, y), n AS (SELECT count(*) AS n FROM t)
          SELECT round(sum(c / n * log2(c * n / (cf * cy))), 6) AS mi FROM (SELECT *, sum(c) OVER (PARTITION BY f) AS cf, sum(c) OVER (PARTITION BY y) AS cy FROM j), n""")
def udf_sql_joint_mi(spark, sf):
    """MI from a table of counts in SQL: the worked example."""
    from gapselect.functions.sql_functions import register

    register(spark)
    return spark.sql("SELECT round(joint_mi(array(array(6L, 2L), array(1L, 3L))), 6) AS mi")


_ENT = "SELECT l_linenumber, round(log2(sum(c)) - sum(c * log2(c)) / sum(c), 6) AS h FROM (SELECT l_linenumber, l_returnflag, count(*) AS c FROM lineitem GROUP BY ALL) GROUP BY l_linenumber"


@query(_ENT)
def udf_pandas_entropy(spark, sf):
    from gapselect.functions.sql_functions import entropy_of

    c = table(spark, sf, "lineitem").groupBy("l_linenumber", "l_returnflag").agg(n_rows_of().alias("c"))
    return c.groupBy("l_linenumber").agg(F.sort_array(F.collect_list("c")).alias("c")).select("l_linenumber", F.round(entropy_of()("c"), 6).alias("h"))


@query(_ENT)
def udaf_entropy(spark, sf):
    from gapselect.functions.sql_functions import entropy_agg

    c = table(spark, sf, "lineitem").groupBy("l_linenumber", "l_returnflag").agg(n_rows_of().alias("c"))
    return c.groupBy("l_linenumber").agg(entropy_agg()("c").alias("h")).withColumn("h", F.round("h", 6))


@query("WITH n AS (SELECT CAST(r AS BIGINT) AS m FROM (SELECT unnest(range(1, 16)) AS r)) SELECT b.m AS neighbour, CASE WHEN bit_count(b.m) = bit_count(a.m) THEN 'intra' ELSE 'inter' END AS kind FROM n a JOIN n b ON a.m = 3 AND a.m <> b.m AND ((abs(bit_count(a.m) - bit_count(b.m)) = 1 AND a.m & b.m IN (a.m, b.m)) OR (bit_count(a.m) = bit_count(b.m) AND bit_count(a.m & b.m) = 1))")
def udtf_neighbours(spark, sf):
    from gapselect.functions.sql_functions import register

    register(spark)
    return spark.sql("SELECT neighbour, kind FROM lattice_neighbours(3, 4)")


@query()
def udf_grouped_map(spark, sf):
    """Ridge predictions per subgroup."""
    from gapselect.model.fit import ridge_all

    packed, spec = prepared(spark, sf, "v_device", 6)
    return ridge_all(info.lattice_mi(packed, spec, level(6, 1, 3)), 6, 1, 3).select("sg", "mask", F.round("mi", 6).alias("mi"))
