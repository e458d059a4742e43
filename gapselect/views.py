"""Analytic views over the given tables: features, subgroup ``sg`` and target ``y``.

They stand for the data sets of the experiments; every expression gives the same values in
Spark and in DuckDB. Noise comes from md5 coins of the row's identity, never from a
generator, so views survive retries and any partitioning.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gapselect.functions.dialect import DUCK, SPARK, Dialect, clip, floor_div
from gapselect.sources.tables import spread, sql, table
from gapselect.spec import FeatureSpec

ROW_KEY = (
    "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, CAST(l_quantity AS BIGINT), "
    "CAST(round(l_extendedprice * 100) AS BIGINT))"
)

DEVICE = ("brand_bin", "type", "size_bin", "name_first", "name_second", "key_fifth", "key_noisy", "lines_band", "qty_band", "disc_band", "tax_max", "supp_band", "ret_band", "first_year", "last_quarter")
STAFF = (
    "qty_bin", "disc_bin", "tax", "ship_quarter", "line_no", "order_status", "priority", "segment", "region", "type",
    "brand_bin", "size_bin", "retail_bin", "cust_bal", "total_bin", "ship_lag", "supp_bal", "price_bin", "order_month_third",
)
CREDIT = ("len_band", "words_band", "vocab_ratio", "upper_ratio", "punct_ratio", "digit_ratio", "lines_band", "accent_ratio", "word_len", "has_pipe", "has_junk", "has_at", "has_url", "source_group", "doc_mod")
LOGIC15 = ("x0", "x1", "x2", "x3", "x4", "c0", "c1", "r0", "r1", "r2", "z0", "z1", "z2", "z3", "z4")
LOGIC20 = ("x0", "x1", "x2", "x3", "x4", "x5", "c0", "c1", "c2", "r0", "r1", "r2", "r3", "z0", "z1", "z2", "z3", "z4", "z5", "z6")

SPECS = {
    "v_device": FeatureSpec(DEVICE), "v_staff": FeatureSpec(STAFF), "v_credit": FeatureSpec(CREDIT),
    "v_logic15": FeatureSpec(LOGIC15), "v_logic20": FeatureSpec(LOGIC20), "v_scale": FeatureSpec(LOGIC20[:10]),
}
GROUPS = {"v_device": 2, "v_staff": 8, "v_credit": 3, "v_logic15": 4, "v_logic20": 4, "v_scale": 4}


def device(d: Dialect) -> str:
    noise = "concat('noise|', CAST(p_partkey AS STRING))"
    return f"""
    WITH a AS (
        SELECT l_partkey, count(*) AS c, sum(CAST(l_quantity AS BIGINT)) AS q, sum(CAST(round(l_discount * 100) AS BIGINT)) AS di,
               count(DISTINCT l_suppkey) AS su, sum(CASE WHEN l_returnflag = 'R' THEN 1 ELSE 0 END) AS rr,
               max(CAST(round(l_tax * 100) AS BIGINT)) AS tx, min(l_shipdate) AS fs, max(l_shipdate) AS ls
        FROM {d.table("lineitem")} GROUP BY l_partkey)
    SELECT p_partkey AS id, CAST(p_size % 2 AS INT) AS sg, {floor_div("p_partkey % 1000", "250")} AS y,
           CAST(CAST(substr(p_brand, 7) AS INT) % 9 AS INT) AS brand_bin, p_type AS type, {floor_div("p_size - 1", "10")} AS size_bin,
           split_part(p_name, ' ', 1) AS name_first, split_part(p_name, ' ', 2) AS name_second,
           {floor_div("p_partkey % 1000", "200")} AS key_fifth,
           CASE WHEN {d.coin(noise, 0, 4)} % 100 < 40 THEN CAST({d.coin(noise, 4, 4)} % 8 AS INT) ELSE {floor_div("p_partkey % 1000", "125")} END AS key_noisy,
           {clip(floor_div("c - 15", "4"))} AS lines_band, {clip(floor_div("10 * q / c - 195", "20"))} AS qty_band,
           {clip(floor_div("100 * di / c - 400", "40"))} AS disc_band, tx AS tax_max, {clip(floor_div("su - 14", "4"))} AS supp_band,
           {clip(floor_div("20 * rr", "c"))} AS ret_band, CAST(year(fs) AS INT) - 1995 AS first_year, CAST(quarter(ls) AS INT) AS last_quarter
    FROM {d.table("part")} LEFT JOIN a ON p_partkey = l_partkey"""


def staff(d: Dialect) -> str:
    return f"""
    WITH b AS (
        SELECT {ROW_KEY} AS k, 2 * {floor_div("year(o_orderdate) - 1995", "2")} + CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END AS sg, l_returnflag,
               {floor_div("l_quantity - 1", "6")} AS qty_bin, {floor_div("round(l_discount * 100)", "2")} AS disc_bin, CAST(round(l_tax * 100) AS INT) AS tax,
               CAST(quarter(l_shipdate) AS INT) AS ship_quarter, l_linenumber AS line_no, o_orderstatus AS order_status, o_orderpriority AS priority,
               c_mktsegment AS segment, r_regionkey AS region, p_type AS type, CAST(CAST(substr(p_brand, 7) AS INT) % 9 AS INT) AS brand_bin,
               {floor_div("p_size - 1", "10")} AS size_bin, {floor_div("p_partkey % 1000", "125")} AS retail_bin,
               {clip(floor_div("c_acctbal + 1000", "1250"))} AS cust_bal, {clip(floor_div("o_totalprice", "60000"))} AS total_bin,
               {clip(floor_div(d.days("o_orderdate", "l_shipdate"), "20"))} AS ship_lag, {clip(floor_div("s_acctbal + 1000", "1250"))} AS supp_bal,
               {clip(floor_div("l_extendedprice", "12000"))} AS price_bin, {floor_div("month(o_orderdate) - 1", "4")} AS order_month_third
        FROM {d.table("lineitem")} JOIN {d.table("orders")} ON l_orderkey = o_orderkey JOIN {d.table("customer")} ON o_custkey = c_custkey
             JOIN {d.table("nation")} ON c_nationkey = n_nationkey JOIN {d.table("region")} ON n_regionkey = r_regionkey
             JOIN {d.table("part")} ON l_partkey = p_partkey JOIN {d.table("supplier")} ON l_suppkey = s_suppkey),
    f AS (SELECT *, total_bin >= 4 AS z1, ship_lag >= 4 AS z2, substr(priority, 1, 1) IN ('1', '2') AS z3, region < 2 AS z4, qty_bin >= 4 AS z5 FROM b)
    SELECT k AS id, sg, {", ".join(STAFF)}, CASE WHEN l_returnflag = 'A' THEN 0 WHEN l_returnflag = 'N' THEN 1 ELSE 2 END AS y_natural,
           CASE WHEN {d.coin("concat('t|', k)", 0, 4)} % 100 < 4 * (sg + 1) THEN CAST({d.coin("concat('t|', k)", 4, 4)} % 2 AS INT)
                WHEN sg < 4 THEN CASE WHEN (z1 AND z3) OR z5 THEN 1 ELSE 0 END
                ELSE CASE WHEN (z1 <> z4) OR (z2 AND z3) THEN 1 ELSE 0 END END AS y
    FROM f"""


def credit(d: Dialect) -> str:
    letters = "length(text) - length(replace(text, '{}', ''))"

    def count(chars: str) -> str:
        return "(" + " + ".join(f"({letters.format(c)})" for c in chars) + ")"

    plain = d.count_of("text", "[A-Za-z0-9 .,;]")
    return f"""
    WITH t AS (
        SELECT d.doc_id, d.text, d.lang, d.source, l.quality, l.toxic, length(d.text) AS n, {d.words("d.text")} AS w, {d.distinct_words("d.text")} AS u
        FROM {d.table("documents")} d JOIN {d.table("labels")} l ON d.doc_id = l.doc_id),
    r AS (
        SELECT *, CASE WHEN n < 300 THEN 0 WHEN n < 800 THEN 1 WHEN n < 1500 THEN 2 WHEN n < 3000 THEN 3 ELSE 6 END AS len_raw,
               CASE WHEN w < 50 THEN 0 WHEN w < 130 THEN 1 WHEN w < 250 THEN 2 WHEN w < 500 THEN 3 ELSE 6 END AS words_raw,
               {floor_div("8 * u", "w")} AS vocab_raw, {floor_div("50 * " + d.count_of("text", "[A-Z]"), "greatest(n, 1)")} AS upper_raw,
               {floor_div("50 * " + count(".,;"), "greatest(n, 1)")} AS punct_raw, {floor_div("50 * " + d.count_of("text", "[0-9]"), "greatest(n, 1)")} AS digit_raw,
               {floor_div(letters.format("' || chr(10) || '").replace("'' || chr(10) || ''", "chr(10)"), "3")} AS lines_raw,
               {floor_div(f"20 * (n - {plain})", "greatest(n, 1)")} AS accent_raw, {floor_div("n", "w")} AS word_raw
        FROM t)
    SELECT doc_id AS id, CASE WHEN lang = 'en' THEN 0 WHEN lang = 'de' THEN 1 ELSE 2 END AS sg, quality AS y, toxic AS y_toxic,
           {floor_div("len_raw", "3")} AS len_band, {floor_div("words_raw", "3")} AS words_band,
           CASE WHEN vocab_raw <= 4 THEN 0 WHEN vocab_raw <= 6 THEN 1 ELSE 2 END AS vocab_ratio, least(2, upper_raw) AS upper_ratio,
           least(2, punct_raw) AS punct_ratio, least(1, digit_raw) AS digit_ratio, {floor_div("least(7, lines_raw)", "3")} AS lines_band,
           least(2, accent_raw) AS accent_ratio, greatest(0, least(2, word_raw - 4)) AS word_len,
           CASE WHEN text LIKE '%|%' THEN 1 ELSE 0 END AS has_pipe, CASE WHEN text LIKE '%###%' OR text LIKE '%***%' THEN 1 ELSE 0 END AS has_junk,
           CASE WHEN text LIKE '%@%' THEN 1 ELSE 0 END AS has_at, CASE WHEN text LIKE '%://%' THEN 1 ELSE 0 END AS has_url,
           {floor_div("CAST(substr(source, 4) AS INT) % 9", "3")} AS source_group, CAST(least(2, doc_id % 5) AS INT) AS doc_mod
    FROM r"""


def logic(d: Dialect, wide: bool, groups: int | None = None) -> str:
    n_x, n_z = (6, 7) if wide else (5, 5)
    rates = (30, 45, 60) if wide else (30, 45)
    x = [f"CAST({d.coin('kx', j, 1)} % 4 AS INT) AS x{j}" for j in range(n_x)]
    z = [f"CAST({d.coin('kz', j, 1)} % 4 AS INT) AS z{j}" for j in range(n_z)]
    first = d.xor("x2", "x3") if not wide else d.xor("x0", "x1")
    clean = f"(x0 & x1) | {first}"
    if wide:
        clean = f"CASE WHEN sg < 2 THEN {first} & (x2 | x4) ELSE {d.xor('x0 & x3', 'x1 | x4')} END"
    c = [f"CASE WHEN {d.coin('kc', 8 * j, 4)} % 100 < {r} THEN CAST({d.coin('kc', 8 * j + 4, 2)} % 4 AS INT) ELSE clean END AS c{j}" for j, r in enumerate(rates)]
    red = ["x0 & x1 AS r0", "x2 | x3 AS r1", f"{d.xor('x4', 'x5' if wide else 'x0')} AS r2"] + (["x1 | x5 AS r3"] if wide else [])
    sg = "l_linenumber % 4" if groups is None else f"CAST({d.coin('concat(' + chr(39) + 'g|' + chr(39) + ', k)', 0, 6)} % {groups} AS INT)"
    return f"""
    WITH a AS (SELECT *, {ROW_KEY} AS k FROM {d.table("lineitem")}),
    b AS (SELECT k, CAST({sg} AS INT) AS sg, concat('x|', k) AS kx, concat('z|', k) AS kz, concat('c|', k) AS kc, concat('t|', k) AS kt FROM a),
    e AS (SELECT *, {", ".join(x + z)} FROM b),
    f AS (SELECT *, {clean} AS clean FROM e)
    SELECT k AS id, sg, {", ".join(f"x{j}" for j in range(n_x))}, {", ".join(c)}, {", ".join(red)}, {", ".join(f"z{j}" for j in range(n_z))},
           CASE WHEN {d.coin("kt", 0, 4)} % 100 < 10 * (sg + 1) THEN CAST({d.coin("kt", 4, 2)} % 4 AS INT) ELSE clean END AS y
    FROM f"""


def view_sql(name: str, d: Dialect, groups: int | None = None) -> str:
    if name in ("v_scale", "v_logic20"):
        return logic(d, True, (groups or 4) if name == "v_scale" else None)
    return {"v_device": device, "v_staff": staff, "v_credit": credit, "v_logic15": lambda x: logic(x, False)}[name](d)


def view(spark: SparkSession, sf_dir: str, name: str, groups: int | None = None) -> DataFrame:
    text = view_sql(name, SPARK, groups)
    large = "documents" if name == "v_credit" else "lineitem"
    frames = {large: spread(table(spark, sf_dir, large))}
    if name == "v_staff":  # rows of lineitem are not sorted, and so not spilled, to meet their orders
        frames["orders"] = table(spark, sf_dir, "orders").hint("shuffle_hash")
    return sql(spark, sf_dir, text, **frames)


def duck_view(name: str, groups: int | None = None) -> str:
    return view_sql(name, DUCK, groups)
