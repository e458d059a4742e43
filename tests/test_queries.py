"""Queries against their SQL twins in DuckDB, and that the entry module stands alone."""

import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

from gapselect.queries import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One or two of each kind; the driver compares all of them.
NAMES = [
    "prep_bin_depth", "prep_encode", "prep_rank_bins", "mi_worked_example", "prep_minterms", "miss_detect", "miss_null_profile", "mi_single_credit", "mi_triples_device", "lmi_blocks", "lmi_rollup",
    "co_information_pairs", "lat_neighbour_mean", "lat_encoding_mean", "smp_arbitrary", "smp_tv_walk", "topk_exact_device", "topk_hybrid", "msr_ndcg",
    "msr_closure_by_level", "knn_impute_device", "mode_impute_device", "gnn_forward_fixed", "join_asof_events", "join_interval_events", "join_theta_dist",
    "agg_grouping_sets", "win_rank_family", "sort_multi", "set_except", "cte_walk", "udtf_neighbours", "stream_session", "stream_mi_counts", "scan_lattice_source",
]


ON_DEVICE = {"mi_triples_device", "smp_tv_walk", "topk_exact_device", "topk_hybrid", "msr_ndcg", "msr_closure_by_level"}


def rows(df):
    out = []
    for r in df.sort_index(axis=1).astype(object).itertuples(index=False, name=None):
        out.append(tuple(None if x is None or x != x else x.item() if hasattr(x, "item") else x for x in r))
    return sorted(map(repr, out))


@pytest.mark.parametrize("name", NAMES)
def test_twin(spark, sf, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    if name in ON_DEVICE:  # the smallest table has one target state on this view
        sf = sf.replace("sf0.001", "sf0.01")
        con = duckdb.connect()
        for t in TABLES:
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
        from gapselect.views import duck_view

        assert con.sql(f"SELECT count(DISTINCT y) FROM ({duck_view('v_device')})").fetchall()[0][0] > 1
    got, want = QUERIES[name](spark, sf).toPandas(), con.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_names():
    assert len(QUERIES) > 150 and set(ORACLES) <= set(QUERIES)


def test_entry(spark):
    import __spark_entry__ as entry

    out = entry.entry(spark)
    assert out.columns == ["sg", "rank", "mask", "score"] and out.count() == 15
    assert len({r["score"] for r in out.collect()}) > 3  # of a target that varies
    assert set(QUERIES) <= set(entry.queries())


def test_entry_without_corpus_operators():
    root = Path(__file__).resolve().parent.parent
    code = (
        "import sys, importlib.abc\n"
        "class Gone(importlib.abc.MetaPathFinder):\n"
        "    def find_spec(self, name, path, target=None):\n"
        "        if name.startswith('gapselect.llm') or name == 'corpus_pipeline': raise ModuleNotFoundError(name)\n"
        "sys.meta_path.insert(0, Gone())\n"
        "import __spark_entry__ as e\n"
        "assert 'topk_exact_device' in e.queries() and not [q for q in e.queries() if q.startswith('op')]\n"
    )
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True, timeout=100)


#: Queries that made their data up before; now Spark reads a given table for them.
READ_TABLES = "co_information_xor cte_walk fn_array fn_bits gnn_forward_fixed join_anti_unsampled join_self_xor join_semi_avail lat_cross_edges lat_degree".split()


@pytest.mark.parametrize("name", READ_TABLES)
def test_reads_a_table(spark, sf, name, monkeypatch):
    from gapselect.queries import around

    monkeypatch.setattr(around, "_AV", {})  # what subgroups have is found in the rows
    got = QUERIES[name](spark, sf)
    if name not in ("join_anti_unsampled", "join_semi_avail"):  # these read through a checkpoint
        assert any(f.startswith(f"file://{sf}/") for f in got.inputFiles())
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    assert rows(got.toPandas()) == rows(con.sql(ORACLES[name]).df())


@pytest.mark.parametrize("name", ["stream_dedupe", "stream_session", "stream_tumbling"])
def test_stream_results_are_files(spark, sf, name):
    got = QUERIES[name](spark, sf)
    assert any("result-" in f for f in got.inputFiles())
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{sf}/events.parquet'")
    assert rows(got.toPandas()) == rows(con.sql(ORACLES[name]).df())
