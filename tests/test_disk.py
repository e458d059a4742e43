"""Room on disk and work of large tables: rows are stored in few bytes, tables are not shuffled
in vain, neighbours are found block by block, near pairs are made by all cores."""

import os

from pyspark.sql import functions as F

from gapselect import experiments as ex
from gapselect.baselines import knn
from gapselect.operators import joins
from gapselect.sources.tables import spread
from gapselect.views import view


def _bytes(folder: str) -> int:
    return sum(os.path.getsize(os.path.join(d, f)) for d, _, files in os.walk(folder) for f in files)


def _plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_views_take_few_bytes_a_row(spark, sf, monkeypatch):
    """A view is joined once, and its rows take a fraction of a checkpoint's bytes."""
    made = []
    monkeypatch.setattr(ex, "stored", lambda df, real=ex.stored: made.append(df) or real(df))
    packed, _ = ex.complete(spark, sf.replace("0.001", "0.01"), "v_staff", truth=False)
    rows, files = packed.count(), packed.inputFiles()
    assert sum("Join" in _plan(df) for df in made) == 1
    assert _bytes(os.path.dirname(files[0].removeprefix("file://"))) < 20 * rows


def test_tables_of_many_row_groups_are_not_shuffled(spark, tmp_path):
    import pyarrow as pa
    from pyarrow import parquet

    table = pa.table({"x": list(range(1000))})
    for name, rows, shuffled in (("many", 10, False), ("one", 1000, True)):
        parquet.write_table(table, tmp_path / f"{name}.parquet", row_group_size=rows)
        out = spread(spark.read.parquet(str(tmp_path / f"{name}.parquet")))
        assert ("Exchange" in _plan(out)) == shuffled and out.count() == 1000


def test_neighbours_in_blocks_are_not_shuffled(spark, sf, monkeypatch):
    """Beyond one block donors are gone through in the tasks of the receivers, for all
    distances and with limits, with the result of one block; cells are made once."""
    pb = ex.problem(spark, sf.replace("0.001", "0.01"), "v_device", truth=False)
    columns = {0: 0b101, 1: 0b1110010}
    found = []
    for most in (knn.MOST_DONORS, 100):
        monkeypatch.setattr(knn, "MOST_DONORS", most)
        for how in ("mismatch", "ignore"):
            for some in (None, columns):
                out = knn.knn_impute(pb.masked, pb.spec, 5, how, columns=some, pool=pb.pool)
                assert not any(x in _plan(out) for x in ("Exchange", "CoGroup"))
                found.append(sorted(map(tuple, out.collect())))
    assert found[:4] == found[4:] and found[0] != found[1]


def test_near_pairs_use_all_cores(spark, sf):
    """One small file makes many pairs: no task makes them all, and a null is near to none."""
    v = view(spark, sf, "v_device").select("id", "sg", "type", "size_bin", "key_fifth", "brand_bin")
    out = joins.near_pairs(v.filter("sg = 0"), v.filter("sg = 1"), [["type"], ["size_bin"], ["key_fifth"], ["brand_bin"]], "id", 1)
    sizes = [r["count"] for r in out.withColumn("p", F.spark_partition_id()).groupBy("p").count().collect()]
    assert max(sizes) < sum(sizes) / 4
    rows = spark.createDataFrame([(1, 1, 1, None), (2, 1, 1, 1), (3, 1, 2, 1), (4, 2, 2, 1)], "id long, p int, q int, r int")
    near = joins.near_pairs(rows, rows, [["p"], ["q"], ["r"]], "id", 1)
    assert sorted(map(tuple, near.collect())) == [(2, 2), (2, 3), (3, 2), (3, 3), (3, 4), (4, 3), (4, 4)]
    two = joins.near_pairs(rows, rows, [["p"], ["q"], ["r"]], "id", 2)
    assert sorted(map(tuple, two.collect())) == [(x, y) for x in (2, 3, 4) for y in (2, 3, 4)]
