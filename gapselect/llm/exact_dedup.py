"""Exact duplicates by progressive refinement, with DataFrame functions only.

Texts are equal when identical after every run of ``[\\x20\\x09-\\x0D]`` became one
space. Three keys of growing cost decide: the length, a hash of the first characters,
and the full hash. Only groups that a cheaper key leaves with two rows or more go on to
the next one. Survivors reach the scan that hashes whole texts as a bit filter of at most
half a megabyte however large the input, so no text is ever shuffled;
bits that collide only cost a hash, never a wrong group.

Defined results: a null text counts as empty, and empty texts are equal to each other;
a null id orders last; of repeated rows exactly one is kept; an empty table gives an
empty result. Other columns, whatever their names, are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.llm.common import SPACES, as_text, distinct_ids, durable, numbered

PREFIX_CHARS = 128
#: Bits of the filter of surviving groups, by their number; once it is full, more rows are hashed.
FILTER_BITS = (1 << 16, 1 << 22)


def normalised(text_col: str = "text") -> Column:
    return F.regexp_replace(as_text(text_col), SPACES, " ")


def _bit_filter(keys: DataFrame, *cols: str) -> bytes:
    """A one-hash filter over ``cols`` with about 16 bits a key, within ``FILTER_BITS``."""
    bits = min(FILTER_BITS[1], max(FILTER_BITS[0], 1 << (16 * keys.count()).bit_length()))
    words = (
        keys.select(F.pmod(F.xxhash64(*cols), F.lit(bits)).alias("slot"))
        .selectExpr("int(slot div 64) AS w", "shiftleft(1L, int(slot % 64)) AS b")
        .groupBy("w")
        .agg(F.bit_or("b").alias("b"))
    )
    out = bytearray(bits // 8)
    for r in words.collect():
        out[8 * r["w"] : 8 * r["w"] + 8] = (r["b"] % (1 << 64)).to_bytes(8, "little")
    return bytes(out)


def _in_filter(filled: bytes, *cols: Column) -> Column:
    slot = F.pmod(F.xxhash64(*cols), F.lit(8 * len(filled)))
    byte = F.conv(F.hex(F.substring(F.lit(filled), F.shiftright(slot, 3).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    return F.call_function("bit_get", byte, slot.bitwiseAND(F.lit(7)).cast("int")) == 1


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", digest: bool = False, row_col: str | None = None) -> DataFrame:
    """One row per row of ``docs``: id, keep_id, group_size, kept and, with ``digest``,
    the SHA-256 of the normalised text, which else is taken of surviving groups alone.
    ``row_col`` names a column that numbers the rows, which then is returned too."""
    norm = normalised(text_col)
    size, prefix = F.length(norm), F.xxhash64(F.substring(norm, 1, PREFIX_CHARS))
    cheap = durable(docs.select(size.alias("size"), prefix.alias("prefix")).groupBy("size", "prefix").agg(F.count(F.lit(1)).alias("n")))
    by_size = cheap.groupBy("size").agg(F.sum("n").alias("n")).filter("n > 1").select("size")
    by_prefix = durable(cheap.join(by_size, "size", "left_semi").filter("n > 1").select("size", "prefix"))
    words = _bit_filter(by_prefix, "size", "prefix")
    full = F.sha2(norm, 256)
    rows = durable(
        docs.select(
            F.col(id_col).alias("id"), size.alias("size"), (F.col(row_col) if row_col else F.monotonically_increasing_id()).alias("row"),
            (full if digest else F.when(_in_filter(words, size, prefix), full)).alias("sha"),
            _in_filter(words, size, prefix).alias("open"),
        )
    )
    first = F.min(F.struct(F.col("id").isNull().alias("no"), F.col("id").alias("id"), F.col("row").alias("row")))
    # Written on its own, so that both sides of the join are plain exchanges and a hot group's rows are split.
    groups = durable(rows.filter("open").groupBy("size", "sha").agg(first.alias("first"), F.count(F.lit(1)).alias("n")).filter("n > 1"))
    joined = rows.alias("r").join(groups.alias("g"), (F.col("r.sha") == F.col("g.sha")) & (F.col("r.size") == F.col("g.size")), "left")
    return joined.select(
        F.col("r.id").alias(id_col),
        F.when(F.col("g.n").isNull(), F.col("r.id")).otherwise(F.col("g.first.id")).alias("keep_id"),
        F.coalesce(F.col("g.n"), F.lit(1)).cast("long").alias("group_size"),
        (F.col("g.n").isNull() | (F.col("r.row") == F.col("g.first.row"))).alias("kept"),
        *([F.col("r.sha").alias("text_sha256")] if digest else []), *([F.col("r.row").alias(row_col)] if row_col else []),
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that repeat an earlier text; columns stay as they are.

    Where some id is in two rows, rows are numbered first and decided one by one, so
    that also of whole rows that repeat exactly one stays.
    """
    if distinct_ids(docs, id_col):
        kept = exact_groups(docs, id_col, text_col).filter("kept").select(F.col(id_col).alias("__kept"))
        return docs.join(kept, docs[id_col].eqNullSafe(kept["__kept"]), "left_semi")
    rows, row = numbered(docs)
    kept = exact_groups(rows, id_col, text_col, row_col=row).filter("kept").select(row)
    return rows.join(kept, row, "left_semi").drop(row)
