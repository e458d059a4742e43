"""Encoding and decoding of whole documents, batch by batch in Arrow.

Defined results: a null text is the empty text, which has no ids; the string of an added
token inside a text becomes that token's id; ids decode to the bytes of their tokens, and
bytes that are not UTF-8 (ids that were not made by the encoder) to the replacement
character. Extra columns are not read; repeated rows are coded each; an empty table gives
no rows; very long texts are coded whole, batches being cut to about 8 MB of text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.llm.bpe import coder
from gapselect.llm.common import as_text


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def slices(batches: Iterator[pa.RecordBatch], text: int, most: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """The batches cut so that each holds about ``most`` bytes of text, whole rows always."""
    for b in batches:
        if not b.num_rows or b.column(text).nbytes <= most:
            yield b
            continue
        sizes = np.cumsum(pc.fill_null(pc.binary_length(b.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        i = 0
        while i < b.num_rows:
            done = sizes[i - 1] if i else 0
            j = max(i + 1, int(np.searchsorted(sizes, done + most, "right")))
            yield b.slice(i, j - i)
            i = j


def encode_documents(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids): ids as little-endian unsigned 32-bit integers in one binary value."""

    def run(batches):
        code = coder(vocabulary)
        for b in slices(batches, 1):
            out = [np.array(code.encode(t), "<u4").tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.binary())], names=["id", "ids"])

    made = docs.select(F.col(id_col).cast("long").alias("id"), as_text(text_col).alias("text")).mapInArrow(run, "id long, ids binary")
    return made.withColumnRenamed("id", id_col)


def decode_documents(encoded: DataFrame, vocabulary: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, ids, text): the texts of ids, by the offset table. Null ids decode to ''."""

    def run(batches):
        code = coder(vocabulary)
        for b in batches:
            out = [code.decode(np.frombuffer(x or b"", "<u4").astype(np.int64)) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(out, pa.string())], names=["id", "ids", "text"])

    made = encoded.select(F.col(id_col).cast("long").alias("id"), F.col(ids_col).alias("ids")).mapInArrow(run, "id long, ids binary, text string")
    return made.withColumnRenamed("id", id_col)
