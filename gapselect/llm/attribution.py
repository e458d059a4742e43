"""Token counts of parts of documents, from one encoding of the whole document.

A document is encoded once. Token character spans are then joined with the spans of its
sections (or fields): both are sorted, so the interval join is two binary searches per
section. A token that crosses a border is given out by an explicit rule:

* ``start``: to the section that holds its first character,
* ``end``: to the section that holds its last character,
* ``split``: to every section it touches, by its share of characters; shares are
  doubles that sum to the token count.

Defined results: null text is empty, with one empty section; tokens inside one character
count at that character; sections may be empty and then have no tokens; tokens outside
every section are counted in none; repeated rows are counted each; extra columns are not
read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gapselect.llm.bpe import coder, fast_ids
from gapselect.llm.coding import slices
from gapselect.llm.common import as_text

SECTION = "array<struct<name:string,start:bigint,end:bigint>>"


def allocate(starts: np.ndarray, ends: np.ndarray, lo: np.ndarray, hi: np.ndarray, rule: str) -> np.ndarray:
    """Tokens of every section [lo, hi); spans of tokens ascend."""
    if rule == "start":
        return np.searchsorted(starts, hi, "left") - np.minimum(np.searchsorted(starts, lo, "left"), np.searchsorted(starts, hi, "left"))
    if rule == "end":
        last = np.maximum(ends - 1, starts)
        return np.searchsorted(last, hi, "left") - np.minimum(np.searchsorted(last, lo, "left"), np.searchsorted(last, hi, "left"))
    if rule != "split":
        raise ValueError(f"unknown rule {rule}")
    # Each character gets the sum over its tokens of 1 / width; sections sum characters.
    width = np.maximum(ends - starts, 1)
    size = int(max(ends.max(initial=0), hi.max(initial=0))) + 2
    change = np.zeros(size)
    np.add.at(change, starts, 1.0 / width)
    np.add.at(change, starts + width, -1.0 / width)
    total = np.concatenate([[0.0], np.cumsum(np.cumsum(change))])
    return total[hi] - total[np.minimum(lo, hi)]


def attribute_tokens(docs: DataFrame, vocabulary: str, sections: str | None = None, rule: str = "start", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, section, name, start, end, n_tokens): a row per section. ``sections`` names an
    array column of (name, start, end) in characters; without it, lines are the sections."""
    kind = "double" if rule == "split" else "long"

    def run(batches):
        code, ids_of = coder(vocabulary), fast_ids(vocabulary)
        for b in slices(batches, 1):
            out = [[] for _ in range(6)]
            given = b.column(2).to_pylist() if sections else None
            for row, (doc, text) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist())):
                first, end = code.spans(text, ids_of(text).astype(np.int64))
                if given is None:
                    hi = np.cumsum([len(x) + 1 for x in text.split("\n")])
                    hi[-1] -= 1
                    lo, names = np.concatenate([[0], hi[:-1]]), [str(k) for k in range(len(hi))]
                else:
                    spans = [s for s in given[row] or [] if s]
                    names = [s["name"] for s in spans]
                    lo = np.array([max(0, s["start"] or 0) for s in spans], np.int64)
                    hi = np.maximum(lo, [min(len(text), s["end"] if s["end"] is not None else len(text)) for s in spans]).astype(np.int64)
                n = allocate(first, end, lo, hi, rule) if len(lo) else []
                for col, values in zip(out, ([doc] * len(lo), range(len(lo)), names, lo, hi, n)):
                    col.extend(values)
            types = (pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.float64() if kind == "double" else pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, types)], names=["id", "section", "name", "start", "end", "n_tokens"])

    cols = [F.col(id_col).cast("long").alias("id"), as_text(text_col).alias("text")] + ([F.col(sections).cast(SECTION).alias("sections")] if sections else [])
    made = docs.select(*cols).mapInArrow(run, f"id long, section int, name string, start long, end long, n_tokens {kind}")
    return made.withColumnRenamed("id", id_col)


def field_text(fields: list[str], separator: str = "\n") -> tuple[Column, Column]:
    """Several columns as one text, and the sections that are these columns: counts of
    fields then are counts within one encoding of the joined text."""
    parts = [as_text(f) for f in fields]
    text = F.concat_ws(separator, *parts)
    spans, at = [], F.lit(0).cast("bigint")
    for f, p in zip(fields, parts):
        spans.append(F.struct(F.lit(f).alias("name"), at.alias("start"), (at + F.length(p)).alias("end")))
        at = at + F.length(p) + len(separator)
    return text, F.array(*spans)
