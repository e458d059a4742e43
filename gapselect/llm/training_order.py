"""Training-order materialisation: token shards in one keyed global order.

Each scan task joins its documents (with an end token after each) into one stream and cuts
it into sequences of fixed length, the last one padded. A first pass counts sequences per
task, which numbers all sequences; a keyed Feistel permutation over ``[0, N)`` (balanced
rounds on the next even number of bits, walking the cycle until it is back inside) then
gives every sequence its slot. No two sequences share a slot and none stays free, so shard
``k`` is exactly the slots ``[k * per_shard, (k + 1) * per_shard)`` in order, and sequence
``s`` lies at byte ``(s % per_shard) * stride`` of its shard: reading on from any step
needs no index. The inverse permutation tells where a slot came from.

Sequences are dealt out by ranges of slots, one shard a task however large the input, and
sorted there. The task writes its shard under a name of the attempt and then moves it to
its final name, so a lost executor or a repeated task leaves whole shards only. Memory is
bounded by one Arrow batch.

Texts are encoded twice, once to count. Keeping the ids of the first pass would write them
a third time beside the exchange and the shards.

Defined results: null and empty texts add the end token alone; repeated rows are written
each; an empty table writes no shard and gives no rows; extra columns are not read. The
input has to give the same rows in the same order when read twice (files do; write other
inputs first): the second pass checks its counts and raises if they differ.
"""

from __future__ import annotations

import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.llm.bpe import fast_ids
from gapselect.llm.coding import slices
from gapselect.llm.common import as_text, durable, shared_dir
from gapselect.llm.shingles import mix

LENGTH, PER_SHARD, END_ID, ROUNDS = 1024, 4096, 50256, 6


class Feistel:
    """A keyed permutation of ``[0, n)`` on numpy arrays."""

    def __init__(self, n: int, key: int, rounds: int = ROUNDS):
        self.n = n
        self.half = max(1, (max(1, n - 1).bit_length() + 1) // 2)
        self.low = np.uint64((1 << self.half) - 1)
        self.keys = [mix(np.array([(key * 0x9E3779B97F4A7C15 + r + 1) % (1 << 64)], np.uint64))[0] for r in range(rounds)]

    def _once(self, x: np.ndarray, keys) -> np.ndarray:
        shift = np.uint64(self.half)
        left, right = x >> shift, x & self.low
        for k in keys:
            left, right = right, left ^ (mix(right ^ k) & self.low)
        return right << shift | left  # halves trade places at the end, so that the same walk with keys turned undoes it

    def _walk(self, x: np.ndarray, keys) -> np.ndarray:
        x = self._once(np.asarray(x, np.uint64), keys)
        while len(out := np.flatnonzero(x >= np.uint64(self.n))):
            x[out] = self._once(x[out], keys)
        return x.astype(np.int64)

    def slot(self, sequence: np.ndarray) -> np.ndarray:
        return self._walk(sequence, self.keys)

    def sequence(self, slot: np.ndarray) -> np.ndarray:
        return self._walk(slot, self.keys[::-1])


def _streams(batches, vocabulary: str, length: int, end_id: int):
    """(first document index, tokens) blocks of whole sequences: yields (matrix of
    sequences, documents of each), the last block padded."""
    ids_of = fast_ids(vocabulary)
    end = np.array([end_id], np.uint32)
    held, docs, total = [], [], 0

    def cut(last: bool):
        nonlocal held, docs, total
        n = -(-total // length) if last else total // length
        if not n:
            return None
        tokens = np.concatenate(held)
        used = min(total, n * length)
        block = np.full(n * length, end_id, np.uint32)
        block[:used] = tokens[:used]
        stops = np.cumsum([len(h) for h in held])
        edges = np.arange(n) * length
        first, last_doc = np.searchsorted(stops, edges, "right"), np.searchsorted(stops, np.minimum(edges + length, used) - 1, "right")
        sizes = last_doc - first + 1
        ends = np.concatenate([[0], np.cumsum(sizes)])
        at = np.arange(ends[-1]) - np.repeat(ends[:-1] - first, sizes)
        of = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(docs, pa.int64()).take(pa.array(at)))
        held, docs, total = ([tokens[used:]], [docs[-1]], total - used) if used < total else ([], [], 0)
        return block.reshape(n, length), of, used

    for b in slices(batches, 1):
        for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            ids = np.concatenate([ids_of(text), end])
            held.append(ids), docs.append(doc)
            total += len(ids)
            if total >= 256 * length and (out := cut(False)):
                yield out
    if out := cut(True):
        yield out


def write_order(docs: DataFrame, vocabulary: str, folder: str | None = None, key: int = 20240229, length: int = LENGTH, per_shard: int = PER_SHARD, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes the shards and gives a row per sequence: slot, shard, offset (bytes in its
    shard), n_tokens (without padding), ids_crc32, doc_ids and the shard's file.

    Token ids are little-endian, 16 bits wide if the vocabulary allows, else 32.
    """
    spark = docs.sparkSession
    folder = folder or f"{shared_dir(spark).rstrip('/')}/token-shards-{uuid.uuid4().hex}"
    width = 2 if _largest(vocabulary, end_id) < 1 << 16 else 4
    kind, stride = f"<u{width}", width * length
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), as_text(text_col).alias("text"))

    def count(batches):
        from pyspark import TaskContext

        ids_of, total = fast_ids(vocabulary), 0
        for b in slices(batches, 0):
            total += sum(ids_of.count(t) + 1 for t in b.column(0).to_pylist())
        yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int32()), pa.array([-(-total // length)], pa.int64())], names=["part", "n"])

    counted = {r["part"]: r["n"] for r in texts.select("text").mapInArrow(count, "part int, n long").collect()}  # a number per input split
    total = sum(counted.values())
    base, at = {}, 0
    for p in sorted(counted):
        base[p], at = at, at + counted[p]
    order = Feistel(max(1, total), key)

    def make(batches):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        at = base.get(part, 0)
        for block, of, used in _streams(batches, vocabulary, length, end_id):
            slots = order.slot(np.arange(at, at + len(block)))
            at += len(block)
            places = pa.array(np.arange(len(block) + 1) * stride, pa.int32())
            raw = pa.Array.from_buffers(pa.binary(), len(block), [None, places.buffers()[1], pa.py_buffer(block.astype(kind).tobytes())])
            sizes = np.full(len(block), length, np.int32)
            sizes[-1] = used - (len(block) - 1) * length
            yield pa.RecordBatch.from_arrays(
                [pa.array(slots), pa.array(slots // per_shard), pa.array(sizes), of, raw],
                names=["slot", "shard", "n_tokens", "doc_ids", "ids"],
            )
        if at - base.get(part, 0) != counted.get(part, 0):
            raise RuntimeError(f"input split {part} changed between two reads")

    def write(batches):
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)
        store.create_dir(root, recursive=True)
        out, name, final = None, "", ""
        for b in batches:
            raws = b.column(4).to_pylist()
            if raws and out is None:
                final = f"shard-{b.column(1)[0].as_py():08d}.bin"
                name = f"_{final}.{uuid.uuid4().hex}"
                out = store.open_output_stream(f"{root}/{name}")
            for raw in raws:
                out.write(raw)
            slots = b.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(slots % per_shard * stride), b.column(2), pa.array([zlib.crc32(r) for r in raws], pa.int64()), b.column(3), pa.array([final] * len(raws))],
                names=["slot", "shard", "offset", "n_tokens", "ids_crc32", "doc_ids", "file"],
            )
        if out is not None:
            out.close()
            store.move(f"{root}/{name}", f"{root}/{final}")

    made = texts.mapInArrow(make, "slot long, shard long, n_tokens int, doc_ids array<long>, ids binary")
    ranged = made.repartitionById(max(1, -(-total // per_shard)), F.col("shard").cast("int")).sortWithinPartitions("slot")
    index = "slot long, shard long, offset long, n_tokens int, ids_crc32 long, doc_ids array<long>, file string"
    return durable(ranged.mapInArrow(write, index)).withColumn("folder", F.lit(folder))


def _largest(vocabulary: str, end_id: int) -> int:
    return max(len(fast_ids(vocabulary).exact.tokens) - 1, end_id)


def read_sequences(folder: str, slots, length: int = LENGTH, per_shard: int = PER_SHARD, width: int = 2) -> np.ndarray:
    """Sequences of given slots: each one seek and one read of a fixed stride."""
    from pyarrow import fs

    store, root = fs.FileSystem.from_uri(folder) if "://" in folder or folder.startswith("file:") else (fs.LocalFileSystem(), folder)
    out = []
    for s in slots:
        with store.open_input_file(f"{root}/shard-{s // per_shard:08d}.bin") as f:
            out.append(np.frombuffer(f.read_at(width * length, s % per_shard * width * length), f"<u{width}"))
    return np.array(out)
