"""Jaccard self-join on word n-gram sets by a prefix tree, and its components.

Sets that are equal are one node. A set that links to another shares at least
``ceil(t * size)`` of its shingles with it, so it misses at most ``p - 1`` of any of them,
``p = size - ceil(t * size) + 1``. Two exact consequences carry the plan:

1. *Sieve.* Of any ``s`` shingles of a linked set, ``s - p + 1`` occur in some other set.
   Every set sends its ``s = 1.5 p`` smallest fingerprints once; sets that have too few
   shared ones among them link with nothing and leave. Shingles seen twice inside one scan
   task are told to their sets there and travel as one flag, so a passage that a third of
   all documents hold costs one row per task.
2. *Prefix tree.* For the sets that stay, document frequencies are counted exactly and
   shingles put in one global order, frequent first. Sets are paths of a tree under that
   order, so near copies share long trunks. A path can only meet another one that links
   with it in one of its last ``p`` steps, the rare end; shingles that no other set has
   cannot match and only shorten that end. A shingle's group is the list of paths through
   it there.

Groups are not expanded into pairs. A few pivots per group are compared with all members
(rows, not squares) and components follow, for large groups turn by turn with other pivots
while that closes a good part of what is open. Of what is then still open, groups of up to
``TREES`` members make each pair that can link once; larger ones are closed as a whole: the
members outside the group's largest component are the queries, all members,
their paths cut behind the group's shingle, are the tree, and only the links that join
components come out.

Trees are sorted paths, which is their depth-first order, with the trunk that each shares
with the one before. All queries of a tree walk through it together: overlaps counted on a
trunk are kept for all paths below it, and a subtree is left as soon as no query's overlap
so far plus the remaining length can reach its bound. Trees and queries meet in blocks of
about ``BLOCK`` sets, so memory does not grow with a group, and groups of a hot shingle are
dealt out over tasks. No cap: every pair that could link is either compared or already
connected.

Defined results: null, empty and blank texts have no shingles and link with nothing; texts
of fewer words than ``width`` have one; repeated rows link through their equal sets, and
rows that repeat an id with other texts are documents of their own; a null id is larger
than any other; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gapselect.llm.common import as_text, counted, distinct_ids, durable, few, numbered, release, written
from gapselect.llm.components import connected_components
from gapselect.llm.shingles import mix, shingle_sets

WIDTH, PERCENT = 4, 85
#: Groups with more members than this get further turns of pivots before the last stage.
LARGE = 16
#: Paths of a tree, queries of a tree, and members of a shingle's group, that go together.
BLOCK = 128
#: Members from which on the open rest of a group is compared in trees of the whole group.
TREES = 1024
#: Sets, pairs of them, and shingles that a task takes where there are few.
TASK, TOKENS = 4000, 200_000
#: Cells of the table of shingles by queries that a walk holds at once.
_CELLS = 1 << 24
#: Bits of the filter of sets that may link, by their number; beyond it more sets pass, which
#: the join with the sets themselves then drops.
FILTER_BITS = (1 << 16, 1 << 24)
_SALT = np.uint64(0xD1B54A32D192ED03)


def _prefix(n, percent: int):
    return n + (-percent * n // 100) + 1  # n - ceil(percent * n / 100) + 1


def set_key(tokens: np.ndarray) -> bytes:
    a = mix(tokens ^ _SALT).sum(dtype=np.uint64)
    b = np.bitwise_xor.reduce(mix(tokens + _SALT)) + np.uint64(len(tokens))
    return np.array([a, b], "<u8").tobytes()


def _node(key: bytes) -> int:
    return int.from_bytes(key[:8], "little") >> 1


def set_rows(docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, n, key, mark): size, 128-bit key and a 63-bit mark of every document's set;
    key and mark are null for none."""

    def run(batches):
        for b in batches:
            n, keys, marks = np.zeros(b.num_rows, np.int64), [None] * b.num_rows, [None] * b.num_rows
            for row, tokens in shingle_sets(b.column(1), width):
                n[row] = len(tokens)
                if len(tokens):
                    keys[row] = set_key(tokens)
                    marks[row] = _node(keys[row])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n), pa.array(keys, pa.binary()), pa.array(marks, pa.int64())], names=["doc_id", "n", "key", "mark"])

    return docs.mapInArrow(run, "doc_id long, n long, key binary, mark long")


def _sieve(docs: DataFrame, total: int, width: int, percent: int) -> DataFrame:
    """mark of every set that may link; total: shingles of all documents."""

    def offer(batches):
        from pyspark import TaskContext

        task = TaskContext.get().partitionId()
        seen: set[int] = set()
        tokens, nodes, needs, sizes = [], [], [], []
        count = 0

        def flush():
            t, where = np.concatenate(tokens), np.repeat(np.arange(len(nodes)), sizes)
            order = np.argsort(t, kind="stable")
            st = t[order]
            same = np.zeros(len(st), bool)
            same[1:] = st[1:] == st[:-1]
            shared = same.copy()
            shared[:-1] |= same[1:]
            node = np.array(nodes, np.int64)
            live = np.bincount(where[order][shared], minlength=len(nodes)).astype(np.int32)
            flags, alone = st[shared & ~same], np.sort(order[~shared])  # by document, so that its rows stay together
            none, zero = np.int64(-1), np.int32(0)
            cols = (
                np.concatenate([t[alone], flags, mix(node.astype(np.uint64))]).view(np.int64),
                np.concatenate([node[where[alone]], np.full(len(flags), none), node]),
                np.concatenate([np.full(len(alone) + len(flags), zero), live]).astype(np.int32),
                np.concatenate([np.full(len(alone) + len(flags), zero), np.array(needs, np.int32)]).astype(np.int32),
            )
            out = pa.RecordBatch.from_arrays([pa.array(c) for c in cols] + [pa.array(np.full(len(cols[0]), task * 4096 + block % 4096, np.int64))], names=["token", "node", "live", "need", "task"])
            for k in range(0, out.num_rows, 50_000):
                yield out.slice(k, 50_000)

        block = 0
        for b in batches:
            for _, found in shingle_sets(b.column(0), width):
                if not len(found):
                    continue
                node = _node(set_key(found))
                if node in seen:
                    continue
                seen.add(node)
                p = _prefix(len(found), percent)
                s = min(len(found), p + (p + 1) // 2)
                tokens.append(found[:s]), nodes.append(node), sizes.append(s), needs.append(s - p + 1)
                count += s
                if count > 400_000:
                    yield from flush()
                    block += 1
                    tokens, nodes, needs, sizes, count = [], [], [], [], 0
        if nodes:
            yield from flush()

    def hits(t, v, k):
        """(set, task) of the rows, sorted by shingle and set, whose shingle is in two sets or
        is flagged; a flag (-1) stands for two."""
        first = np.r_[True, t[1:] != t[:-1]]
        other = np.r_[True, (v[1:] != v[:-1])] | first
        group = np.cumsum(first) - 1
        kinds = np.bincount(group[other]) + np.bincount(group[v == -1], minlength=int(group[-1]) + 1)
        hit = (kinds[group] > 1) & (v != -1)
        return v[hit], k[hit]

    def meet(batches):
        # What is carried on of a shingle that goes on in the next batch: the rows of its one
        # set so far, at most one a scan task; or a flag, once it has two.
        t, v, k = (np.zeros(0, np.int64) for _ in range(3))
        for b in batches:
            token, node, live, need, task = (b.column(i).to_numpy(zero_copy_only=False) for i in range(5))
            posting = need == 0
            t, v, k = (np.concatenate([x, y[posting]]) for x, y in ((t, token), (v, node), (k, task)))
            found, runs = np.zeros(0, np.int64), np.zeros(0, np.int64)
            if len(t):
                cut = int(np.flatnonzero(np.r_[True, t[1:] != t[:-1]])[-1])
                if v[-1] == -1 or v[cut] != v[-1]:
                    found, runs = hits(t, v, k)
                    t, v, k = t[-1:], np.full(1, -1, np.int64), k[-1:]
                else:
                    if cut:
                        found, runs = hits(t[:cut], v[:cut], k[:cut])
                    t, v, k = t[cut:], v[cut:], k[cut:]
            own = ~posting
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate(c)) for c in ((found, node[own]), (runs, task[own]), (np.ones(len(found), np.int64), live[own].astype(np.int64)), (np.zeros(len(found), np.int64), need[own].astype(np.int64)))],
                names=["node", "task", "live", "need"],
            )

    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), total // 4 // 500_000 + 1)
    sent = docs.select("text").mapInArrow(offer, "token long, node long, live int, need int, task long")
    told = sent.repartition(parts, "token").sortWithinPartitions("token", "node").mapInArrow(meet, "node long, task long, live long, need long")
    able = told.groupBy("node", "task").agg(F.sum("live").alias("live"), F.max("need").alias("need")).filter("live >= need")
    return able.select(F.col("node").alias("mark")).distinct()


def _filter_of(marks: DataFrame, n: int) -> np.ndarray:
    """A one-hash filter of ``n`` marks, at most 2 MB, gathered by its words."""
    bits = min(FILTER_BITS[1], max(FILTER_BITS[0], 1 << (16 * n).bit_length()))
    slot = marks.select(F.expr(f"mark % {bits}").alias("slot"))
    words = slot.selectExpr("int(slot div 64) AS w", "shiftleft(1L, int(slot % 64)) AS b").groupBy("w").agg(F.bit_or("b").alias("b")).toArrow()
    out = np.zeros(bits // 64, np.int64)
    out[words.column("w").to_numpy()] = words.column("b").to_numpy()
    return np.unpackbits(out.view(np.uint8), bitorder="little").astype(bool)


def _candidate_sets(docs: DataFrame, passing: np.ndarray, width: int) -> DataFrame:
    """(key, n, tokens) of the sets that the filter lets pass, once per scan task."""

    def run(batches):
        seen: set[bytes] = set()
        for b in batches:
            rows = []
            for _, tokens in shingle_sets(b.column(0), width):
                if not len(tokens) or (key := set_key(tokens)) in seen or not passing[_node(key) % len(passing)]:
                    continue
                seen.add(key)
                rows.append((key, len(tokens), tokens.view(np.int64)))
            for k in range(0, len(rows), 500):
                part = rows[k : k + 500]
                ends = np.cumsum([0, *(r[1] for r in part)])
                tokens = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([r[2] for r in part])))
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in part], pa.binary()), pa.array([r[1] for r in part], pa.int64()), tokens], names=["key", "n", "tokens"])

    return docs.select("text").mapInArrow(run, "key binary, n long, tokens array<long>")


class PrefixTree:
    """Sets of sizes ``sizes`` as sorted paths of a tree."""

    def __init__(self, paths: list[np.ndarray], sizes: np.ndarray):
        self.paths, self.sizes = paths, sizes
        self.ends = np.cumsum([0, *map(len, paths)])
        self.flat = np.concatenate(paths)
        self.shared = [0]  # steps that a path has in common with the one before
        for x, y in zip(paths, paths[1:]):
            k = min(len(x), len(y))
            apart = x[:k] != y[:k]
            at = int(apart.argmax()) if k else 0
            self.shared.append(at if k and apart[at] else k)

    def walk(self, queries: list[np.ndarray], sizes: np.ndarray, percent: int) -> np.ndarray:
        """Which path links with which query: one depth-first walk of all queries."""
        known = np.unique(np.concatenate(queries))
        step = max(1, _CELLS // (len(known) + 1))
        if step < len(queries):
            return np.concatenate([self.walk(queries[k : k + step], sizes[k : k + step], percent) for k in range(0, len(queries), step)], axis=1)
        held = np.zeros((len(known) + 1, len(queries)), np.uint8)
        for q, tokens in enumerate(queries):
            held[np.searchsorted(known, tokens), q] = 1
        at = np.minimum(np.searchsorted(known, self.flat), len(known) - 1)
        at[known[at] != self.flat] = len(known)  # the row of no query
        lengths = np.array([len(q) for q in queries])
        need = -(-percent * (self.sizes[:, None] + sizes[None, :]) // (100 + percent))
        kept = np.zeros((int(np.diff(self.ends).max()) + 1, len(queries)), np.int32)  # overlaps after each step of the trunk
        out, depth = np.zeros(need.shape, bool), 0
        for i in range(len(self.paths)):
            a, b = self.ends[i], self.ends[i + 1]
            k = min(self.shared[i], depth)
            if (kept[k] + np.minimum(b - a - k, lengths - kept[k]) < need[i]).all():
                depth = k
                continue
            np.cumsum(held[at[a + k : b]], axis=0, dtype=np.int32, out=kept[k + 1 : b - a + 1])
            kept[k + 1 : b - a + 1] += kept[k]
            out[i] = kept[b - a] >= need[i]
            depth = int(b - a)
        return out


def _walked(trees: DataFrame, percent: int, spanning: bool) -> DataFrame:
    """(a, b, ok) of every path a and query b of a tree; with ``spanning`` only those links
    that join components, each of a block once.

    trees: tree, part, is_path, node, n, comp, tokens; the queries of a part go through
    its paths.
    """

    def joined(queries, paths):
        tree = PrefixTree([p[3] for p in paths], np.array([p[1] for p in paths]))
        ok = tree.walk([q[3] for q in queries], np.array([q[1] for q in queries]), percent)
        if not spanning:
            return [(p[0], q[0], bool(ok[i, k])) for i, p in enumerate(paths) for k, q in enumerate(queries)]
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while root.setdefault(x, x) != x:
                x = root[x]
            return x

        out = []
        for i, k in zip(*np.nonzero(ok)):
            x, y = find(paths[i][2]), find(queries[k][2])
            if x != y:
                root[x] = y
                out.append((paths[i][0], queries[k][0], True))
        return out

    def run(batches):
        key, queries, paths = None, [], []

        def batch(rows):
            a, b, ok = zip(*rows)
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(ok, pa.bool_())], names=["a", "b", "ok"])

        for rows in batches:
            tree, part, is_path, node, n, comp = (rows.column(k).to_pylist() for k in range(6))
            flat, ends = rows.column(6).values.to_numpy(), rows.column(6).offsets.to_numpy()
            for i in range(rows.num_rows):
                if (tree[i], part[i]) != key:
                    if queries and paths and (found := joined(queries, paths)):
                        yield batch(found)
                    key, queries, paths = (tree[i], part[i]), [], []
                (paths if is_path[i] else queries).append((node[i], n[i], comp[i], flat[ends[i] : ends[i + 1]].copy()))
        if queries and paths and (found := joined(queries, paths)):
            yield batch(found)

    ordered = trees.select("tree", "part", "is_path", "node", "n", "comp", "tokens").repartition("tree", "part").sortWithinPartitions("tree", "part", "is_path", "tokens")
    return ordered.mapInArrow(run, "a long, b long, ok boolean")


def _parts(count) -> str:
    return f"int(({count} - 1) div {BLOCK} + 1)"


def _compare(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b, ok) of the pairs (a, b); b is the query, the sets of its a are its tree."""
    pairs, rows = counted(pairs.select("a", "b"))
    sizes = written(few(pairs.groupBy("b").agg(F.expr(_parts("count(1)")).alias("parts")), rows))
    dealt = pairs.join(sizes.filter("parts > 1"), "b", "left").withColumn("part", F.coalesce(F.expr("pmod(xxhash64(a), parts)"), F.lit(0)))
    paths = dealt.select(F.col("b").alias("tree"), "part", F.lit(1).alias("is_path"), F.col("a").alias("node"))
    queries = sizes.select(F.col("b").alias("tree"), F.expr("explode(sequence(0L, bigint(parts - 1)))").alias("part"), F.lit(0).alias("is_path"), F.col("b").alias("node"))
    trees = few(queries.unionByName(paths).join(sets, "node"), 2 * rows, TASK)
    return few(_walked(trees.withColumn("comp", F.col("node")), percent, False), rows, TASK)


def _fits(x: str, y: str, percent: int):
    """Whether two paths that first meet here, from the rare end, can still link: what is
    left of either one, this step included, must reach the overlap that their sizes ask."""
    return (100 + percent) * F.least(f"{x}left", f"{y}left") >= percent * (F.col(f"{x}n") + F.col(f"{y}n"))


def _able_to_link(group: DataFrame, percent: int) -> DataFrame:
    """Rows of groups without those that fit no other member. ``top`` is the largest size
    that a path's rest can still link with; sizes of the group, and what its members reach,
    bound it from both sides. A pair that links fits where it last meets, so it stays there."""
    group, rows = counted(group.withColumn("top", F.expr(f"((100 + {percent}) * left - {percent} * n) div {percent}")))
    ends = group.groupBy("token").agg(F.min("n").alias("least"), F.max("top").alias("most"), F.count(F.lit(1)).alias("m")).filter("m > 1 AND most >= least").drop("m")
    ends = written(few(ends, rows))
    return few(group.join(ends, "token").filter("top >= least AND n <= most").drop("top", "least", "most"), rows)


def components_of_links(links: DataFrame, per_task: int = 200_000) -> DataFrame:
    """(node, component) of the nodes of links (a, b). Tasks first join what they hold, at
    most about ``per_task`` links each, into stars; where more than one task was needed,
    the stars meet in rounds over all of them."""

    def contract(batches):
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while root[x] != x:
                root[x] = root[root[x]]
                x = root[x]
            return x

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ra, rb = find(root.setdefault(a, a)), find(root.setdefault(b, b))
                root[max(ra, rb)] = min(ra, rb)
        nodes = np.fromiter(root, np.int64, len(root))
        yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(np.fromiter(map(find, root), np.int64, len(root)))], names=["node", "component"])

    parts = links.count() // per_task + 1
    stars = links.select("a", "b").coalesce(parts).mapInArrow(contract, "node long, component long")
    if parts == 1:
        return stars
    return connected_components(stars.select(F.col("node").alias("u"), F.col("component").alias("v")))


def _blocks_of(tokens: DataFrame) -> DataFrame:
    """A row for each block of the group of a shingle."""
    return tokens.withColumn("block", F.expr("explode(sequence(0, blocks - 1))")).drop("blocks")


def _still_open(group: DataFrame, links: DataFrame, rows: int) -> DataFrame:
    """Rows of groups that hold more than one component, with components by ``links``.
    Groups of two are done once a pivot was compared with the other member."""
    label = components_of_links(links)
    named = group.drop("comp", "m").join(label, "node", "left").withColumn("comp", F.coalesce("component", "node"))
    named = written(few(named.drop("component"), rows))
    several = named.groupBy("token").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1"), F.count(F.lit(1)).alias("m"), F.max("blocks").alias("blocks")).filter("c0 <> c1 AND m > 2")
    several = _blocks_of(few(several.select("token", "m", "blocks"), rows))
    return written(few(named.join(several, ["token", "block"]), rows))


def _once(met: DataFrame) -> DataFrame:
    """(a, b) of the pairs of a member x and a query q, each pair once."""
    return met.groupBy(F.least("x", "q").alias("lo"), F.greatest("x", "q").alias("hi")).agg(F.min("q").alias("b")).select(F.expr("if(b = lo, hi, lo)").alias("a"), "b")


def _pivot_pairs(group: DataFrame, turn: int, pivots: int, percent: int, rows: int) -> DataFrame:
    """Pairs of every member with its group's pivots, where not yet connected."""
    picks = [F.min(F.struct(F.xxhash64("node", F.lit(turn * pivots + k)).alias("h"), "node", "n", "left", "comp")).alias(f"p{k}") for k in range(pivots)]
    chosen = group.groupBy("token").agg(*picks, F.min("comp").alias("c0"), F.max("comp").alias("c1"), F.max("blocks").alias("blocks")).filter("c0 <> c1")
    each = _blocks_of(few(chosen, rows).select("token", "blocks", F.explode(F.array(*[f"p{k}" for k in range(pivots)])).alias("p")))
    met = group.join(each, ["token", "block"]).filter((F.col("comp") != F.col("p.comp")) & _fits("", "p.", percent))
    return few(_once(few(met.select(F.col("node").alias("x"), F.col("p.node").alias("q")), pivots * rows)), pivots * rows)


def _open_pairs(group: DataFrame, rows: int) -> tuple[int, int]:
    """Pairs that the last stage would have to look at (members outside their group's
    largest component times the group), and rows."""
    sized = few(group.groupBy("token", "comp").agg(F.count(F.lit(1)).alias("k")), rows).groupBy("token").agg(F.sum("k").alias("all"), F.max("k").alias("main"))
    return tuple(few(sized, rows).agg(F.coalesce(F.sum((F.col("all") - F.col("main")) * F.col("all")), F.lit(0)), F.coalesce(F.sum("all"), F.lit(0))).first())


def _rest_pairs(group: DataFrame, ordered: DataFrame, percent: int, rows: int) -> DataFrame:
    """All pairs of a group that are not connected: of members outside the group's largest
    component with every other member. A pair is made once, where its paths first meet from
    the rare end: the steps behind this one, which are few, must have nothing in common."""
    sized = few(group.groupBy("token", "comp").agg(F.count(F.lit(1)).alias("m"), F.max("blocks").alias("blocks")), rows)
    top = sized.groupBy("token").agg(F.max(F.struct("m", "comp")).alias("top"), F.count(F.lit(1)).alias("k"), F.max("blocks").alias("blocks")).filter("k > 1")
    low = F.ceil(percent * F.col("n") / 100).cast("int")
    tails = ordered.select("node", F.slice("tokens", low, F.size("tokens")).alias("tail"))
    placed = group.select("node", "n", "token", "left", "comp", "block", "blocks").join(tails, "node")
    placed = written(few(placed.withColumn("behind", F.slice("tail", F.col("left") - low + 2, F.size("tail"))).drop("tail"), rows, TASK))
    out = placed.join(_blocks_of(few(top, rows).select("token", F.col("top.comp").alias("main"), "blocks")), ["token", "block"]).filter("comp <> main")
    x = out.drop("block").withColumn("block", F.expr("explode(sequence(0, blocks - 1))")).alias("x")
    y = placed.alias("y")
    new = (F.col("x.comp") != F.col("y.comp")) & _fits("x.", "y.", percent) & ~F.arrays_overlap("x.behind", "y.behind")
    met = x.join(y, (F.col("x.token") == F.col("y.token")) & (F.col("x.block") == F.col("y.block"))).filter(new)
    return _once(met.select(F.col("y.node").alias("x"), F.col("x.node").alias("q")))


def _rest_links(group: DataFrame, ordered: DataFrame, percent: int, rows: int) -> DataFrame:
    """Links (a, b) that join components of a group: its members outside the largest one
    walk through the tree of all members. Where a pair links, the group of its last common
    step sees its whole overlap, so paths and queries are cut behind their group's step."""
    sized = few(group.groupBy("token", "comp").agg(F.count(F.lit(1)).alias("m"), F.max("blocks").alias("blocks")), rows)
    top = sized.groupBy("token").agg(F.max(F.struct("m", "comp")).alias("top"), F.sum("m").alias("m"), F.count(F.lit(1)).alias("k"), F.max("blocks").alias("blocks")).filter("k > 1")
    top = _blocks_of(top.selectExpr("token", "top.comp AS main", f"{_parts('m - top.m')} AS parts", "blocks"))
    open_rows = written(few(group.select("token", "block", "blocks", "node", "n", "left", "comp").join(top, ["token", "block"]), rows))
    queries = open_rows.filter("comp <> main").withColumn("own", F.expr("pmod(xxhash64(node, 1), parts)")).withColumn("block", F.expr("explode(sequence(0, blocks - 1))"))
    paths = open_rows.withColumn("own", F.expr("explode(sequence(0L, bigint(parts - 1)))"))
    cols = [F.col("token").alias("tree"), F.expr("block * bigint(parts) + own").alias("part"), "node", "n", "left", "comp"]
    both = queries.select(*cols, F.lit(0).alias("is_path")).unionByName(paths.select(*cols, F.lit(1).alias("is_path")))
    trees = both.join(ordered.select("node", "tokens"), "node").withColumn("tokens", F.slice("tokens", F.lit(1), F.col("left")))
    return written(_walked(trees, percent, True))


def link_components(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text", pivots: int = 2, turns: int = 2) -> DataFrame:
    """doc_id, n_shingles, component_id: smallest doc_id reachable by links."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), as_text(text_col).alias("text"))
    rows = written(set_rows(texts, width).withColumn("row", F.monotonically_increasing_id()))
    total, texts_n = rows.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    nodes = written(few(rows.filter("key IS NOT NULL").groupBy("key", "mark").agg(F.min("row").alias("node"), F.min("doc_id").alias("least")), texts_n))
    known = nodes.select("key", "least")
    able, many = counted(few(_sieve(texts, total, width, percent), texts_n))
    release(docs.sparkSession)
    if many:
        found = _candidate_sets(texts, _filter_of(able, many), width).groupBy("key").agg(F.first("n").alias("n"), F.first("tokens").alias("tokens"))
        sets = durable(few(found.join(few(nodes.join(able, "mark", "left_semi"), many), "key").select("node", "n", "tokens"), many, TASK))
        del found
        release(docs.sparkSession)
        label = _components_of(sets, percent, pivots, turns)
        if label is not None:
            named, linked_n = counted(few(nodes.join(label, "node").select("key", "least", "component"), many))
            first = written(few(named.groupBy("component").agg(F.min("least").alias("first")), linked_n))
            linked = written(few(named.join(first, "component").select("key", "first"), linked_n))
            known = written(few(nodes.join(linked, "key", "left").select("key", F.coalesce("first", "least").alias("least")), texts_n))
    out = few(rows.join(known, "key", "left"), texts_n)
    return out.select(F.col("doc_id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("least", "doc_id").alias("component_id"))


def _components_of(sets: DataFrame, percent: int, pivots: int, turns: int, most_turns: int = 10) -> DataFrame | None:
    """(node, component) of the nodes that link; None if there are none."""
    held, many = sets.agg(F.coalesce(F.sum(F.size("tokens")), F.lit(0)), F.count(F.lit(1))).first()
    every = sets.select("node", "n", F.explode("tokens").alias("token"))
    common = few(every.groupBy("token").agg(F.count(F.lit(1)).alias("df")).filter("df > 1"), held, TOKENS)
    # A shingle's number is its place in the one global order, frequent first.
    common = written(common.orderBy(F.desc("df"), "token").select("token", F.monotonically_increasing_id().alias("step")))
    shared = few(every.join(common, "token"), held, TOKENS).groupBy("node", "n").agg(F.sort_array(F.collect_list("step")).alias("tokens"))
    # ceil(percent * n / 100) shared shingles at least; the others of the set are in no other set
    ordered = durable(few(shared.filter(100 * F.size("tokens") >= percent * F.col("n")).select("node", "n", "tokens"), many, TASK))
    del every, common, shared
    release(sets.sparkSession)
    # a step further than ceil(percent * n / 100) from the trunk is where a path may first meet another
    low = F.ceil(percent * F.col("n") / 100).cast("int")
    held = ordered.agg(F.coalesce(F.sum(F.size("tokens") - low + 1), F.lit(0))).first()[0]
    steps = ordered.select("node", "n", low.alias("low"), F.posexplode(F.slice("tokens", low, F.size("tokens"))).alias("k", "token"))
    group = steps.select("node", "n", "token", (F.col("low") + F.col("k")).alias("left"))
    group = _able_to_link(group, percent)
    # Of groups with the same members only that of the last step is kept: their pairs meet
    # there too, and their last common step is not before it. Sets are told apart by their
    # size and two 64-bit sums.
    members = [F.count(F.lit(1)).alias("m"), F.bit_xor(F.xxhash64("node")).alias("s0"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("s1")]
    several = few(group.groupBy("token").agg(*members).filter("m > 1"), held).groupBy("m", "s0", "s1").agg(F.max("token").alias("token"))
    several = written(few(several, held).selectExpr("token", f"{_parts('m')} AS blocks"))
    group, rows = counted(few(group.join(several, "token"), held).withColumn("block", F.expr("int(pmod(xxhash64(node), blocks))")).withColumn("comp", F.col("node")))
    if not rows:
        return None
    tried, links = None, None

    def compare(pairs: DataFrame, most: int | None = None) -> None:
        nonlocal tried, links
        if tried is not None:
            pairs = pairs.join(tried, (F.least("a", "b") == F.col("lo")) & (F.greatest("a", "b") == F.col("hi")), "left_anti")
            pairs = few(pairs, most) if most else pairs
        seen = written(_compare(pairs, ordered, percent))
        good, done = seen.filter("ok").select("a", "b"), seen.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi"))
        tried = done if tried is None else tried.unionByName(done)
        links = good if links is None else links.unionByName(good)

    for turn in range(turns):
        compare(_pivot_pairs(group, turn, pivots, percent, rows), pivots * rows)
        group = _still_open(group, links, rows)
    # Large groups get more turns while that closes a tenth or more of what is open there.
    large, before = group.filter(F.col("m") > LARGE), None
    for turn in range(turns, most_turns):
        now, left = _open_pairs(large, rows)
        if 2 * now <= left or before is not None and now > 0.9 * before:
            break
        before = now
        compare(_pivot_pairs(large, turn, 2 * pivots, percent, rows), 2 * pivots * rows)
        large = _still_open(large, links, rows)
    if before is not None:
        group = _still_open(group, links, rows)
    # What is still open: few members make few pairs, which cost ids; large groups go as trees.
    compare(_rest_pairs(group.filter(F.col("m") <= TREES), ordered, percent, rows))
    rest = _rest_links(group.filter(F.col("m") > TREES), ordered, percent, rows).select("a", "b")
    return written(components_of_links(links.unionByName(rest)))


def one_of_each(docs: DataFrame, width: int = WIDTH, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with one row of each component, that of the smallest id (of rows that
    repeat it, the first); rows without shingles all stay. Columns stay as they are."""
    if distinct_ids(docs, id_col):
        found = link_components(docs, width, percent, id_col, text_col)
        stay = found.filter((F.col("component_id") == F.col(id_col)) | F.col("component_id").isNull()).select(F.col(id_col).alias("__stay"))
        return docs.join(stay, docs[id_col].eqNullSafe(stay["__stay"]), "left_semi")
    rows, row = numbered(docs)
    found = written(link_components(rows, width, percent, row, text_col))
    least = rows.select(F.col(row).alias("at"), F.struct(F.col(id_col).isNull(), F.col(id_col), F.col(row).alias("at")).alias("place")).join(found.withColumnRenamed(row, "at"), "at")
    alone = found.filter("n_shingles = 0").select(row)
    stay = least.filter("n_shingles > 0").groupBy("component_id").agg(F.min("place").alias("place")).select(F.col("place.at").alias(row)).unionByName(alone)
    return rows.join(stay, row, "left_semi").drop(row)
