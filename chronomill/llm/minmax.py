"""Near-duplicate groups by min-max hashing with exact confirmation.

A document is the set of its k-word shingle hashes. Each of `HASHES` hash functions gives two signature values, the
minimum and the maximum, so the signature is twice as long as the hashing is costly; its values are cut into bands of
`ROWS`. Documents with equal sets become one node. Nodes that share a band value are compared in rounds:

1. each node with the chief of one of its band values (the node with the most company in all its band values), 2. with
the chiefs of its others, unless links of the first round lead both to one node, 3. among the nodes of a chief that
still are in several groups, every node outside the largest group with all nodes of other groups, in blocks. A comparison
intersects the full sets; after rounds 2 and 3 links are joined into groups. Pairs that already are in one group need no
comparison, so a family of n copies costs about n comparisons, and those that its chief does not link cost block
products, which emit links only. No bucket, group or number of partners is capped. A node with very many links (a hub)
is looked up by broadcast (`textscan.lookup`, bounded) or dealt out by salt, so that its links are spread over tasks.

Edge cases: null and empty texts have an empty set and stay alone; texts with fewer words than k are one shingle;
null ids count as the smallest; repeated rows are copies; rows with equal ids and different texts are kept apart while
grouping; an empty table gives no rows; further columns pass or are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from . import textscan as ts

HASHES = 40
ROWS = 4
#: Rows and shingles of a block (on average), and columns of shingles taken at a time, when sets are intersected in blocks.
BLOCK = 256
BLOCK_SHINGLES = 400_000
COLUMNS = 8192
LEAST_ID = -(1 << 63)

_random = np.random.default_rng(7_340_033)
# Odd multipliers and masks of the hash functions.
_times = _random.integers(0, 1 << 63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_masks = _random.integers(0, 1 << 63, HASHES, dtype=np.uint64)


def sets_of(column: pa.Array, k: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, sorted distinct shingle hashes, first of each row)."""
    for a, b, data, offsets in ts.slices(column):
        values, first = ts.shingles(ts.scan(data, offsets), k)
        yield a, b, *ts.distinct_per_document(values, first)


def signatures(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Minima and maxima of each non-empty set, one row each."""
    starts = first[:-1][np.diff(first) > 0]
    out = np.empty((len(starts), 2 * HASHES), np.uint64)
    if len(starts):
        with np.errstate(over="ignore"):
            for j in range(HASHES):
                h = (values ^ _masks[j]) * _times[j]
                h ^= h >> np.uint64(29)
                out[:, j] = np.minimum.reduceat(h, starts)
                out[:, HASHES + j] = np.maximum.reduceat(h, starts)
    return out


def banded(sig: np.ndarray, rows: int = ROWS) -> np.ndarray:
    """One hash for each band; bands have values of their own."""
    n = sig.shape[1] // rows
    with np.errstate(over="ignore"):
        out = np.tile(np.arange(1, n + 1, dtype=np.uint64) * np.uint64(ts.BASE), (len(sig), 1))
        for j in range(rows):
            out = ts.mix(out * np.uint64(ts.MIX_A) + sig[:, j : n * rows : rows])
    return out


def _signed(df: DataFrame, k: int) -> DataFrame:
    """node parts (d, s), set identity t, size n and bands of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, values, first in sets_of(batch.column("text"), k):
                sizes = np.diff(first)
                full = np.flatnonzero(sizes)
                sig = signatures(values, first)
                ident = np.zeros((2, b - a), np.uint64)
                if len(full):
                    starts = first[:-1][full]
                    with np.errstate(over="ignore"):
                        ident[0, full] = ts.mix(np.add.reduceat(ts.mix(values + np.uint64(1)), starts) + sizes[full].astype(np.uint64))
                        ident[1, full] = ts.mix(np.add.reduceat(ts.mix(values * np.uint64(ts.BASE)), starts))
                bands = banded(sig)
                per_row = np.concatenate([[0], np.cumsum(sizes > 0)]).astype(np.int32)
                lists = lambda m, kind: pa.ListArray.from_arrays(pa.array(per_row * m.shape[1], pa.int32()), pa.array(m.ravel().view(kind)))
                yield pa.RecordBatch.from_arrays(
                    [batch.column("d").slice(a, b - a), pa.array(ident[0].view(np.int64)), pa.array(ident[1].view(np.int64)), pa.array(sizes.astype(np.int64)), lists(bands, np.int64)],
                    ["d", "s", "t", "n", "bands"],
                )

    rows = df.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST_ID)).alias("d"), F.col("text").cast("string").alias("text"))
    return rows.transform(ts.mapped, run, "d long, s long, t long, n long, bands array<long>")


def _full_sets(df: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """node and set of the nodes in wanted (column node)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, values, first in sets_of(batch.column("text"), k):
                sizes = np.diff(first)
                full = np.flatnonzero(sizes)
                ident = np.zeros(b - a, np.uint64)
                if len(full):
                    with np.errstate(over="ignore"):
                        ident[full] = ts.mix(np.add.reduceat(ts.mix(values + np.uint64(1)), first[:-1][full]) + sizes[full].astype(np.uint64))
                yield pa.RecordBatch.from_arrays([batch.column("d").slice(a, b - a), pa.array(ident.view(np.int64)), pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(values.view(np.int64)))], ["d", "s", "members"])

    rows = df.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST_ID)).alias("d"), F.col("text").cast("string").alias("text"))
    ids = wanted.select(F.col("node.d").alias("d")).distinct()
    # Merged at every size, so that small inputs are dealt out as large ones are.
    got = rows.join(ids.hint("merge"), "d", "left_semi").transform(ts.mapped, run, "d long, s long, members array<long>")
    return got.select(F.struct("d", "s").alias("node"), "members").dropDuplicates(["node"])


def _linked(pairs: DataFrame, sets: DataFrame, percent: int, total: int) -> DataFrame:
    """Pairs (a, b) whose full sets have at least percent / 100 of their union in common; there are at most total pairs.
    The set of a node that is a in many pairs is copied once for each `bound` of them, and its pairs are dealt to the copies."""
    bound = max(256, total // ts.HOT_KEYS)
    # At most HOT_KEYS rows are broadcast.
    hubs = F.broadcast(pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / bound).cast("int").alias("copies")).filter("copies > 1"))
    dealt = pairs.join(hubs, "a", "left").withColumn("copy", F.pmod(F.xxhash64("b"), F.coalesce("copies", F.lit(1))).cast("int")).drop("copies")
    chiefs = sets.join(pairs.select(F.col("a").alias("node")).distinct(), "node", "left_semi").withColumnRenamed("node", "a").join(hubs, "a", "left")
    copied = chiefs.select("a", F.col("members").alias("_set_a"), F.explode(F.sequence(F.lit(0), F.coalesce("copies", F.lit(1)) - 1)).alias("copy"))
    both = dealt.join(sets.select(F.col("node").alias("b"), F.col("members").alias("_set_b")).hint("merge"), "b").join(copied.hint("merge"), ["a", "copy"])
    common = F.size(F.array_intersect("_set_a", "_set_b"))
    return both.filter(100 * common >= percent * (F.size("_set_a") + F.size("_set_b") - common)).select("a", "b")


def _block_links(t: pa.Table, percent: int) -> pa.Table:
    """Links between rows of different groups, one of them outside: exact intersections of a block of sets with another."""
    outside = t.column("outside").to_numpy(zero_copy_only=False)
    lists = t.column("members").combine_chunks()
    lists = lists if isinstance(lists, pa.ListArray) else pa.concat_arrays(lists.chunks)
    offsets, flat = lists.offsets.to_numpy(), lists.values.to_numpy()
    sizes = np.diff(offsets)
    owner = np.repeat(np.arange(len(t)), sizes)
    values, at = np.unique(flat[offsets[0] : offsets[-1]], return_inverse=True)
    # Only shingles that both sides have count.
    both = (np.bincount(at[outside[owner]], minlength=len(values)) > 0) & (np.bincount(at[~outside[owner]], minlength=len(values)) > 0)
    rank = np.cumsum(both) - 1
    rows = {True: np.flatnonzero(outside), False: np.flatnonzero(~outside)}
    place = np.empty(len(t), np.int64)
    for r in rows.values():
        place[r] = np.arange(len(r))
    common = np.zeros((len(rows[True]), len(rows[False])), np.float32)
    for low in range(0, int(both.sum()), COLUMNS):
        use = both[at] & (rank[at] >= low) & (rank[at] < low + COLUMNS)
        part = {}
        for side, r in rows.items():
            own = use & (outside[owner] == side)
            part[side] = np.zeros((len(r), min(COLUMNS, int(both.sum()) - low)), np.float32)
            part[side][place[owner[own]], rank[at[own]] - low] = 1
        common += part[True] @ part[False].T
    n_out, n_in = sizes[rows[True]][:, None], sizes[rows[False]][None, :]
    x, y = np.nonzero(100 * common.astype(np.int64) >= percent * (n_out + n_in - common.astype(np.int64)))
    groups = t.column("group").to_pylist()
    nodes = t.column("node").to_pylist()
    pairs = [(nodes[rows[True][i]], nodes[rows[False][j]]) for i, j in zip(x, y, strict=True) if groups[rows[True][i]] != groups[rows[False][j]]]
    kind = pa.struct([("d", pa.int64()), ("s", pa.int64())])
    return pa.table({"a": pa.array([p[0] for p in pairs], kind), "b": pa.array([p[1] for p in pairs], kind)})


def components(edges: DataFrame) -> DataFrame:
    """node and group (its smallest reachable node) of the nodes of edges (a, b), by alternating star contraction."""

    def kept(e: DataFrame, name: str) -> tuple[DataFrame, tuple]:
        seen = Observation()
        out = ts.stored(e.observe(seen, F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")), name)
        return out, (seen.get["n"], seen.get["h"])

    def stars(e: DataFrame, total: int, both_ways: bool) -> DataFrame:
        # Each node's neighbours (a > b: or only the smaller ones) move to the least of the node and them.
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b"))) if both_ways else e
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n")).withColumn("m", F.least("a", "m"))
        moved = ts.lookup(both, least, ["a"], total).select(F.col("b").alias("a"), F.col("m").alias("b"))
        return moved.unionByName(least.select("a", F.col("m").alias("b"))).filter(F.col("a") != F.col("b")).distinct()

    edges, now = kept(edges.filter(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    before = None
    while now != before and now[0]:
        before = now
        large, (n, _) = kept(stars(edges, 2 * now[0], True).filter(F.col("a") > F.col("b")), "large")
        last = edges
        edges, now = kept(stars(large, n, False).filter(F.col("a") > F.col("b")), "edges")
        ts.dropped(last, large)
    top = edges.select(F.col("b").alias("node"), F.col("b").alias("group")).distinct()
    return edges.select(F.col("a").alias("node"), F.col("b").alias("group")).unionByName(top)


def _labelled(pairs: DataFrame, labels: DataFrame, column: str, total: int, own: Column | None = None) -> DataFrame:
    """pairs with label, that of column by a table (node, label), or own (the column itself, if not given)."""
    counted = pairs.groupBy(column).agg(F.count(F.lit(1)).alias("n"))
    values = counted.join(labels.select(F.col("node").alias(column), "label"), column, "left")
    values = values.withColumn("label", F.coalesce("label", column if own is None else own))
    return ts.lookup(pairs, values, [column], total).drop("n")


def groups(df: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row: kept rows are the smallest of their group."""
    signed = ts.stored(_signed(df, k), "signed")
    nodes = signed.filter("n > 0").groupBy("s", "t").agg(F.min("d").alias("d"), F.any_value("n").alias("n"), F.any_value("bands").alias("bands"))
    nodes = ts.stored(nodes.select(F.struct("d", "s").alias("node"), "t", "n", "bands"), "nodes")
    entries = nodes.select("node", F.explode("bands").alias("band"))
    shared = entries.groupBy("band").agg(F.count(F.lit(1)).alias("c")).filter("c > 1")
    live = ts.stored(entries.join(shared, "band"), "live")
    # The node of a band value with the most company in all of its band values: in a family of copies, what they copy.
    company = live.groupBy("node").agg(F.sum("c").alias("company"))
    chief = live.join(company, "node").groupBy("band").agg(F.max(F.struct("company", "node")).alias("chief"))
    stars = live.join(chief, "band").select("node", "chief").filter(F.col("node") != F.col("chief.node")).distinct()
    stars = ts.stored(stars.select(F.col("chief.node").alias("a"), F.col("node").alias("b"), F.col("chief.company").alias("company")), "stars")
    total = stars.count()
    if not total:
        return _placed(signed, nodes, None)
    ts.dropped(live)
    ends = stars.select(F.col("a").alias("node")).unionByName(stars.select(F.col("b").alias("node")))
    sets = ts.stored(_full_sets(df, ends, k), "sets")

    first = stars.groupBy("b").agg(F.max(F.struct("company", "a")).alias("m")).select(F.col("m.a").alias("a"), "b")
    links = ts.stored(_linked(first, sets, percent, total), "links")
    # Where the first links lead in up to three steps: nodes that meet there are in one group.
    label = links.select(F.col("b").alias("node"), F.col("a").alias("label"))
    for _ in range(2):
        label = _labelled(label.withColumnRenamed("label", "at"), links.select(F.col("b").alias("node"), F.col("a").alias("label")), "at", total).drop("at")
    label = ts.stored(label, "labels")
    one = _labelled(stars.select("a", "b"), label, "a", total).withColumnRenamed("label", "g_a")
    others = _labelled(one, label, "b", total).filter(F.col("g_a") != F.col("label")).select("a", "b").join(first, ["a", "b"], "left_anti")
    more = ts.stored(_linked(ts.stored(others, "pairs"), sets, percent, total), "links")
    every_link = links.unionByName(more)
    found = components(every_link)

    # Stars whose nodes still are in several groups: all pairs of different groups, in blocks.
    named = nodes.select(F.col("node").alias("b"), "n").join(found.withColumnRenamed("node", "b"), "b", "left").select("b", F.col("n").alias("size"), F.coalesce("group", "b").alias("group"))
    every_end = stars.select("a", "b").unionByName(stars.select("a", F.col("a").alias("b")).distinct())
    placed = ts.stored(every_end.join(named, "b"), "placed")
    counted = placed.groupBy("a", "group").agg(F.count(F.lit(1)).alias("c"), F.sum("size").alias("w"))
    mixed = counted.groupBy("a").agg(F.sum("c").alias("n"), F.sum("w").alias("w"), F.max(F.struct("c", "group", "w")).alias("m"), F.count(F.lit(1)).alias("groups")).filter("groups > 1")
    parts = lambda c, w: F.ceil(F.greatest(c / BLOCK, w / BLOCK_SHINGLES)).cast("int")
    mixed = mixed.select("a", "n", F.col("m.group").alias("main"), parts(F.col("n"), F.col("w")).alias("inner"), parts(F.col("n") - F.col("m.c"), F.col("w") - F.col("m.w")).alias("outer"))
    mixed = ts.stored(mixed, "mixed")
    if not mixed.isEmpty():
        members = ts.lookup(placed, mixed, ["a"], 2 * total).join(sets.select(F.col("node").alias("b"), "members"), "b")
        every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
        block = lambda n: F.pmod(F.xxhash64("b"), F.col(n)).cast("int")
        carried = [F.col("a").alias("star"), F.col("b").alias("node"), "group", "members"]
        inside = members.select(*carried, F.lit(False).alias("outside"), block("inner").alias("i"), every("outer").alias("j"))
        outside = members.filter(F.col("group") != F.col("main")).select(*carried, F.lit(True).alias("outside"), every("inner").alias("i"), block("outer").alias("j"))
        node_type = "struct<d:bigint,s:bigint>"
        last = inside.unionByName(outside).groupBy("star", "i", "j").applyInArrow(lambda t: _block_links(t, percent), f"a {node_type}, b {node_type}")
        last = ts.stored(last.distinct(), "links")
        if not last.isEmpty():
            found = components(every_link.unionByName(last))
    return _placed(signed, nodes, found)


def _placed(signed: DataFrame, nodes: DataFrame, found: DataFrame | None) -> DataFrame:
    """Every row with the group of its node."""
    group = F.col("node")
    if found is not None:
        nodes, group = nodes.join(found, "node", "left"), F.coalesce("group", "node")
    by_set = nodes.select("node.s", "t", group["d"].alias("component"))
    joined = signed.select("d", "s", "t", "n").withColumn("_full", F.col("n") > 0)
    joined = joined.join(by_set.withColumn("_full", F.lit(True)), ["s", "t", "_full"], "left")
    component = F.coalesce("component", "d")
    real = lambda c: F.when(c != LEAST_ID, c)
    return joined.select(real(F.col("d")).alias("doc_id"), F.col("n").alias("n_shingles"), real(component).alias("component_id"), (component == F.col("d")).alias("kept"))


def deduplicated(df: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """df without the rows that are not the smallest of their group; of rows with equal ids and texts one stays."""
    judged = ts.stored(groups(df, k, percent), "judged")
    gone = judged.filter(~F.col("kept")).select(F.col("doc_id").alias("_mm_id")).distinct()
    if not judged.groupBy("doc_id").count().filter("count > 1").isEmpty():
        df = df.dropDuplicates(["doc_id", "text"])
    return df.join(gone, F.col("doc_id").eqNullSafe(F.col("_mm_id")), "left_anti")
