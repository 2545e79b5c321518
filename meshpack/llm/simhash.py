"""SimHash near-duplicates by tiled exact comparison of 64-bit fingerprints.

Fingerprints that differ in at most ``RADIUS`` bits agree on one of ``RADIUS + 1`` blocks of
bits, so each block value names a set in which all such pairs can be found.  Within a set the
distinct fingerprints form tiles; a pair of tiles is skipped when its population counts
differ beyond the radius, and otherwise compared whole with exclusive-or and bit counts.
Sets of more than ``TILE`` fingerprints are dealt out as pairs of tiles, so no set has to
fit one task, and a tile pair reports a spanning forest of its links rather than all of them:
components stay exact and the output stays linear.

Defined cases: null and wordless texts have fingerprint zero and link like any other; a text
of fewer than three words is one shingle; equal fingerprints are one node, whatever their
number; null ids count as larger than all others and give a null component if alone; ids may be of
any type, and other than whole numbers order as text; ``keep_first`` keeps all columns, whatever
their names, and of rows that repeat one.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, fresh, id_key, map_texts, released, utf8

RADIUS = 3
SHINGLE = 3
SEED = 42
#: Fingerprints in a tile.
TILE = 2048
#: Distinct fingerprints per block value that call for longer blocks.
CROWD = 4096

LOWER = bytes(b + 32 if 0x41 <= b <= 0x5A else b for b in range(256))
#: Ids of rows up to which ``keep_first`` sends them to all executors.
BROADCAST_IDS = 2_000_000


def fingerprint(text: str | None, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """Signed 64-bit view of the fingerprint."""
    import xxhash

    words = utf8(text).translate(LOWER).split()  # bytes.split() takes exactly 09-0D and 20
    n = len(words)
    if not n:
        return 0
    flat = b" ".join(words)
    if n <= shingle:
        hashes = np.array([xxhash.xxh64_intdigest(flat, seed)], np.uint64)
    else:
        size = np.fromiter(map(len, words), np.int64, n) + 1
        end = np.cumsum(size) - 1
        begin = end - size + 1
        digest = xxhash.xxh64_intdigest
        pairs = zip(begin[: n - shingle + 1].tolist(), end[shingle - 1 :].tolist())
        hashes = np.fromiter((digest(flat[a:b], seed) for a, b in pairs), np.uint64, n - shingle + 1)
    ones = np.zeros(64, np.int64)
    for lo in range(0, len(hashes), 65536):
        bits = np.unpackbits(hashes[lo : lo + 65536].astype("<u8").view(np.uint8), bitorder="little")
        ones += bits.reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<i8")[0])


def fingerprints(docs: DataFrame, keep=("doc_id",), text: str = "text") -> DataFrame:
    def make():
        return lambda texts: {"fp": [fingerprint(t) for t in texts]}

    return map_texts(docs, make, [T.StructField("fp", T.LongType())], list(keep), text)


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edges to the least member of each component of the graph with edges (a, b)."""
    nodes, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    i, j = ends[: len(a)], ends[len(a) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[i], label[j])
        before = label.copy()
        np.minimum.at(label, i, low)
        np.minimum.at(label, j, low)
        np.minimum.at(label, before[i], low)
        np.minimum.at(label, before[j], low)
        while (again := label[label]).tobytes() != label.tobytes():
            label = again
        if np.array_equal(label, before):
            break
    away = label != np.arange(len(nodes))
    return nodes[away], nodes[label[away]]


def links_between(left: np.ndarray, right: np.ndarray | None, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links within ``left`` (``right`` None) or between two tiles of int64 views."""
    own = right is None
    right = left if own else right
    x, y = left.view(np.uint64), right.view(np.uint64)
    px, py = np.bitwise_count(x), np.bitwise_count(y)
    order = np.argsort(py, kind="stable")
    y, py = y[order], py[order].astype(np.int64)
    out_a, out_b, kept = [], [], 0
    rows = np.argsort(px, kind="stable")
    for lo in range(0, len(rows), 256):
        take = rows[lo : lo + 256]
        first = np.searchsorted(py, int(px[take[0]]) - radius, "left")
        last = np.searchsorted(py, int(px[take[-1]]) + radius, "right")
        if first == last:
            continue
        near = np.bitwise_count(x[take][:, None] ^ y[None, first:last]) <= radius
        i, j = np.nonzero(near)
        a, b = x[take[i]].view(np.int64), y[first + j].view(np.int64)
        if own:
            once = a < b
            a, b = a[once], b[once]
        if len(a):
            out_a.append(a)
            out_b.append(b)
            kept += len(a)
        if kept > 200_000:
            a, b = forest(np.concatenate(out_a), np.concatenate(out_b))
            out_a, out_b, kept = [a], [b], len(a)
    if not out_a:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(out_a), np.concatenate(out_b)


def block_keys(n_distinct: int, radius: int = RADIUS) -> list[list[tuple[int, int]]]:
    """Sets of bit ranges of which a linked pair shares at least one set in full.

    With ``m`` blocks at least ``m - radius`` agree.  ``m`` grows with the number of
    fingerprints so that a set holds about ``CROWD`` of evenly spread ones at most.
    """
    from itertools import combinations

    for m in range(radius + 1, 17):
        edges = [64 * k // m for k in range(m + 1)]
        width = sum(edges[k + 1] - edges[k] for k in range(m - radius))
        if n_distinct <= CROWD << min(width, 60):
            break
    ranges = [(edges[k], edges[k + 1] - edges[k]) for k in range(m)]
    return [list(c) for c in combinations(ranges, m - radius)]


def near_links(distinct: DataFrame, n_distinct: int, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """Links (a, b) of a spanning forest of each set; ``distinct`` has one row per fp."""
    keys = block_keys(n_distinct, radius)

    def value(ranges):
        out = F.lit(0).cast("long")
        for at, width in ranges:
            part = F.shiftrightunsigned("fp", at).bitwiseAND(F.lit((1 << width) - 1)) if width < 64 else F.col("fp")
            out = F.shiftleft(out, width).bitwiseOR(part)
        return out

    keyed = distinct.select("fp", F.bit_count("fp").alias("ones"), F.posexplode(F.array(*(value(r) for r in keys))).alias("block", "value"))
    sizes = keyed.groupBy("block", "value", "ones").agg(F.count("*").alias("n"))
    whole = sizes.groupBy("block", "value").agg(F.sum("n").alias("n"), F.map_from_entries(F.collect_list(F.struct("ones", F.ceil(F.col("n") / tile).cast("int").alias("tiles")))).alias("tiles"))
    # a set of a single fingerprint has no pair; the others carry how they are cut
    sets = whole.where("n > 1").select("block", "value", "n", F.when(F.col("n") > tile, F.col("tiles")).alias("tiles"))
    placed = keyed.join(sets, ["block", "value"])
    sub = lambda ones: F.coalesce(F.element_at(F.col("tiles"), ones), F.lit(0))
    mine = F.pmod(F.xxhash64("fp"), F.greatest(sub(F.col("ones")), F.lit(1))).cast("int")
    one = F.array(F.struct(F.lit(-1).alias("p"), F.lit(0).alias("s"), F.lit(-1).alias("q"), F.lit(0).alias("t"), F.lit(0).alias("side")))

    def with_other(q):
        """Tile pairs of my tile (ones, mine) with each tile of population count ``q``."""
        return F.transform(
            F.sequence(F.lit(0), sub(q) - 1),
            lambda t: F.when(
                (F.col("ones") < q) | ((F.col("ones") == q) & (F.col("mine") <= t)),
                F.struct(F.col("ones").alias("p"), F.col("mine").alias("s"), q.alias("q"), t.alias("t"), F.lit(0).alias("side")),
            ).otherwise(F.struct(q.alias("p"), t.alias("s"), F.col("ones").alias("q"), F.col("mine").alias("t"), F.lit(1).alias("side"))),
        )

    near = F.filter(F.sequence(F.col("ones") - radius, F.col("ones") + radius), lambda q: sub(q) > 0)
    dealt = (
        placed.withColumn("mine", F.when(F.col("tiles").isNotNull(), mine))
        .withColumn("pair", F.explode(F.when(F.col("tiles").isNull(), one).otherwise(F.flatten(F.transform(near, with_other)))))
        .select("block", "value", "pair.*", "fp")
    )
    parts = dealt.repartition("block", "value", "p", "s", "q", "t").sortWithinPartitions("block", "value", "p", "s", "q", "t", "side", "fp")
    schema = T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())])

    def run(batches):
        tail = None
        for batch in batches:
            cols = [batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(8)]
            if tail is not None:
                cols = [np.concatenate([t, c]) for t, c in zip(tail, cols)]
            same = np.ones(max(0, len(cols[0]) - 1), bool)
            for c in cols[:6]:
                same &= c[1:] == c[:-1]
            starts = np.concatenate([[0], np.flatnonzero(~same) + 1]) if len(cols[0]) else np.zeros(1, int)
            tail = [c[starts[-1] :] for c in cols]
            yield from compared(cols, starts)
        if tail is not None and len(tail[0]) > 1:
            yield from compared(tail, np.array([0, len(tail[0])]))

    def compared(cols, starts):
        out_a, out_b, kept = [], [], 0
        block, value, p, s, q, t, side, fp = cols
        for lo, hi in zip(starts[:-1], starts[1:]):
            if hi - lo < 2:
                continue
            if (p[lo], s[lo]) == (q[lo], t[lo]):
                a, b = links_between(fp[lo:hi], None, radius)
            else:
                mid = lo + int(np.searchsorted(side[lo:hi], 1))
                if mid in (lo, hi):
                    continue
                a, b = links_between(fp[lo:mid], fp[mid:hi], radius)
            if len(a):
                out_a.append(a)
                out_b.append(b)
                kept += len(a)
            if kept > 200_000:
                yield batch_of(out_a, out_b)
                out_a, out_b, kept = [], [], 0
        if kept:
            yield batch_of(out_a, out_b)

    def batch_of(out_a, out_b):
        a, b = forest(np.concatenate(out_a), np.concatenate(out_b))
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return parts.mapInArrow(released(run), schema)


def components(links: DataFrame, rounds: int = 64) -> DataFrame:
    """(node, root) for every node of ``links`` (a, b): the least node of its component.

    Each round points a node's neighbours at the least of them, first among larger and then
    among smaller neighbours, until nothing changes; edges are stored between rounds.
    """
    edges = cut(links.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct())

    def mark(df):
        return df.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()

    seen = mark(edges)
    for _ in range(rounds):
        if not seen[0]:
            break
        both = edges.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(edges.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").distinct()
        small_least = large.groupBy("hi").agg(F.min("lo").alias("m"))
        joined = large.join(small_least, "hi")
        moved = joined.where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo"))
        edges = cut(moved.union(small_least.select("hi", F.col("m").alias("lo"))).distinct())
        now = mark(edges)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError(f"components are not settled after {rounds} rounds")
    return edges.select(F.col("hi").alias("node"), F.col("lo").alias("root"))


def classes(prints: DataFrame, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """(fp, root, least) for each distinct fp of stored ``prints`` (doc_id, fp); ``least`` is the class's first ``id_key``."""
    distinct = cut(prints.groupBy("fp").agg(F.min(id_key(prints)[0]).alias("own")))
    roots = components(near_links(distinct, distinct.count(), radius, tile))
    labelled = distinct.join(roots, distinct.fp == roots.node, "left").select("fp", "own", F.coalesce("root", "fp").alias("root"))
    # summed by task before the shuffle: a class of very many fingerprints costs a row for each
    least = labelled.groupBy("root").agg(F.min("own").alias("least"))
    return labelled.join(least, "root").select("fp", "root", "least")


def near_duplicates(docs: DataFrame, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """doc_id, fingerprint and component_id of every row of ``docs``."""
    prints = cut(fingerprints(docs))
    return prints.join(classes(prints, radius, tile), "fp").select(
        "doc_id",
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        F.nullif("least", id_key(prints)[1]).alias("component_id"),
    )


def keep_first(docs: DataFrame, broadcast_ids: int = BROADCAST_IDS) -> DataFrame:
    """``docs`` with one row of each class of near-duplicates: the least doc_id.

    Rows that share their doc_id and text with the kept one go too.  Only the ids that go are joined
    with the texts, by broadcast where their checked number allows it.
    """
    prints = cut(fingerprints(docs))
    found = cut(classes(prints))
    key = id_key(prints)[0]
    per = prints.join(found, "fp").groupBy("doc_id").agg(F.count("*").alias("n"), F.bool_or(key == F.col("least")).alias("first"))
    moved = cut(per.where("n > 1 or not first or doc_id is null"))
    count = moved.agg(F.count("*"), F.count_if(F.expr("n > 1 or doc_id is null"))).first()
    i, fp, root = fresh(docs.columns, "id", "fp", "root")
    sent = lambda df: F.broadcast(df) if count[0] <= broadcast_ids else df.hint("merge")
    gone = moved.where("doc_id is not null").select(F.col("doc_id").alias(i))
    single = docs.where("doc_id is not null").join(sent(gone), F.col("doc_id") == F.col(i), "left_anti")
    if not count[1]:
        return single
    # repeated ids: tell their rows apart by fingerprint, keep one for each class
    odd = moved.where("n > 1 or doc_id is null").select(F.col("doc_id").alias(i))
    some = docs.join(sent(odd), F.col("doc_id").eqNullSafe(F.col(i)), "left_semi")
    marked = map_texts(some, lambda: lambda texts: {fp: [fingerprint(t) for t in texts]}, [T.StructField(fp, T.LongType())])
    known = found.select(F.col("fp").alias(fp), F.col("root").alias(root), F.col("least").alias(i))
    rest = marked.join(known, fp).where(id_key(docs)[0] == F.col(i)).dropDuplicates([root])
    return single.unionByName(rest.select(*docs.columns))
