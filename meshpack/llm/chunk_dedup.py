"""Substring deduplication by content-defined chunks.

A gear rolling hash runs over the bytes of a text.  Places after white space may end a chunk (in
stretches without any, character bounds that the hash picks), and of each ``WINDOW`` such places
in turn the one with the least hash does, so ends depend on the 32 bytes before them and on
their neighbours only.  A chunk's digest of 128 bits is that of at least the last ``RUN_WORDS``
places before its end: two texts that share ``RUN_WORDS`` + ``WINDOW`` words share a digest,
wherever their cuts agree, and a shared digest is never a chance repeat of a few words.

Of equal digests the one with the least (doc_id, place) is kept.  Later ones go, with the words
ahead of the chunk that the digest covers, where they stand in a run of at least ``RUN_WORDS``
words, or make up the whole text.  Up to ``WINDOW`` words at each end of a passage can stay.

Chunk digests are summed by key before the shuffle, so a passage in a third of all documents
costs one row for each task; occurrences are joined back with split hot keys.

Defined cases: null and empty texts have no chunks; ``BYTES_A_WORD`` bytes count as a word at least, for texts
without white space; chunks over ``MOST`` bytes are cut at white space or character bounds; rows of one doc_id
are one document, so repeated rows keep what either keeps; null ids come last; ids may be of any type,
and other than whole numbers order as text; ``cut_repeats`` keeps all columns, whatever their names.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, fresh, id_key, map_texts, released, utf8

LEAST, MOST = 32, 512
RUN_WORDS = WINDOW = 16
#: In stretches without white space of over UNBROKEN bytes the hash picks places, one in four.
UNBROKEN, PICK = 64, 2**30
BYTES_A_WORD = 8

#: Random words for the byte values, from a fixed seed.
GEAR = np.random.default_rng(20240229).integers(0, 2**32, 256, dtype=np.uint32)
SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])

#: Chunks are stored as arrays side by side, 32 bytes each.
CHUNKS = [T.StructField(n, T.ArrayType(T.LongType())) for n in ("d1", "d2")] + [T.StructField(n, T.ArrayType(T.IntegerType())) for n in ("stop", "words", "back", "back_words")]


def gear_hash(raw: np.ndarray) -> np.ndarray:
    """Rolling hash at each byte: the sum of gear words shifted by their distance, in 32 bits.

    Built by doubling: the hash of 2w bytes is that of the last w and, shifted by w, of the w before.
    """
    h = GEAR[raw]
    for w in (1, 2, 4, 8, 16):
        if len(h) > w:
            back = h[:-w] << np.uint32(w)
            h = h.copy()
            h[w:] += back
    return h


def places_of(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Places that may end a chunk, the text's end not included, and their hashes."""
    data = np.frombuffer(raw, np.uint8)
    space, h = SPACE[data], gear_hash(data)
    ok = space[:-1] & ~space[1:]
    if len(data) > UNBROKEN:
        since = np.arange(len(data)) - np.maximum.accumulate(np.where(space, np.arange(len(data)), -1))
        ok |= (since[:-1] > UNBROKEN) & (h[:-1] < PICK) & ((data[1:] & 0xC0) != 0x80) & ~space[1:]
    at = np.flatnonzero(ok)
    return at + 1, h[at]


def winnowed(h: np.ndarray, w: int = WINDOW) -> np.ndarray:
    """Numbers of the least hashes of all windows of ``w`` in turn, the last of equals; equals within a window are thinned."""
    if len(h) < w:
        return np.empty(0, np.int64)
    windows = np.lib.stride_tricks.sliding_window_view(h[::-1], w)
    some = np.unique(len(h) - 1 - (windows.argmin(axis=1) + np.arange(len(windows))))
    if not np.any((h[some[1:]] == h[some[:-1]]) & (np.diff(some) < w)):
        return some
    kept = [int(some[0])]
    for k in some[1:].tolist():
        if h[k] != h[kept[-1]] or k - kept[-1] >= w:
            kept.append(k)
    return np.array(kept)


def ends_of(raw: bytes, places: tuple[np.ndarray, np.ndarray] | None = None) -> list[int]:
    """Ends of the chunks, the text's end included."""
    n = len(raw)
    if not n:
        return []
    at, h = places or places_of(raw)
    ends, last = [], 0
    for p in [*at[winnowed(h)].tolist(), n]:
        while p - last > MOST:
            stop = last + MOST
            soft = raw.rfind(b" ", last + LEAST, stop) + 1
            if soft:
                stop = soft
            else:
                while stop > last + 1 and (raw[stop] & 0xC0) == 0x80:
                    stop -= 1
            ends.append(stop)
            last = stop
        ends.append(p)
        last = p
    return ends


def chunks_of(text: str | None) -> tuple[list[int], ...]:
    """Both halves of the digests, the ends and numbers of words of the chunks, and the bytes and words that
    the digests cover ahead of them."""
    import xxhash

    raw, last = utf8(text), 0
    if not raw:
        return [], [], [], [], [], []
    at, h = places_of(raw)
    ends = ends_of(raw, (at, h))
    # the place RUN_WORDS places before each end
    firsts = np.concatenate([np.zeros(RUN_WORDS, np.int64), at])[np.searchsorted(at, ends)].tolist()
    digests, words, back, back_words = bytearray(), [], [], []
    for stop, first in zip(ends, firsts):
        first = min(first, last)
        digests += xxhash.xxh3_128_digest(raw[first:stop])
        words.append(len(raw[last:stop].split()))
        back.append(last - first)
        back_words.append(len(raw[first:last].split()))
        last = stop
    halves = np.frombuffer(bytes(digests), ">i8").astype(np.int64)
    return halves[0::2], halves[1::2], ends, words, back, back_words


def chunked(docs: DataFrame) -> DataFrame:
    """row, doc_id, hash of the text and chunks of every row, stored."""

    def make():
        def kernel(texts):
            rows = [chunks_of(t) for t in texts]
            return {f.name: [r[i] for r in rows] for i, f in enumerate(CHUNKS)}

        return kernel

    own = docs.select("doc_id", F.xxhash64("text").alias("th"), "text")
    return cut(map_texts(own, make, CHUNKS, ["doc_id", "th"]).withColumn("row", F.monotonically_increasing_id()))


def repeats(stored: DataFrame) -> DataFrame:
    """Occurrences of chunks that occur more than once: row, at, the id that keeps it and whether this is the kept one.

    The shared digests are stored ahead of the join, whose sides are then plain exchanges: a digest
    with very many occurrences is split over tasks.
    """
    key, top = id_key(stored)
    each = stored.select(key.alias("id"), "row", F.posexplode(F.arrays_zip("d1", "d2")).alias("at", "c")).select("row", "c.d1", "c.d2", F.struct("id", "at").alias("place"))
    shared = cut(each.groupBy("d1", "d2").agg(F.min("place").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"))
    joined = each.join(shared.hint("merge"), ["d1", "d2"])
    return joined.select("row", F.col("place.at").alias("at"), F.nullif("first.id", top).alias("keeper"), (F.col("place") == F.col("first")).alias("is_first"))


def removals(stored: DataFrame, run_words: int = RUN_WORDS) -> DataFrame:
    """row, and arrays by chunk place: of later occurrences in runs, and of the ids kept for them."""
    found = repeats(stored).groupBy("row").agg(F.collect_list(F.struct("at", F.col("is_first"), F.col("keeper").alias("id"))).alias("found"))
    joined = stored.join(found, "row", "left")
    ids = found.schema["found"].dataType.elementType["id"].dataType
    schema = T.StructType([
        T.StructField("row", T.LongType()), stored.schema["doc_id"], T.StructField("th", T.LongType()),
        *(T.StructField(n, T.LongType()) for n in ("n_bytes", "n_words", "n_chunks", "n_removed", "removed_bytes", "removed_words", "n_shared", "shared_words")),
        T.StructField("cuts", T.ArrayType(T.ArrayType(T.LongType()))), T.StructField("first_doc_ids", T.ArrayType(ids)),
    ])

    def run(batches):
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        as_arrow = to_arrow_schema(schema)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                yield pa.RecordBatch.from_pylist([verdict(r, run_words) for r in batch.slice(lo, 256).to_pylist()], schema=as_arrow)

    return joined.select("row", "doc_id", "th", *(f.name for f in CHUNKS[2:]), "found").mapInArrow(released(run), schema)


def verdict(r: dict, run_words: int) -> dict:
    """Counts of one text, the byte ranges to cut, and the documents that keep them."""
    words, starts = r["words"] or [], [0, *(r["stop"] or [])]
    n = len(words)
    later, shared, keeper = [False] * n, [False] * n, [None] * n
    for f in r["found"] or []:
        shared[f["at"]] = True
        later[f["at"]] = not f["is_first"]
        keeper[f["at"]] = f["id"]

    def long_runs(flags):
        """(first chunk, its start or what the digest covers ahead of it, words, stop) of each run, none over another."""
        at = before = 0
        while at < n:
            if not flags[at]:
                at += 1
                continue
            stop = at
            while stop < n and flags[stop]:
                stop += 1
            size, count = starts[stop] - starts[at] + r["back"][at], sum(words[at:stop]) + r["back_words"][at]
            if max(count, size // BYTES_A_WORD) >= run_words or stop - at == n:
                low, ahead = starts[at] - r["back"][at], r["back_words"][at]
                if low < starts[before]:
                    low, ahead = starts[before], sum(words[before:at])
                yield at, low, ahead + sum(words[at:stop]), stop
                before = stop
            at = stop

    cuts = list(long_runs(later))
    alike = list(long_runs(shared))
    gone = [k for a, _, _, b in cuts for k in range(a, b)]
    joined = []
    for _, low, _, b in cuts:
        if joined and joined[-1][1] == low:
            joined[-1][1] = starts[b]
        else:
            joined.append([low, starts[b]])
    return {
        "row": r["row"], "doc_id": r["doc_id"], "th": r["th"], "n_bytes": starts[-1], "n_words": sum(words), "n_chunks": n,
        "n_removed": len(gone), "removed_bytes": sum(starts[b] - low for _, low, _, b in cuts), "removed_words": sum(w for _, _, w, _ in cuts),
        "n_shared": sum(b - a for a, _, _, b in alike), "shared_words": sum(w for _, _, w, _ in alike),
        "cuts": joined,
        "first_doc_ids": sorted({keeper[k] for k in gone if keeper[k] is not None}),
    }


def substring_dedup(docs: DataFrame, run_words: int = RUN_WORDS) -> DataFrame:
    """doc_id, counts, the byte ranges to cut and the ids of the documents that keep the copies."""
    return removals(chunked(docs), run_words).drop("row", "th")


def cut_repeats(docs: DataFrame, run_words: int = RUN_WORDS) -> DataFrame:
    """``docs`` with later copies of repeated passages cut out of the texts."""
    i, h, found = fresh(docs.columns, "id", "th", "cuts")
    cuts = removals(chunked(docs), run_words).where("size(cuts) > 0").dropDuplicates(["doc_id", "th"]).select(F.col("doc_id").alias(i), F.col("th").alias(h), F.col("cuts").alias(found))
    joined = docs.join(cuts, F.col("doc_id").eqNullSafe(F.col(i)) & (F.xxhash64("text") == F.col(h)), "left").select(*docs.columns, found)
    schema = docs.schema

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            t, n = schema.names.index("text"), len(schema.names)
            texts = [without(a, b) for a, b in zip(batch.column(t).to_pylist(), batch.column(n).to_pylist())]
            yield pa.RecordBatch.from_arrays([pa.array(texts, batch.column(t).type) if k == t else batch.column(k) for k in range(n)], names=schema.names)

    return joined.mapInArrow(run, schema)


def without(text: str | None, cuts) -> str | None:
    if not text or not cuts:
        return text
    raw, out, last = utf8(text), [], 0
    for a, b in cuts:
        out.append(raw[last:a])
        last = b
    return b"".join([*out, raw[last:]]).decode("utf-8", "replace")
