"""Benchmark decontamination with one Aho-Corasick automaton over normalised test items.

Questions and answers become sequences of coded words; the automaton runs over these codes, two
characters a word, and one scan of a text reports each place that can belong to a window of
``window`` words shared with an item (see ``Machine``).  Word numbers, and from them offsets in
the original text, follow from where a match ends.

Defined cases: a null or wordless text has no words, no hits and is clean; an item of fewer
than ``window`` words is one window, an item without words none; items of equal windows are
all reported; repeated rows get equal results; ids may be of any type; items with a null id are
left out; columns of the names that are added give way, and ``drop_contaminated`` keeps all columns.
"""

from __future__ import annotations

import hashlib
import itertools

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ROWS_AT_ONCE, cut, fresh, map_texts, released, utf8

#: Lower-case ASCII letters, digits and all non-ASCII bytes make words.
NORMAL = bytes(
    b + 32 if 0x41 <= b <= 0x5A else b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20
    for b in range(256)
)
WINDOW = 13
#: Bytes of benchmark text, and 64 for each item, in one automaton: about 16 bytes of memory for each.
BLOCK_BYTES = 60_000_000
#: Items that a block of words may be looked up in one by one.
CROWD = 16
#: Hit words, and items eightfold, up to which the hits of several blocks are joined back by broadcast.
BROADCAST_HITS = 5_000_000

SPAN = T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())])
FOUND = [
    T.StructField("n_words", T.LongType()),
    T.StructField("n_hit", T.LongType()),
    T.StructField("items", T.ArrayType(T.StringType())),
    T.StructField("spans", T.ArrayType(SPAN)),
]

#: Words hit by one block of several.
HITS = [T.StructField("hits", T.ArrayType(T.LongType())), FOUND[2]]

_BUILT: dict[str, "Machine"] = {}


def words_of(text: str | None) -> list[bytes]:
    return utf8(text).translate(NORMAL).split()


class Machine:
    """The automaton over coded words, and the items that its matches are grown in.

    Whatever ``window`` words of an item are taken, they hold a whole block of the item's own
    division into ``(window + 1) // 2`` words.  The automaton's patterns are these blocks, so it grows
    with the items' words, not with their windows; a match is grown word by word in its item, and
    counts if ``window`` words or more agree.  An item of fewer words is one pattern and needs no growth.

    A word is coded by two characters, the digits of its number, from ranges that do not meet: a
    match can only begin at a word, and no state has more ways out than a digit has values.
    """

    def __init__(self, items: list[tuple[str, str | None]], window: int):
        import ahocorasick

        self.window, self.block = window, (window + 1) // 2
        self.reach = window - self.block
        self.near = (self.reach + 1) // 2
        known = dict.fromkeys(w for _, text in items for w in words_of(text))
        base = max(2, int(np.ceil(np.sqrt(len(known)))))
        self.code = {w: chr(0x100 + n % base) + chr(0x10000 + n // base) for n, w in enumerate(known)}
        owners: dict[str, set[str]] = {}
        for item, text in items:
            owners.setdefault("".join(map(self.code.__getitem__, words_of(text))), set()).add(item)
        owners.pop("", None)
        self.texts, self.items = list(owners), [tuple(sorted(ids)) for ids in owners.values()]
        self.trie = ahocorasick.Automaton()
        for k, t in enumerate(self.texts):
            n = len(t) // 2
            size = self.block if n >= window else n
            for at in range(0, n - size + 1, size):
                pattern = t[2 * at : 2 * (at + size)]
                value = self.trie.get(pattern, None)
                if value is None:
                    self.trie.add_word(pattern, [size, k, at])
                else:
                    value += k, at
        if self.texts:
            for value in self.trie.values():
                if len(value) > 2 * CROWD:
                    value[1:] = self.by_sides(value)
            self.trie.make_automaton()

    def by_sides(self, value: list) -> list[dict]:
        """Places of a block that many items have, by the words next to it: of the ``reach`` words that
        must agree around a block, half or more stand on one side."""
        left: dict[str, list] = {}
        right: dict[str, list] = {}
        for k, at in zip(value[1::2], value[2::2]):
            t, end = self.texts[k], at + value[0]
            if len(t) < 2 * self.window:
                left.setdefault("", []).append((k, at))
            if at >= self.near:
                left.setdefault(t[2 * (at - self.near) : 2 * at], []).append((k, at))
            if 2 * (end + self.near) <= len(t):
                right.setdefault(t[2 * end : 2 * (end + self.near)], []).append((k, at))
        return [left, right]

    def places(self, value: list, row: str, start: int):
        if isinstance(value[1], int):
            return zip(value[1::2], value[2::2])
        end = start + value[0]
        left = value[1].get(row[2 * (start - self.near) : 2 * start], ()) if start >= self.near else ()
        return {*value[1].get("", ()), *left, *value[2].get(row[2 * end : 2 * (end + self.near)], ())}

    def found(self, words: list[bytes]) -> tuple[np.ndarray, set[str]]:
        """Numbers of the words that stand in an occurrence of a window, and the items of these."""
        get, items = self.code.get, set()
        if not self.texts or not words:
            return np.zeros(0, np.int64), items
        row = "".join([get(w, "??") for w in words])
        change, seen = None, set()
        for last, value in self.trie.iter(row):
            size = value[0]
            start = (last + 1) // 2 - size
            for k, at in self.places(value, row, start):
                text, low, high = self.texts[k], 0, size
                n = len(text) // 2
                if n >= self.window:
                    while low < self.reach and low < at and low < start and text[2 * (at - low) - 2 : 2 * (at - low)] == row[2 * (start - low) - 2 : 2 * (start - low)]:
                        low += 1
                    while high < size + self.reach and at + high < n and start + high < len(words) and text[2 * (at + high) : 2 * (at + high) + 2] == row[2 * (start + high) : 2 * (start + high) + 2]:
                        high += 1
                    if low + high < self.window:
                        continue
                if change is None:
                    change = np.zeros(len(words) + 1, np.int64)
                change[start - low] += 1
                change[start + high] -= 1
                seen.add(k)
        if change is None:
            return np.zeros(0, np.int64), items
        for k in seen:
            items.update(self.items[k])
        return np.flatnonzero(np.cumsum(change[:-1]) > 0), items


def word_offsets(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each word, in code points of the original text."""
    raw = utf8(text)
    inside = np.frombuffer(raw.translate(NORMAL), np.uint8) != 0x20
    edge = np.diff(np.concatenate([[False], inside, [False]]).astype(np.int8))
    points = np.concatenate([[0], np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)])
    return points[np.flatnonzero(edge == 1)], points[np.flatnonzero(edge == -1)]


def scan(text: str | None, machine: Machine) -> tuple[int, np.ndarray, set[str]]:
    """Number of words, which words are hit, and the items found."""
    words = words_of(text)
    return len(words), *machine.found(words)


def spans_of(text: str, hit: np.ndarray) -> list[dict]:
    """Maximal runs of hit words, as code points of the original text."""
    if not len(hit):
        return []
    start, end = word_offsets(text)
    first = np.flatnonzero(np.diff(hit, prepend=-2) != 1)
    final = np.append(first[1:] - 1, len(hit) - 1)
    return [{"start": int(start[hit[a]]), "end": int(end[hit[b]])} for a, b in zip(first, final)]


def benchmark_blocks(benchmark: DataFrame, block_bytes: int = BLOCK_BYTES):
    """Bounded blocks of (item_id, text), one at a time on the driver."""
    rows = benchmark.where(F.col("item_id").isNotNull()).select(F.col("item_id").cast("string").alias("item_id"), "text").distinct()
    block, size = [], 0
    for row in rows.toLocalIterator():
        n = len(utf8(row.text)) + 64
        if block and size + n > block_bytes:
            yield block
            block, size = [], 0
        block.append((row.item_id, row.text))
        size += n
    yield block


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES, spans: bool = True, keep=None) -> DataFrame:
    """``docs`` with n_words, n_hit, items and, if asked for, the spans of hit words.

    A benchmark of up to ``block_bytes`` is one automaton and one narrow pass.  More of it makes an
    automaton for each block; texts are not stored between: each block's scan gives the hit words
    of the texts that have any, by a key of the text, and these few rows are summed and joined back.
    """
    kept = [c for c in (docs.columns if keep is None else keep) if c not in {f.name for f in FOUND}]
    blocks = benchmark_blocks(benchmark, block_bytes)
    first = next(blocks)
    second = next(blocks, None)
    if second is None:
        return map_texts(docs, _kernel(docs, first, window, spans), FOUND, kept)
    key, hit = fresh([*docs.columns, *(f.name for f in FOUND)], "key", "hit")
    own = docs.withColumn(key, F.struct(F.xxhash64("text"), F.crc32(F.col("text").cast("binary")), F.length("text")))
    found = None
    for block in itertools.chain([first, second], blocks):
        some = map_texts(own, _kernel(docs, block, window, None), HITS, [key]).where("size(items) > 0")
        # copies of a text say the same, and are one row before anything is dealt out
        some = cut(some.groupBy(key).agg(F.first("hits").alias("hits"), F.first("items").alias("items")))
        found = some if found is None else found.unionByName(some)
    merged = found.groupBy(key).agg(F.flatten(F.collect_list("hits")).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    merged = cut(merged.select(F.col(key).alias(hit), F.struct("hits", "items").alias("found")))
    few = merged.agg(F.sum(F.size("found.hits") + 8 * F.size("found.items"))).first()[0] or 0
    side = F.broadcast(merged) if few <= BROADCAST_HITS else merged.hint("merge")
    got, name = fresh(own.columns, "found")[0], [f.name for f in FOUND]
    joined = own.join(side.withColumnRenamed("found", got), own[key] == side[hit], "left").select(*docs.columns, got)
    return _with_hits(joined, kept, got, spans).select(*kept, *name)


def _automaton(session: SparkSession, block, window):
    """What a worker builds once from a block that is sent to each executor once."""
    key = hashlib.sha256(repr((window, block)).encode()).hexdigest()
    sent = session.sparkContext.broadcast(block)  # at most BLOCK_BYTES of text

    def automaton() -> Machine:
        if key not in _BUILT:
            _BUILT.clear()
            _BUILT[key] = Machine(sent.value, window)
        return _BUILT[key]

    return automaton


def _kernel(docs: DataFrame, block, window, spans: bool | None):
    """Kernel for a block: the counts and spans of FOUND, or with ``spans`` None the words of HITS."""
    automaton = _automaton(docs.sparkSession, block, window)

    def make():
        machine = automaton()

        def kernel(texts):
            rows = [scan(t, machine) for t in texts]
            items = [sorted(found) for _, _, found in rows]
            if spans is None:
                return {"hits": [hit for _, hit, _ in rows], "items": items}
            marked = [spans_of(t or "", hit) if spans else [] for t, (_, hit, _) in zip(texts, rows)]
            return {"n_words": [n for n, _, _ in rows], "n_hit": [len(hit) for _, hit, _ in rows], "items": items, "spans": marked}

        return kernel

    return make


def _with_hits(df: DataFrame, kept: list[str], got: str, spans: bool) -> DataFrame:
    """FOUND from the joined-back words of all blocks."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_type

    own = df.select(*dict.fromkeys([*kept, "text"]), got)
    schema = T.StructType([*(df.schema[c] for c in kept), *FOUND])
    names, types = own.columns, {f.name: to_arrow_type(f.dataType) for f in FOUND}

    def run(batches):
        for batch in batches:
            for lo in range(0, batch.num_rows, ROWS_AT_ONCE):
                part = batch.slice(lo, ROWS_AT_ONCE)
                rows = []
                for text, found in zip(part.column(names.index("text")).to_pylist(), part.column(names.index(got)).to_pylist()):
                    hit = np.unique(np.array(found["hits"] if found else [], np.int64))
                    rows.append((len(words_of(text)), len(hit), found["items"] if found else [], spans_of(text or "", hit) if spans else []))
                arrays = [part.column(names.index(c)) for c in kept]
                arrays += [pa.array([r[i] for r in rows], type=types[f.name]) for i, f in enumerate(FOUND)]
                yield pa.RecordBatch.from_arrays(arrays, names=schema.names)

    return own.mapInArrow(released(run), schema)


def is_contaminated() -> F.Column:
    return (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words"))


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row of ``docs`` each: counts, a digest of the items found, and the verdict."""
    found = contamination(docs, benchmark, spans=False, keep=["doc_id"])
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), is_contaminated().alias("contaminated"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """``docs`` without contaminated rows, columns unchanged."""
    names = dict(zip((f.name for f in FOUND), fresh(docs.columns, *(f"own_{f.name}" for f in FOUND))))
    own = docs.withColumnsRenamed({c: names[c] for c in docs.columns if c in names})
    kept = contamination(own, benchmark, spans=False).where(~is_contaminated())
    return kept.drop(*names).withColumnsRenamed({v: k for k, v in names.items()}).select(*docs.columns)
