"""Quality rules with cross-document line frequency.

Lines are normalised (ASCII letters in lower case, digits as 0, runs of white space as one
space) and hashed; for each host the number of distinct documents with a line decides whether
the line goes.  A document goes when too little is left of it, or by the base rules on words
that repeat.

A document reports each of its lines once, so the count is one aggregation in which a very
common line is summed before the shuffle.  Lines above the limit are joined back by broadcast
if their checked number allows it, by shuffle otherwise.

Defined cases: null texts have no lines and no words and are not kept; a null host is a host
of its own; repeated rows count once where their doc_id is equal, rows without one each; lines
without a word are never counted or removed; ids may be of any type; ``strip_lines`` keeps all
columns, whatever their names.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, fresh, map_texts, utf8

#: Distinct documents of a host that may share a line.
LINE_DOCS = 10
#: Least share of characters in words that must be left.
LEFT = 0.5
#: Frequent lines up to which the join is by broadcast (24 bytes each).
BROADCAST_LINES = 1_000_000
#: Tasks that the occurrences of one frequent line are dealt to beyond that.
SALTS = 16

NORMAL = bytes(b + 32 if 0x41 <= b <= 0x5A else 0x30 if 0x30 <= b <= 0x39 else b for b in range(256))
WINDOW = 5

BASE = [T.StructField(n, T.LongType()) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
LINE = T.StructType([T.StructField("h", T.LongType()), T.StructField("chars", T.LongType())])


def code_points(raw: bytes) -> int:
    return len(raw) - len(raw.translate(None, bytes(b for b in range(256) if not 0x80 <= b < 0xC0))) if not raw.isascii() else len(raw)


def repeated_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside windows that are found twice or more, the first finding included."""
    n = len(words) - window + 1
    if n < 2:
        return 0
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.int64, len(words))
    if len(number) == len(words):
        return 0
    key = ids[:n].copy()
    for j in range(1, window):
        _, key = np.unique(key * len(number) + ids[j : j + n], return_inverse=True)
    hit = np.bincount(key)[key] > 1
    if not hit.any():
        return 0
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, np.flatnonzero(hit), 1)
    np.add.at(edge, np.flatnonzero(hit) + window, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def base_counts(text: str | None) -> tuple[int, int, int, int, int]:
    raw = utf8(text)
    words = raw.split()  # bytes.split() takes exactly 09-0D and 20
    seen, again = set(), 0
    for line in raw.split(b"\n"):
        if line in seen:
            again += bool(line.split())
        else:
            seen.add(line)
    return len(words), code_points(b"".join(words)), len(raw) - len(raw.translate(None, b"#*$%&|<>")), again, repeated_words(words)


def lines_of(text: str | None) -> list[tuple[int, int]]:
    """Hash of each normalised line with a word, and the code points of its words in all."""
    import xxhash

    found: dict[int, int] = {}
    for line in utf8(text).split(b"\n"):
        words = line.split()
        if words:
            h = xxhash.xxh3_64_intdigest(b" ".join(words).translate(NORMAL)) - 2**63
            found[h] = found.get(h, 0) + code_points(b"".join(words))
    return list(found.items())


def text_key() -> F.Column:
    """Equal for rows of equal id, host and text."""
    return F.struct(F.xxhash64("doc_id").alias("i"), F.xxhash64("text").alias("t"), F.coalesce("source", F.lit("")).alias("s"))


def analysed(docs: DataFrame) -> DataFrame:
    """doc_id, host, key, base counts and lines of each row, stored."""

    def make():
        def kernel(texts):
            rows = [base_counts(t) for t in texts]
            out = {f.name: [r[i] for r in rows] for i, f in enumerate(BASE)}
            out["lines"] = [[{"h": h, "chars": c} for h, c in lines_of(t)] for t in texts]
            return out

        return kernel

    added = [*BASE, T.StructField("lines", T.ArrayType(LINE))]
    host = docs.select("doc_id", F.coalesce("source", F.lit("")).alias("host"), text_key().alias("key"), "text")
    return cut(map_texts(host, make, added, ["doc_id", "host", "key"]).withColumn("row", F.monotonically_increasing_id()))


def frequent_lines(lines: DataFrame, limit: int = LINE_DOCS) -> DataFrame:
    """(host, h, n_docs) of the lines that more than ``limit`` documents of a host have."""
    return lines.groupBy("host", "h").agg(F.count_distinct(F.struct("doc_id", F.when(F.col("doc_id").isNull(), F.col("row")))).alias("n_docs")).where(F.col("n_docs") > limit)


def line_rules(docs: DataFrame, limit: int = LINE_DOCS, left: float = LEFT, broadcast_lines: int = BROADCAST_LINES) -> DataFrame:
    """doc_id, base counts, n_removed_lines, removed_chars, base_failed and kept."""
    rows = analysed(docs)
    lines = rows.select("row", "doc_id", "host", F.explode("lines").alias("line")).select("row", "doc_id", "host", "line.*")
    frequent = cut(frequent_lines(lines, limit))
    if frequent.count() <= broadcast_lines:
        removed = lines.join(F.broadcast(frequent.select("host", "h")), ["host", "h"])
    else:
        removed = salted(lines, frequent.select("host", "h"))
    lost = removed.groupBy("row").agg(F.count("*").alias("n_removed_lines"), F.sum("chars").alias("removed_chars"))
    counted = rows.drop("lines", "host", "key").join(lost, "row", "left").drop("row").na.fill(0, ["n_removed_lines", "removed_chars"])
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    depleted = (F.col("word_chars") - F.col("removed_chars")) < left * F.col("word_chars")
    return counted.withColumn("base_failed", failed).withColumn("kept", ~failed & ~depleted)


def salted(lines: DataFrame, frequent: DataFrame) -> DataFrame:
    """``lines`` that are ``frequent``, by shuffle; a line that all of a host has goes to ``SALTS`` tasks."""
    side = frequent.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return lines.withColumn("salt", F.pmod(F.hash("row"), F.lit(SALTS))).join(side.hint("merge"), ["host", "h", "salt"]).drop("salt")


def strip_lines(docs: DataFrame, limit: int = LINE_DOCS) -> DataFrame:
    """``docs`` with the frequent lines of each host cut out of the texts.

    Line hashes of the host travel to a document as an array, for frequent lines only.
    """
    rows = analysed(docs)
    lines = rows.select("row", "key", "doc_id", "host", F.explode("lines").alias("line")).select("row", "key", "doc_id", "host", "line.*")
    frequent = frequent_lines(lines, limit).select("host", "h")
    key, found = fresh(docs.columns, "key", "gone")
    gone = salted(lines, frequent).groupBy(F.col("key").alias(key)).agg(F.collect_set("h").alias(found))
    joined = docs.withColumn(key, text_key()).join(gone, key, "left")
    schema = docs.schema

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            t, g = schema.names.index("text"), len(schema.names)
            texts = [strip(a, set(b or ())) for a, b in zip(batch.column(t).to_pylist(), batch.column(g).to_pylist())]
            arrays = [pa.array(texts, batch.column(t).type) if i == t else batch.column(i) for i in range(g)]
            yield pa.RecordBatch.from_arrays(arrays, names=schema.names)

    return joined.select(*schema.names, found).mapInArrow(run, schema)


def strip(text: str | None, gone: set[int]) -> str | None:
    if not text or not gone:
        return text
    return "\n".join(line for line in text.split("\n") if not any(h in gone for h, _ in lines_of(line)))


