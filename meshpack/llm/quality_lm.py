"""Quality by the perplexity of an interpolated modified Kneser-Ney model of characters.

The model is trained on all trusted texts (label quality = 1).  Counts of n-grams of ``ORDER``
characters are gathered from every document, trusted or not, summed by map-side and shuffled
aggregation, and joined, shard by shard of their hash, with the tables of each lower order:
contexts, continuation counts and discounts.  What results is a log-probability for every
n-gram of the corpus.  Documents then sum these over their whole text: the most frequent n-grams,
up to a stated number, are sent to all executors; what a document has of others is joined with
their probabilities in shards of the n-gram's hash.  Such n-grams are rare by choice, so the join
is small and has no hot key.  Sums are of whole steps of ``LOG_STEP``, so they don't depend on
which n-grams were sent.  A quantile of the trusted texts' perplexity in the same language, over
an exact histogram, sets the threshold.

Defined cases: null and empty texts have no perplexity and are not kept; a null language is a
language of its own; a language with fewer than ``ENOUGH`` trusted texts takes the threshold
of all languages together; without trusted texts all perplexities and thresholds are null and
nothing is rejected but empty texts; rows that repeat get equal results; ids may be of any type that
``labels`` has too; ``keep_fluent`` keeps all columns, whatever their names.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Lookup, cut, fresh, map_texts, released

ORDER = 4
QUANTILE = 0.995
#: Allowed excess over the quantile, in natural-log units of perplexity.
SLACK = 0.02
ENOUGH = 50
#: Steps of the histogram of log-perplexity.
STEP = 0.001
#: N-grams that are sent to all executors, the most frequent ones (12 bytes each).
HEAD_GRAMS = 2_000_000
#: Log-probabilities are counted in steps of this.
LOG_STEP = 2.0**-24
#: Trusted ids up to which they are sent to all executors.
BROADCAST_IDS = 2_000_000
#: Code points gathered by a task before it sums them up.
GATHER = 3_000_000
PAD = "\x02"


def code_points(texts: list[str], order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """Code points of lower-cased texts, each after ``order - 1`` marks, and where texts end."""
    lead = PAD * (order - 1)
    parts = [lead + t.lower() for t in texts]
    sizes = np.fromiter(map(len, parts), np.int64, len(parts))
    flat = np.frombuffer("".join(parts).encode("utf-32-le", "replace"), "<u4")
    return flat, np.cumsum(sizes)


def gram_starts(ends: np.ndarray, order: int = ORDER) -> np.ndarray:
    """Places of the n-grams: all but the last ``order - 1`` of each text."""
    if not len(ends):
        return np.zeros(0, bool)
    ok = np.ones(int(ends[-1]), bool)
    for k in range(1, order):
        ok[ends - k] = False
    return ok


class Gather:
    """Distinct n-grams of a task with their counts in trusted texts.

    Characters get 16-bit numbers in order of arrival; when these run out, the sums are let go.
    """

    def __init__(self, order: int = ORDER):
        self.order = order
        self.reset()

    def reset(self):
        self.number = np.zeros(0x110000, np.uint16)
        self.chars: list[np.ndarray] = []
        self.n = 0
        self.keys = np.zeros(0, np.uint64)
        self.counts = np.zeros((2, 0), np.int64)  # in trusted texts, in all
        self.waiting: list[tuple[np.ndarray, int]] = []
        self.size = 0

    def add(self, texts: list[str], weight: int):
        """Yields batches that had to be let go."""
        if not texts:
            return
        flat, ends = code_points(texts, self.order)
        seen = np.zeros(0x110000, bool)
        seen[flat] = True
        new = np.flatnonzero(seen & (self.number == 0))
        if self.n + len(new) > 65_535:
            yield from self.flush()
            new = np.flatnonzero(seen)
        self.number[new] = np.arange(self.n + 1, self.n + 1 + len(new))
        self.chars.append(new)
        self.n += len(new)
        ids, keys = self.number[flat].astype(np.uint64), None
        for k in range(self.order):
            part = ids[k : len(ids) - self.order + 1 + k]
            keys = part if keys is None else (keys << np.uint64(16)) | part
        self.waiting.append((keys[gram_starts(ends, self.order)[: len(keys)]], weight))
        self.size += len(keys)
        if self.size > GATHER:
            self.settle()

    def settle(self):
        keys, counts = [self.keys], [self.counts]
        for weight in (0, 1):
            some = [k for k, w in self.waiting if w == weight]
            if some:
                k, c = np.unique(np.concatenate(some), return_counts=True)
                keys.append(k)
                counts.append(np.stack([c * weight, c]))
        every, each = np.concatenate(keys), np.concatenate(counts, axis=1)
        self.keys, at = np.unique(every, return_inverse=True)
        self.counts = np.stack([np.bincount(at, c, len(self.keys)) for c in each]).astype(np.int64)
        self.waiting, self.size = [], 0

    def flush(self):
        self.settle()
        if len(self.keys):
            chars = np.concatenate([[0], *self.chars]).astype("<u4")
            points = np.empty((len(self.keys), self.order), "<u4")
            for k in range(self.order):
                points[:, k] = chars[(self.keys >> np.uint64(16 * (self.order - 1 - k))).astype(np.int64) & 0xFFFF]
            for lo in range(0, len(points), 100_000):
                some = points[lo : lo + 100_000]
                grams = some.tobytes().decode("utf-32-le")
                yield pa.RecordBatch.from_arrays(
                    [pa.array([grams[i : i + self.order] for i in range(0, len(grams), self.order)], pa.string()), *(pa.array(c[lo : lo + 100_000], pa.int64()) for c in self.counts)],
                    names=["g", "c", "a"],
                )
        self.reset()


def gram_counts(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """(g, c, a): every n-gram of ``docs`` (text, trusted) with its counts in trusted and in all texts."""

    def run(batches):
        gather = Gather(order)
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                texts, trusted = part.column(0).to_pylist(), part.column(1).to_pylist()
                for weight in (0, 1):
                    yield from gather.add([t for t, w in zip(texts, trusted) if t and w == weight], weight)
        yield from gather.flush()

    schema = T.StructType([T.StructField("g", T.StringType()), *(T.StructField(n, T.LongType()) for n in ("c", "a"))])
    return docs.select("text", "trusted").mapInArrow(released(run), schema).groupBy("g").agg(F.sum("c").alias("c"), F.sum("a").alias("a"))


def counts_of_counts(df: DataFrame) -> list[float]:
    """Discounts for counts of 1, 2 and 3 or more, from the table's counts of counts."""
    n = df.agg(*(F.count_if(F.col("c") == k).alias(f"n{k}") for k in (1, 2, 3, 4))).first()
    n1, n2, n3, n4 = (float(x or 0) for x in n)
    if not n1 or not n2:
        return [0.5, 0.75, 0.9]  # too small a table to estimate from
    y = n1 / (n1 + 2 * n2)
    raw = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 2.0]
    return [min(max(d, 0.05), k - 0.05) for k, d in enumerate(raw, 1)]


def discount(c: Column, d: list[float]) -> Column:
    return F.when(c == 1, d[0]).when(c == 2, d[1]).when(c >= 3, d[2]).otherwise(0.0)


def log_probabilities(grams: DataFrame, order: int = ORDER) -> DataFrame:
    """(g, a, lp) for every n-gram of stored ``grams`` (g, c, a), by interpolation of all orders; lp in steps."""
    tables, upper = [], grams.where("c > 0").select("g", "c")
    for k in range(order, 0, -1):
        tables.append((k, upper, counts_of_counts(upper)))
        # one order down a count is the number of distinct characters seen before the n-gram
        upper = upper.select(F.expr(f"substring(g, 2, {max(k - 1, 1)})").alias("g")).groupBy("g").agg(F.count("*").alias("c"))
        if k > 1:
            upper = cut(upper)
    symbols = tables[-1][1].count() + 1  # and one for all that training did not see
    out = grams.select("g", "a", F.col("c").alias("c_own"))
    lp = F.lit(1.0 / symbols)
    for k, table, d in reversed(tables):
        prefix = F.expr(f"substring(g, 1, {k - 1})") if k > 1 else F.lit("")
        ctx = table.groupBy(prefix.alias("x")).agg(
            F.sum("c").alias(f"t{k}"),
            *(F.sum(F.when(test, 1).otherwise(0)).alias(f"m{k}{i}") for i, test in enumerate((F.col("c") == 1, F.col("c") == 2, F.col("c") >= 3))),
        )
        out = out.withColumn("x", F.expr(f"substring(g, {order - k + 1}, {k - 1})") if k > 1 else F.lit(""))
        # tables of one and no character have at most as many rows as Unicode has code points
        out = out.join(F.broadcast(ctx) if k <= 2 else ctx, "x", "left").drop("x")
        if k == order:
            c = F.col("c_own")
        else:
            out = out.withColumn("s", F.expr(f"substring(g, {order - k + 1}, {k})"))
            low = table.select(F.col("g").alias("s"), F.col("c").alias(f"c{k}"))
            out = out.join(F.broadcast(low) if k == 1 else low, "s", "left").drop("s")
            c = F.coalesce(F.col(f"c{k}"), F.lit(0))
        t = F.col(f"t{k}").cast("double")
        gamma = (d[0] * F.col(f"m{k}0") + d[1] * F.col(f"m{k}1") + d[2] * F.col(f"m{k}2")) / t
        lp = F.when(t > 0, (F.greatest(c - discount(c, d), F.lit(0.0)) / t) + gamma * lp).otherwise(lp)
        out = out.withColumn(f"p{k}", lp)
        lp = F.col(f"p{k}")
    return out.select("g", "a", F.round(F.ln(f"p{order}") / LOG_STEP).cast("long").alias("lp"))


def mixed(flat: np.ndarray, order: int = ORDER) -> np.ndarray:
    """64-bit mix of each n-gram of code points."""
    out = np.zeros(max(0, len(flat) - order + 1), np.uint64)
    for k in range(order):
        out = (out ^ flat[k : k + len(out)].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return out | np.uint64(1)


def head_of(logs: DataFrame, n_grams: int, size: int = HEAD_GRAMS) -> int:
    """The least frequency of which at most ``size`` n-grams have as much or more; 0 if all may go."""
    if n_grams <= size:
        return 0
    # steps of an eighth: a few hundred rows, whatever the number of n-grams
    step = F.floor(F.log2("a") * 8).cast("int")
    counts = sorted(((r["s"], r["n"], r["least"]) for r in logs.groupBy(step.alias("s")).agg(F.count("*").alias("n"), F.min("a").alias("least")).collect()), reverse=True)
    total, least = 0, 2**62
    for _, n, low in counts:
        total += n
        if total > size:
            break
        least = low
    return least


def perplexities(docs: DataFrame, logs: DataFrame, n_grams: int, keep, size: int = HEAD_GRAMS) -> DataFrame:
    """``keep`` columns of ``docs``, stored, with n_scored and log_ppl (per character)."""
    least = head_of(logs, n_grams, size)
    head = logs.where(F.col("a") >= least).select("g", "lp").toArrow()  # at most ``size`` rows
    flat = np.frombuffer("".join(head["g"].to_pylist()).encode("utf-32-le"), "<u4")
    keys = mixed(flat)[::ORDER] if len(flat) else np.zeros(0, np.uint64)
    sent = docs.sparkSession.sparkContext.broadcast((keys, np.maximum(head["lp"].to_numpy(), -(2**31) + 1).astype(np.int32)))
    absent = 1  # log-probabilities are not above 0

    def make():
        table = Lookup(*sent.value, absent)

        def kernel(texts):
            some = [i for i, t in enumerate(texts) if t]
            flat, ends = code_points([texts[i] for i in some])
            n, total, rest = [0] * len(texts), [0] * len(texts), [None] * len(texts)
            if some:
                ok = gram_starts(ends)
                got = np.zeros(len(flat), np.int64)
                keys = mixed(flat)
                got[: len(keys)] = table.get(keys)
                out = ok & (got == absent)
                got[~ok | out] = 0
                begin = np.concatenate([[0], ends[:-1]])
                sums = np.add.reduceat(got, begin)
                at = np.flatnonzero(out)
                for j, i in enumerate(some):
                    n[i], total[i] = int(ends[j] - begin[j]) - (ORDER - 1), int(sums[j])
                for k, j in zip(at.tolist(), (np.searchsorted(begin, at, "right") - 1).tolist()):
                    i = some[j]
                    rest[i] = rest[i] or []
                    rest[i].append(flat[k : k + ORDER].tobytes().decode("utf-32-le"))
            return {"n_scored": n, "steps": total, "rest": rest}

        return kernel

    added = [T.StructField("n_scored", T.LongType()), T.StructField("steps", T.LongType()), T.StructField("rest", T.ArrayType(T.StringType()))]
    scored = map_texts(docs, make, added, keep)
    if least:
        scored = cut(scored.withColumn("row", F.monotonically_increasing_id()))
        each = scored.where("rest is not null").select("row", F.explode("rest").alias("g"))
        tail = each.join(logs.where(F.col("a") < least).select("g", "lp").hint("merge"), "g").groupBy("row").agg(F.sum("lp").alias("more"))
        scored = scored.join(tail, "row", "left").withColumn("steps", F.col("steps") + F.coalesce("more", F.lit(0)))
    per = F.when(F.col("n_scored") > 0, -F.col("steps") * LOG_STEP / F.col("n_scored"))
    return cut(scored.select(*keep, "n_scored", per.alias("log_ppl")))


def thresholds(scored: DataFrame, quantile: float = QUANTILE) -> DataFrame:
    """(lang, limit, n): upper edge of the step that holds the quantile; lang null is for all."""
    steps = scored.where("trusted = 1 and log_ppl is not null").select(F.coalesce("lang", F.lit("")).alias("lang"), F.floor(F.col("log_ppl") / STEP).alias("step"))
    counts = steps.groupBy("lang", "step").agg(F.count("*").alias("n"))
    both = counts.unionByName(counts.groupBy("step").agg(F.sum("n").alias("n")).select(F.lit(None).cast("string").alias("lang"), "step", "n"))
    upto = Window.partitionBy("lang").orderBy("step")
    ranked = both.withColumns({"upto": F.sum("n").over(upto), "total": F.sum("n").over(Window.partitionBy("lang"))})
    return ranked.where(F.col("upto") >= quantile * F.col("total")).groupBy("lang").agg(((F.min("step") + 1) * STEP).alias("limit"), F.first("total").alias("n"))


def quality(docs: DataFrame, labels: DataFrame, quantile: float = QUANTILE, slack: float = SLACK, head_grams: int = HEAD_GRAMS) -> DataFrame:
    """doc_id, lang, log_ppl, perplexity, limit and kept of every row of ``docs``."""
    trusted = labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct().withColumn("trusted", F.lit(1))
    few = trusted.count() <= BROADCAST_IDS
    own = docs.select("doc_id", "text", "lang").join(F.broadcast(trusted) if few else trusted.hint("merge"), "doc_id", "left").na.fill(0, ["trusted"])
    grams = cut(gram_counts(own))
    n = grams.agg(F.count("*"), F.sum("c")).first()
    if not n[1]:
        out = docs.select("doc_id", "lang", F.lit(0).cast("long").alias("n_scored"), F.lit(None).cast("double").alias("log_ppl"), (F.length(F.coalesce("text", F.lit(""))) > 0).alias("kept"))
        return out.select("doc_id", "lang", "n_scored", "log_ppl", F.lit(None).cast("double").alias("perplexity"), F.lit(None).cast("double").alias("threshold"), "kept")
    logs = cut(log_probabilities(grams))
    scored = perplexities(own, logs, n[0], ["doc_id", "lang", "trusted"], head_grams)
    limits = thresholds(scored, quantile)
    every = limits.where("lang is null").first()
    known = limits.where(F.col("lang").isNotNull() & (F.col("n") >= ENOUGH)).select(F.col("lang").alias("_l"), "limit")
    joined = scored.withColumn("_l", F.coalesce("lang", F.lit(""))).join(known, "_l", "left")
    limit = F.coalesce("limit", F.lit(every["limit"] if every else None).cast("double")) + slack
    return joined.select(
        "doc_id", "lang", "n_scored", "log_ppl", F.exp("log_ppl").alias("perplexity"), F.exp(limit).alias("threshold"),
        F.coalesce(F.col("log_ppl") <= limit, F.lit(False)).alias("kept"),
    )


def keep_fluent(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``docs`` without the texts whose perplexity is above their language's threshold."""
    (name,) = fresh(docs.columns, "gone")
    gone = quality(docs, labels).where("not kept").select(F.col("doc_id").alias(name)).distinct()
    return docs.join(gone, docs.doc_id.eqNullSafe(gone[name]), "left_anti")
