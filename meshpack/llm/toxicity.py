"""Toxicity by non-negative positive-unlabelled learning.

Confirmed toxic documents and unlabelled ones train a logistic classifier in numpy.  The
risk of the negative class is estimated from unlabelled text less the part that positives of
the assumed class prior contribute, and kept from falling below zero, so that the classifier
can't gain by fitting single unlabelled rows.

Features are hashed words and word beginnings of whole texts, by presence.  Only features
that positives show more often than unlabelled texts do, beyond chance, get a weight; a word
without one costs a table lookup.

Fitting takes a bounded sample: at most ``MAX_POSITIVE`` toxic rows and ``MAX_UNLABELLED``
others, chosen by a hash of the id among rows that are not held out.  Scoring covers all rows.

Defined cases: null and empty texts get the score of a text without known features; with no
positives in the training rows all scores are next to 0; ties in the sample go by id; repeated rows
get equal scores; ids may be of any type; ``drop_toxic`` keeps all columns, whatever their names.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, fresh, map_texts, utf8

MAX_POSITIVE = 3000
MAX_UNLABELLED = 9000
DIMENSION = 1 << 20
FEATURES = 20_000
#: Positives that must show a feature.
LEAST = 3
CUT_OFF = 0.7
REMEMBERED = 400_000

WORDS = bytes(b + 32 if 0x41 <= b <= 0x5A else b if 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256))


def held_out(doc_id="doc_id") -> F.Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1, F.lit(False))


def features_of(word: bytes) -> tuple[int, ...]:
    """Hashed features of a word: itself, and its beginnings of 4, 5 and 6 letters."""
    import xxhash

    text = word.decode("utf-8", "replace")
    parts = {text, *(f"{text[:n]}*" for n in (4, 5, 6) if len(text) > n)}
    return tuple(xxhash.xxh3_64_intdigest(p.encode()) % DIMENSION for p in parts)


def features(text: str | None) -> np.ndarray:
    found: set[int] = set()
    for word in set(utf8(text).translate(WORDS).split()):
        found.update(features_of(word))
    return np.fromiter(found, np.int32, len(found))


def training_sample(docs: DataFrame, labels: DataFrame, max_positive: int, max_unlabelled: int) -> tuple[DataFrame, float]:
    """(row, doc_id, side, f), stored: feature sets of confirmed toxic (side 1) and of unlabelled texts; and the class prior."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    share = known.agg(F.count("*").alias("n"), F.sum("toxic").alias("toxic")).first()
    order = F.xxhash64(F.lit("fit"), "doc_id")
    positive = known.where("toxic = 1").orderBy(order, "doc_id").limit(max_positive).select("doc_id", F.lit(1).alias("side"))
    others = docs.where(F.col("doc_id").isNotNull() & ~held_out()).select("doc_id").orderBy(order, "doc_id").limit(max_unlabelled).select("doc_id", F.lit(0).alias("side"))
    # both lists are bounded by the parameters above
    chosen = docs.select("doc_id", "text").join(F.broadcast(positive.union(others)), "doc_id")
    sets = map_texts(chosen, lambda: lambda texts: {"f": [features(t) for t in texts]}, [T.StructField("f", T.ArrayType(T.IntegerType()))], ["doc_id", "side"])
    return cut(sets.withColumn("row", F.monotonically_increasing_id())), (share["toxic"] or 0) / share["n"] if share["n"] else 0.0


class Rows:
    """Sparse rows of feature numbers, with the products that a linear model needs."""

    def __init__(self, n: int, row: np.ndarray, col: np.ndarray):
        self.n, self.row, self.col = n, row, col

    @classmethod
    def of(cls, sets: list[np.ndarray], good: np.ndarray) -> Rows:
        """Of the features in each set, those among the sorted ``good`` ones, by their place there."""
        kept = [np.flatnonzero(np.isin(good, s)) for s in sets]
        return cls(len(kept), np.repeat(np.arange(len(kept)), [len(k) for k in kept]), np.concatenate(kept) if kept else np.zeros(0, np.int64))

    def times(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, w[self.col], self.n)

    def back(self, r: np.ndarray, d: int) -> np.ndarray:
        return np.bincount(self.col, r[self.row], d)


def chosen_features(f: np.ndarray, a: np.ndarray, b: np.ndarray, n: int, m: int) -> np.ndarray:
    """Of features ``f``, shown by ``a`` of ``n`` positives and ``b`` of ``m`` unlabelled texts, the sorted ones that tell."""
    # lift over the rate among unlabelled texts, in standard deviations
    expected = np.maximum(b / m, 1 / m) * n
    z = (a - expected) / np.sqrt(expected)
    lift = (a / n) / np.maximum(b / m, 0.5 / m)
    good = np.flatnonzero((a >= LEAST) & (z > 2.5) & (lift > 2))
    return np.sort(f[good[np.lexsort((f[good], -z[good]))][:FEATURES]])


def risk(p: Rows, u: Rows, w: np.ndarray, bias: float, prior: float) -> tuple[float, float]:
    """Risk of the positive class, and that of the negative one as estimated from unlabelled texts, with logistic losses."""
    # -log s(f) for the positive class, -log s(-f) for the negative one
    fp, fu = p.times(w) + bias, u.times(w) + bias
    return prior * np.logaddexp(0, -fp).mean(), np.logaddexp(0, fu).mean() - prior * np.logaddexp(0, fp).mean()


def direction(p: Rows, u: Rows, w: np.ndarray, bias: float, prior: float, decay: float) -> np.ndarray:
    """Gradient for (w, bias) of both risks; where the negative one has fallen below zero, of its ascent alone."""
    sigmoid = lambda x: 1 / (1 + np.exp(-np.clip(x, -30, 30)))
    fp, fu = p.times(w) + bias, u.times(w) + bias
    rise, own = sigmoid(fu) / u.n, -prior * sigmoid(fp) / p.n
    if risk(p, u, w, bias, prior)[1] >= 0:
        rp, ru = prior * (sigmoid(fp) - 1) / p.n + own, rise
    else:  # only climb back: step against the overfitted part
        rp, ru = -own, -rise
    return np.append(p.back(rp, len(w)) + u.back(ru, len(w)) + decay * w, rp.sum() + ru.sum())


def descend(p: Rows, u: Rows, good: np.ndarray, prior: float, rounds: int = 400, rate: float = 0.1, decay: float = 1e-4) -> dict:
    """Weights of the ``good`` features by moment-scaled steps down the non-negative risk."""
    w, bias = np.zeros(len(good)), -1.0
    sums, moves = np.zeros(len(good) + 1), np.zeros(len(good) + 1)
    for step in range(1, rounds + 1):
        grad = direction(p, u, w, bias, prior, decay)
        moves = 0.9 * moves + 0.1 * grad
        sums = 0.99 * sums + 0.01 * grad**2
        move = rate * (moves / (1 - 0.9**step)) / (np.sqrt(sums / (1 - 0.99**step)) + 1e-8)
        w, bias = w - move[:-1], bias - move[-1]
    return {"index": good, "weight": w, "bias": float(bias)}


#: A model that knows nothing scores 0.
NOTHING = {"index": np.zeros(0, np.int64), "weight": np.zeros(0), "bias": -30.0}


def fit(positive: list[np.ndarray], unlabelled: list[np.ndarray], prior: float) -> dict:
    """Weights from feature sets in memory; none without positives."""
    if not positive or not unlabelled or prior <= 0:
        return NOTHING
    a, b = (np.bincount(np.concatenate(sets), minlength=DIMENSION) for sets in (positive, unlabelled))
    good = chosen_features(np.arange(DIMENSION), a, b, len(positive), len(unlabelled))
    return descend(Rows.of(positive, good), Rows.of(unlabelled, good), good, prior) if len(good) else NOTHING


def scorer(model: dict):
    """Kernel over texts; remembers which words have a weighted feature."""
    weight = dict(zip(model["index"].tolist(), model["weight"].tolist()))
    known: dict[bytes, tuple[int, ...]] = {}

    def score(text: str | None) -> float:
        got: set[int] = set()
        for word in set(utf8(text).translate(WORDS).split()):
            f = known.get(word)
            if f is None:
                if len(known) >= REMEMBERED:
                    known.clear()
                f = known[word] = tuple(k for k in features_of(word) if k in weight)
            if f:
                got.update(f)
        x = model["bias"] + sum(weight[k] for k in sorted(got))
        return float(1 / (1 + np.exp(-min(30.0, max(-30.0, x)))))

    return lambda texts: {"score": [score(t) for t in texts]}


def trained(docs: DataFrame, labels: DataFrame, max_positive: int = MAX_POSITIVE, max_unlabelled: int = MAX_UNLABELLED) -> dict:
    """The model of a sample.  Features are counted and chosen on the executors; the driver gets at most
    DIMENSION counts, and of each sampled row the chosen features it has."""
    spark = docs.sparkSession
    sets, prior = training_sample(docs, labels, max_positive, max_unlabelled)
    rows = sets.select("side", F.col("doc_id").cast("string").alias("id"), "row").toArrow().to_pylist()
    rows.sort(key=lambda r: (-r["side"], len(r["id"]), r["id"], r["row"]))  # rows come in any order; the fit must not depend on it
    n = sum(r["side"] for r in rows)
    m = len(rows) - n
    if not n or not m or prior <= 0:
        return NOTHING
    each = sets.select("row", "side", F.explode("f").alias("f"))
    shown = each.groupBy("f").agg(F.sum("side").alias("a"), F.count("*").alias("n")).where(F.col("a") >= LEAST).toArrow()
    f, a = shown["f"].to_numpy(), shown["a"].to_numpy()
    good = chosen_features(f, a, shown["n"].to_numpy() - a, n, m)
    if not len(good):
        return NOTHING
    known = spark.createDataFrame([(int(k),) for k in good], "f int")
    pairs = each.join(F.broadcast(known), "f").select("row", "f").toArrow()
    number = {r["row"]: k for k, r in enumerate(rows)}
    at = np.fromiter(map(number.__getitem__, pairs["row"].to_pylist()), np.int64, len(pairs))
    col = np.searchsorted(good, pairs["f"].to_numpy())
    order = np.lexsort((col, at))
    at, col = at[order], col[order]
    side = at < n
    return descend(Rows(n, at[side], col[side]), Rows(m, at[~side] - n, col[~side]), good, prior)


def scores(docs: DataFrame, model: dict, keep=None, name: str = "score") -> DataFrame:
    """``docs`` with a score from 0 to 1."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # at most FEATURES numbers
    return map_texts(docs, lambda: (lambda k: lambda texts: {name: k(texts)["score"]})(scorer(sent.value)), [T.StructField(name, T.DoubleType())], keep)


def toxicity(docs: DataFrame, labels: DataFrame, cut_off: float = CUT_OFF) -> DataFrame:
    """doc_id, held_out, score and predicted of every row."""
    got = scores(docs, trained(docs, labels), ["doc_id"])
    return got.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= cut_off).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, cut_off: float = CUT_OFF) -> DataFrame:
    """``docs`` without rows that score ``cut_off`` or more, columns unchanged."""
    (name,) = fresh(docs.columns, "score")
    got = scores(docs, trained(docs, labels), name=name)
    return got.where(F.col(name) < cut_off).select(*docs.columns)
