"""Secret scans with multipart credential linking, in DataFrame functions only.

Each kind of part is found by one expression.  Matches are fenced with a control character,
the text is split at the fences, and positions follow from the lengths of the pieces, so no
text leaves the scan: what is dealt out are lengths.  Weak parts (account names, long mixed
strings, endpoints) are candidates only; an interval join within ``SCOPE`` code points of the
same text tells which complementary parts stand near, and a candidate is reported only then:

* an account name near a secret (assignment, hex string or long mixed string),
* a long mixed string near an access identifier or an account name,
* an endpoint near both an identifier and a secret.

The join's key is the text and a bucket of ``SCOPE`` code points; a part stands in every bucket
from its start to its end, so its rows are bounded by its length.  Parts have a least length, so
a bucket holds a bounded number of them and no key can grow.

Defined cases: null is the empty text; matches too short for their kind are dropped after
matching; a long mixed string that overlaps an assured span is none; rows that repeat with
equal id and text get equal results; ids may be of any type; ties of start go by kind in the listed order;
``redact`` keeps all columns, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, fresh

#: The kinds in order, with expression, the group whose length counts, the least length.
#: Where words in either case begin a match, their first letters are looked for first.
KINDS = [
    ("assign", r"""(?=[PSTApsta])((?i)password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"(AKIA[A-Z0-9]+)", 1, 20),
    # runs of these characters are maximal, so asking for 24 here drops the same matches
    ("hex", r"([0-9a-f]{24,})", 1, 24),
    ("account", r"""(?=[CALUcalu])((?i)client_?id|access_?id|account|login|user_?name|user)["']?\x20*[:=]\x20*["']?([A-Za-z0-9@._+-]+)""", 2, 3),
    ("mixed", r"((?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*+[0-9])(?=[a-z0-9+/_-]*+[A-Z])(?=[A-Z0-9+/_-]*+[a-z])[A-Za-z0-9+/_-]{32,}+)", 1, 32),
    ("endpoint", r"""(?=[AHJMPRSahjmprs])((?i)(?:https?|jdbc:[a-z]+|postgres|mysql|mongodb|redis|amqp|s3)://[^\x00-\x20"'<>]+)""", 1, 8),
]
NAMES = [k for k, *_ in KINDS]
#: Signs of which a text with a match of the kind has at least one; none named: any text may.
SIGNS = {"assign": ("=", ":"), "access": ("AKIA",), "hex": (), "account": ("=", ":"), "mixed": (), "endpoint": ("://",)}
ASSURED = ("assign", "access", "hex")
SECRETS = ("assign", "hex", "mixed")
IDENTIFIERS = ("access", "account")
SCOPE = 200
#: Found spans up to which redaction joins them by broadcast.
BROADCAST_TEXTS = 200_000

FENCE, MARK = "\x01", "\x02"
SPANS = "array<struct<start:bigint,kind:int,stop:bigint>>"


def _pieces(text: Column, pattern: str, group: int) -> Column:
    """Lengths of the pieces between matches and of matches, in turn, and of the group that counts."""
    fenced = F.split(F.regexp_replace(text, pattern, f"{FENCE}$0{MARK}${group}{FENCE}"), FENCE)
    return F.transform(
        fenced,
        lambda x: F.struct(
            F.length(F.substring_index(x, MARK, 1)).alias("size"),
            F.length(F.substring_index(x, MARK, -1)).alias("counts"),
        ),
    )


def keyed(docs: DataFrame) -> list[Column]:
    """Key of a row: equal for rows that repeat, and spread where only the texts are equal."""
    return [F.xxhash64("doc_id").alias("id"), F.xxhash64("text").alias("th")]


def scanned(docs: DataFrame) -> DataFrame:
    """(id, th, kinds): piece lengths of the kinds found, for each distinct text with any.

    Expressions run only on texts with a sign that the kind can't do without.  One generator and
    one exchange stand between the scan and all that reads it, so no filter is moved below it and
    the scan is made once, without a stored copy.
    """
    text = F.coalesce("text", F.lit(""))
    marks = text.contains(FENCE) | text.contains(MARK)
    text = F.when(marks, F.translate(text, FENCE + MARK, "\x03\x03")).otherwise(text)  # no kind matches these
    one = lambda i, p, g, signs: F.when(_any(text, signs), F.struct(F.lit(i).alias("kind"), _pieces(text, p, g).alias("pieces")))
    kinds = F.array(*(one(i, p, g, SIGNS[k]) for i, (k, p, g, _) in enumerate(KINDS)))
    found = F.filter(kinds, lambda k: F.size(k["pieces"]) > 1)
    return docs.select(*keyed(docs), F.explode(found).alias("k")).groupBy("id", "th").agg(F.collect_set("k").alias("kinds"))


def _any(text: Column, signs: tuple[str, ...]) -> Column:
    out = F.lit(not signs)
    for s in signs:
        out = out | text.contains(s)
    return out


def parts_of(found: DataFrame) -> DataFrame:
    """(id, th, kind, start, stop) of every part of each distinct text."""
    rows = found.select("id", "th", F.explode("kinds").alias("k")).select("id", "th", F.col("k.kind").alias("kind"), F.posexplode("k.pieces").alias("at", "piece"))
    upto = Window.partitionBy("id", "th", "kind").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    least = F.element_at(F.array(*(F.lit(n) for *_, n in KINDS)), F.col("kind") + 1)
    ends = rows.withColumn("stop", F.sum("piece.size").over(upto))
    parts = ends.where((F.col("at") % 2 == 1) & (F.col("piece.counts") >= least))
    return parts.select("id", "th", "kind", (F.col("stop") - F.col("piece.size")).alias("start"), "stop")


def linked(parts: DataFrame, scope: int = SCOPE) -> DataFrame:
    """The weak parts of ``parts`` whose complementary parts co-occur within the scope."""
    number = {k: i for i, k in enumerate(NAMES)}
    among = lambda c, ks: F.col(c).isin([number[k] for k in ks])
    weak = parts.where(~among("kind", ASSURED))
    # a weak part stands in each bucket that it or its scope touches, the other in each that it or its end touches:
    # whatever pair is near then shares a bucket, and pairs that share several do no harm to the aggregates
    here = weak.withColumn("bucket", F.explode(F.sequence(F.floor((F.col("start") - scope) / scope), F.floor((F.col("stop") + scope) / scope))))
    other = parts.select("id", "th", F.col("kind").alias("k"), F.col("start").alias("a"), F.col("stop").alias("b"), F.explode(F.sequence(F.floor(F.col("start") / scope), F.floor(F.col("stop") / scope))).alias("bucket"))
    near = here.join(other, ["id", "th", "bucket"]).where("a <= stop + %d and b + %d >= start" % (scope, scope))
    overlap = (F.col("a") < F.col("stop")) & (F.col("start") < F.col("b"))
    known = near.groupBy("id", "th", "kind", "start", "stop").agg(
        F.bool_or(among("k", SECRETS) & ~overlap).alias("secret"),
        F.bool_or(among("k", IDENTIFIERS) & ~overlap).alias("identifier"),
        F.bool_or(among("k", ASSURED) & overlap).alias("assured"),
    )
    case = (
        (F.col("kind") == number["account"]) & F.col("secret")
        | (F.col("kind") == number["mixed"]) & F.col("identifier") & ~F.col("assured")
        | (F.col("kind") == number["endpoint"]) & F.col("identifier") & F.col("secret")
    )
    return known.where(case).select("id", "th", "kind", "start", "stop")


def spans_by_text(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """(id, th, spans) of each distinct text with spans: (start, kind, stop) in order."""
    parts = parts_of(scanned(docs))
    assured = parts.where(F.col("kind") < len(ASSURED))
    return (
        assured.unionByName(linked(parts, scope)).groupBy("id", "th")
        .agg(F.array_sort(F.collect_list(F.struct("start", "kind", "stop"))).alias("spans"))
    )


def written(spans: Column) -> Column:
    name = lambda s: F.element_at(F.array(*map(F.lit, NAMES)), s["kind"] + 1)
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", name(s), s["start"].cast("string"), s["stop"].cast("string"))), ",")


def secret_spans(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """doc_id and spans of every row of ``docs``: (start, kind, stop) in code points."""
    none = F.array().cast(SPANS)
    return docs.select("doc_id", *keyed(docs)).join(spans_by_text(docs, scope), ["id", "th"], "left").select("doc_id", F.coalesce(F.col("spans").cast(SPANS), none).alias("spans"))


def report(docs: DataFrame) -> DataFrame:
    """doc_id, the number of spans of the assured kinds, their digest, and all spans."""
    rows = secret_spans(docs)
    base = F.filter("spans", lambda s: s["kind"] < len(ASSURED))
    count = lambda i: F.size(F.filter("spans", lambda s: s["kind"] == i)).cast("long")
    return rows.select(
        "doc_id", *(count(i).alias(f"n_{k}") for i, k in enumerate(ASSURED)),
        F.sha2(written(base), 256).alias("base_sha256"), written(F.col("spans")).alias("spans"),
    )


def redact(docs: DataFrame, broadcast_texts: int = BROADCAST_TEXTS) -> DataFrame:
    """``docs`` with every span replaced by its kind in square brackets, columns unchanged.

    Spans that overlap are replaced together, under the kind of the first.
    """
    spans = cut(spans_by_text(docs))
    i, h, found = fresh(docs.columns, "id", "th", "spans")
    side = spans.withColumnsRenamed({"id": i, "th": h, "spans": found})
    few = spans.count() <= broadcast_texts and (spans.agg(F.sum(F.size("spans"))).first()[0] or 0) <= 10 * broadcast_texts
    own = docs.withColumns(dict(zip((i, h), keyed(docs))))
    joined = own.join(F.broadcast(side) if few else side.hint("merge"), [i, h], "left")
    name = lambda s: F.concat(F.lit("["), F.upper(F.element_at(F.array(*map(F.lit, NAMES)), s["kind"] + 1)), F.lit("]"))
    start = F.struct(F.lit("").alias("out"), F.lit(0).cast("long").alias("at"))
    gap = lambda a, s: F.substring("text", (a["at"] + 1).cast("int"), F.greatest(s["start"] - a["at"], F.lit(0)).cast("int"))

    def step(a, s):
        first = s["start"] >= a["at"]
        return F.struct(
            F.when(first, F.concat(a["out"], gap(a, s), name(s))).otherwise(a["out"]).alias("out"),
            F.greatest(a["at"], s["stop"]).alias("at"),
        )

    rest = lambda a: F.concat(a["out"], F.substring("text", (a["at"] + 1).cast("int"), 2**31 - 1))
    clean = F.when(F.col(found).isNull(), F.col("text")).otherwise(F.aggregate(found, start, step, rest))
    return joined.select(*(clean.alias("text") if c == "text" else F.col(c) for c in docs.columns))
