"""Boolean and float coding: operators, baselines and measures on pruned trees."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import bits
from ..functions.shifts import shr
from ..operators import analysis, baselines, layout, measures, mesh, prune, pxor, run52
from ..operators.mesh import Params
from ..operators.storage import cut
from ..sources.tables import MESHES, table
from . import sql
from .base import SNAPSHOTS, cells_of, domains_of, local_of, pruned_of, query, with_params

P = Params()
FIELDS = ("rho", "v", "p", "smooth")


def _all(frames):
    return reduce(lambda a, b: a.unionByName(b), frames)


def _union(texts):
    return " UNION ALL ".join(f"SELECT * FROM ({t})" for t in texts)


def _d(x):
    return x.cast("double")


# ---- runs --------------------------------------------------------------------------------------

query("op_runs", sql.with_(sql.pruned("events", 16, P) + sql.run_table("pruned", "refined"), "SELECT domain, run_no, bit, len FROM runs"))(
    lambda s, d: run52.runs(pruned_of(s, d, "events", P), ["domain"], ["level", "path"], "refined")
)


def _sizes_sql(m, source="pruned", marked=False):
    extra = " + max(level) - min(level)" if marked else ""
    parts = sql.pruned(m, domains_of(m), P)
    out = []
    for bit in ("refined", "masked"):
        parts = parts + sql.run_table(source, bit, level="level" if marked else None, name=f"r_{bit}")
        out.append(f"SELECT '{m}' AS mesh, '{bit}' AS stream, domain, (1 + sum({sql.run_bytes()}){extra})::BIGINT AS code_bytes, sum(len)::BIGINT AS n_bits FROM r_{bit} GROUP BY domain")
    return parts, out


def _stream_sizes(after, m, marked=False):
    out = []
    for bit in ("refined", "masked"):
        found = run52.runs(after, ["domain"], ["level", "path"], bit, "level" if marked else None)
        out.append(run52.encoded_bytes(found, ["domain"], marked).select(F.lit(m).alias("mesh"), F.lit(bit).alias("stream"), "domain", "code_bytes", "n_bits"))
    return _all(out)


_parts, _outs = _sizes_sql("line")
query("op_run52_bytes", sql.with_(_parts, " UNION ALL ".join(_outs)))(lambda s, d: _stream_sizes(pruned_of(s, d, "line", P), "line"))
_parts, _outs = _sizes_sql("line", marked=True)
query("op_run52_marked", sql.with_(_parts, " UNION ALL ".join(_outs)))(lambda s, d: _stream_sizes(pruned_of(s, d, "line", P), "line", True))

_BIT_RUNS = sql.pruned("events", 16, P) + sql.run_table("pruned", "masked")


@query("op_run52_decode", sql.with_(sql.pruned("events", 16, P), "SELECT domain, count(*) AS n, string_agg(masked::INTEGER::VARCHAR, '' ORDER BY level, path) AS bits FROM pruned GROUP BY 1"))
def _(spark, sf_dir):
    codes = run52.encode(pruned_of(spark, sf_dir, "events", P), ["domain"], ["level", "path"], "masked", "level")
    found = run52.runs_of_code(codes, ["domain"])
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("run_no", "bit", "len"))), lambda r: F.repeat(r["bit"].cast("int").cast("string"), r["len"].cast("int"))), "")
    return found.groupBy("domain").agg(F.sum("len").alias("n"), text.alias("bits"))


def _hex_sql(bit, marked):
    digit = "lpad(hex(((len // (52::BIGINT ** j)::BIGINT) % 52 + 11)::BIGINT), 2, '0')"
    n = sql.digits()
    run = f"CASE WHEN {n} > 1 THEN lpad(hex({n}::BIGINT), 2, '0') ELSE '' END || list_reduce(list_transform(list_reverse(range({n})), lambda j: {digit}), lambda a, b: a || b)"
    parts = sql.pruned("events", 16, P) + sql.run_table("pruned", bit, level="level" if marked else None)
    mark = "CASE WHEN lag(level) OVER w <> level THEN CASE WHEN lag(bit) OVER w <> bit THEN '09' ELSE '0A' END ELSE '' END || " if marked else ""
    parts.append(("hexed", f"SELECT domain, run_no, CASE WHEN run_no = 0 THEN CASE WHEN bit THEN '01' ELSE '00' END ELSE '' END || {mark}{run} AS h FROM runs WINDOW w AS (PARTITION BY domain ORDER BY run_no)"))
    return sql.with_(parts, "SELECT domain, string_agg(h, '' ORDER BY run_no) AS code FROM hexed GROUP BY 1")


for _label, _bit, _marked in (("grid", "refined", True), ("mask", "masked", False)):
    query(f"op_run52_encode_{_label}", _hex_sql(_bit, _marked))(
        lambda s, d, b=_bit, m=_marked: run52.encode(pruned_of(s, d, "events", P), ["domain"], ["level", "path"], b, "level" if m else None).select("domain", F.hex("code").alias("code"))
    )

_OFFSETS = "SELECT domain, (count(*) * k // 7)::BIGINT AS o FROM pruned, (SELECT unnest(range(7)) AS k) GROUP BY domain, k"


@query("op_bit_at", sql.with_(sql.pruned("line", 16, P) + [("offs", _OFFSETS), ("placed", "SELECT domain, masked, row_number() OVER (PARTITION BY domain ORDER BY level, path) - 1 AS o FROM pruned")], 'SELECT domain, o AS "offset", masked AS bit FROM placed JOIN (SELECT DISTINCT * FROM offs) USING (domain, o)'))
def _(spark, sf_dir):
    after = pruned_of(spark, sf_dir, "line", P)
    offsets = after.groupBy("domain").agg(F.count("*").alias("n")).withColumn("k", F.explode(F.array(*map(F.lit, range(7))))).select("domain", F.expr("n * k div 7").alias("offset")).distinct()
    codes = run52.encode(after, ["domain"], ["level", "path"], "masked", "level")
    return run52.bits_at(run52.runs_of_code(codes, ["domain"]), offsets, ["domain"])


@query("w_bit_at", sql.with_(sql.pruned("line", 16, P) + [("offs", _OFFSETS), ("placed", "SELECT domain, masked, row_number() OVER (PARTITION BY domain ORDER BY level, path) - 1 AS o FROM pruned")], 'SELECT domain, o AS "offset", masked::INTEGER AS bit FROM placed JOIN (SELECT DISTINCT * FROM offs) USING (domain, o)'))
def _(spark, sf_dir):
    """The same by an Arrow UDF over each stream."""
    after = pruned_of(spark, sf_dir, "line", P)
    codes = run52.encode(after, ["domain"], ["level", "path"], "masked")
    n = after.groupBy("domain").agg(F.count("*").alias("n"))
    offsets = n.withColumn("k", F.explode(F.array(*map(F.lit, range(7))))).select("domain", F.expr("n * k div 7").alias("offset")).distinct()
    return codes.join(offsets, "domain").select("domain", "offset", run52.bit_at_udf("code", "offset").alias("bit"))


@query("op_varint_bytes", sql.with_(_BIT_RUNS, "SELECT domain, (1 + sum(1 + (len >= 128)::INTEGER + (len >= 16384)::INTEGER + (len >= 2097152)::INTEGER + (len >= 268435456)::INTEGER))::BIGINT AS code_bytes FROM runs GROUP BY 1"))
def _(spark, sf_dir):
    packed = layout.to_arrays(pruned_of(spark, sf_dir, "events", P), 3)
    return baselines.codec_report(packed, "masked", [("varint", None, None)]).select("domain", F.col("enc_bytes").alias("code_bytes"))


_RUN_EXAMPLE = [(1, "0C"), (51, "3E"), (52, "020C0B"), (2703, "023E3E"), (2704, "030C0B0B"), (2904, "030C0E37"), (52**7 - 1, "07" + "3E" * 7)]


_CENTS = "round(o_totalprice * 100)::BIGINT"


def _run_hex_sql(n):
    byte = lambda e: f"format('{{:02X}}', ({e})::BIGINT)"
    each = " || ".join(f"CASE WHEN {sql.digits(n)} > {j} THEN {byte(f'({n} // {52**j}) % 52 + 11')} ELSE '' END" for j in reversed(range(7)))
    return f"CASE WHEN {sql.digits(n)} > 1 THEN {byte(sql.digits(n))} ELSE '' END || {each}"


@query("w_run52_example", f"SELECT o_orderkey, {_run_hex_sql('o_orderkey')} AS key_code, {_run_hex_sql(_CENTS)} AS cents_code FROM orders")
def _(spark, sf_dir):
    """Codes of the numbers of a table, each as the length of a run."""
    cents = F.round(F.col("o_totalprice") * 100).cast("long")
    return table(spark, sf_dir, "orders").select("o_orderkey", run52.run_hex(F.col("o_orderkey")).alias("key_code"), run52.run_hex(cents).alias("cents_code"))


_FLAGS = {"quality": ("labels", "quality = 1", "doc_id"), "toxic": ("labels", "toxic = 1", "doc_id"), "returned": ("lineitem", "l_returnflag = 'R'", "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_returnflag")}


def _flags_sql(k):
    name, test, order = _FLAGS[k]
    src = [("src", f"SELECT 0 AS g, ({test}) AS bit, {order} FROM {name}")]
    return f"{sql.with_(src + sql.run_table('src', 'bit', by='g', order=order), f'''SELECT '{k}' AS flags, sum(len)::BIGINT AS n_bits, count(*) AS n_runs, (1 + sum({sql.run_bytes()}))::BIGINT AS code_bytes FROM runs''')}"


@query("w_run52_labels", _union(_flags_sql(k) for k in _FLAGS))
def _(spark, sf_dir):
    """Runs of boolean columns that are no mesh: cut by a global order without gathering the rows.

    Rows are range-partitioned by the order; each partition sums its runs, and only runs at the
    edges of partitions are joined up.
    """
    out = []
    for k, (name, test, order) in _FLAGS.items():
        found = runs_in_order(table(spark, sf_dir, name), F.expr(test), order.split(", "))
        out.append(found.agg(F.sum("len").alias("n_bits"), F.count("*").alias("n_runs"), (1 + F.sum(run52.run_bytes(F.col("len")))).cast("long").alias("code_bytes")).select(F.lit(k).alias("flags"), "*"))
    return _all(out)


def runs_in_order(df, bit, order: list[str]):
    """(bit, len) of the runs of ``bit`` over all rows in order."""
    parts = cut(df.select(bit.alias("bit"), *order).repartitionByRange(*order).sortWithinPartitions(*order).select("bit", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at")))
    own = run52.runs(parts, ["part"], ["at"], "bit")
    first = Window.partitionBy("part")
    marked = own.withColumns({"lo": F.min("run_no").over(first) == F.col("run_no"), "hi": F.max("run_no").over(first) == F.col("run_no")})
    inner = marked.where("not lo and not hi").select("bit", "len")
    edges = marked.where("lo or hi").select(F.lit(0).alias("g"), "part", "run_no", "bit", "len")  # two rows a partition at most
    w = Window.partitionBy("g").orderBy("part", "run_no")
    new = (F.lag("bit").over(w).isNull() | (F.lag("bit").over(w) != F.col("bit"))) | ((F.lag("part").over(w) == F.col("part")) & F.lit(True))
    joined = edges.withColumn("fresh", new.cast("int")).withColumn("r", F.sum("fresh").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return inner.unionByName(joined.groupBy("r").agg(F.first("bit").alias("bit"), F.sum("len").alias("len")).drop("r"))


# ---- sizes of boolean arrays -------------------------------------------------------------------


def _bool_summary(m):
    parts, outs = _sizes_sql(m)
    return f"{sql.with_(parts, 'SELECT mesh, stream, sum(n_bits)::BIGINT AS raw_bytes, sum(code_bytes)::BIGINT AS enc_bytes, sum(n_bits)::BIGINT::DOUBLE / sum(code_bytes)::BIGINT::DOUBLE AS ratio, sum((n_bits + 7) // 8)::BIGINT::DOUBLE / sum(code_bytes)::BIGINT::DOUBLE AS bit_ratio FROM (' + ' UNION ALL '.join(outs) + ') GROUP BY 1, 2')}"


def _summed_sizes(spark, sf_dir, m):
    per = _stream_sizes(pruned_of(spark, sf_dir, m, P), m)
    return per.groupBy("mesh", "stream").agg(
        F.sum("n_bits").alias("raw_bytes"), F.sum("code_bytes").alias("enc_bytes"), (_d(F.sum("n_bits")) / _d(F.sum("code_bytes"))).alias("ratio"),
        (_d(F.sum(F.expr("(n_bits + 7) div 8"))) / _d(F.sum("code_bytes"))).alias("bit_ratio"),
    )


query("w_run52_sizes", _union(_bool_summary(m) for m in SNAPSHOTS))(lambda s, d: _all([_summed_sizes(s, d, m) for m in SNAPSHOTS]))


@query("w_bool_codecs")
def _(spark, sf_dir):
    """Sizes of both arrays under every boolean codec; speeds are in ``w_speeds``."""
    packed = cut(layout.to_arrays(pruned_of(spark, sf_dir, "line", P), 3))
    return _all([baselines.codec_report(packed, a, baselines.BOOL_CODECS) for a in ("refined", "masked")]).groupBy("array", "codec").agg(
        F.sum("raw_bytes").alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes"), (F.sum("raw_bytes") / F.sum("enc_bytes")).alias("ratio"), F.bool_and("exact").alias("exact")
    )


_GRID = lambda d: f"(4 * ({2 * d} + 1 + 2 + {3 * (1 << d)}) + {8 * d})"


def _chain_sql(m):
    d = MESHES[m].dim
    parts, outs = _sizes_sql(m, marked=True)
    return f"""{sql.with_(parts, f'''SELECT '{m}' AS mesh, (SELECT count(*) FROM local WHERE refined) * {_GRID(d)} AS legacy_bytes, (SELECT sum(code_bytes)::BIGINT FROM ({' UNION ALL '.join(outs)})) AS grid_bytes,
    ((SELECT count(*) FROM local WHERE refined) * {_GRID(d)})::DOUBLE / (SELECT sum(code_bytes)::BIGINT FROM ({' UNION ALL '.join(outs)}))::DOUBLE AS ratio''')}"""


@query("w_chain", _union(_chain_sql(m) for m in SNAPSHOTS))
def _(spark, sf_dir):
    out = []
    for m in SNAPSHOTS:
        d = MESHES[m].dim
        local = local_of(spark, sf_dir, m, P)
        code = _stream_sizes(cut(prune.prune(local, d)), m, True).agg(F.sum("code_bytes").alias("grid_bytes"))
        old = local.agg(baselines.legacy_grid_bytes(d, F.count_if("refined")).alias("legacy_bytes"))
        both = old.withColumn("k", F.lit(1)).join(code.withColumn("k", F.lit(1)), "k")
        out.append(both.select(F.lit(m).alias("mesh"), "legacy_bytes", "grid_bytes", (_d(F.col("legacy_bytes")) / _d(F.col("grid_bytes"))).alias("ratio")))
    return _all(out)




_TIGHT = "SELECT domain, (1 + sum({b}))::BIGINT AS code, (1 + sum(length(bin(len))))::BIGINT AS exact FROM runs GROUP BY 1"


def _headroom_sql(bit):
    digits = f"SELECT {sql.digits()} AS n, len FROM runs"
    each = "SELECT n AS b FROM dg WHERE n > 1 UNION ALL SELECT ((len // (52::BIGINT ** j)::BIGINT) % 52 + 11)::BIGINT FROM dg, (SELECT unnest(range(7)) AS j) WHERE j < n UNION ALL SELECT any_value(CASE WHEN bit THEN 1 ELSE 0 END) FROM runs WHERE run_no = 0 GROUP BY domain"
    parts = sql.pruned("line", 16, P) + sql.run_table("pruned", bit) + [("dg", digits), ("byt", each), ("h", "SELECT b, count(*) AS c FROM byt GROUP BY 1"), ("t", _TIGHT.format(b=sql.run_bytes()))]
    entropy = "(SELECT round(-sum(c::DOUBLE / (SELECT sum(c) FROM h)::DOUBLE * log2(c::DOUBLE / (SELECT sum(c) FROM h)::DOUBLE)), 9) FROM h)"
    six, exact, code = "sum((6 * code + 7) // 8)::BIGINT", "sum((exact + 7) // 8)::BIGINT", "sum(code)::BIGINT"
    return sql.with_(parts, f"SELECT '{bit}' AS stream, (SELECT sum(c) FROM h)::BIGINT AS code_bytes, {entropy} AS entropy, {six} AS six_bit_bytes, {exact} AS exact_bytes, 1 - {six}::DOUBLE / {code}::DOUBLE AS six_bit_saving, 1 - {exact}::DOUBLE / {code}::DOUBLE AS exact_saving FROM t")


@query("w_run52_headroom", _union(_headroom_sql(bit) for bit in ("refined", "masked")))
def _(spark, sf_dir):
    """What tighter streams would save: words of six bits, and the bits of the run lengths alone."""
    after = pruned_of(spark, sf_dir, "line", P)
    out = []
    for bit in ("refined", "masked"):
        codes = run52.encode(after, ["domain"], ["level", "path"], bit)
        each = codes.select(F.explode(F.regexp_extract_all(F.hex("code"), F.lit("(..)"), F.lit(1))).alias("byte"))
        hist = cut(each.groupBy("byte").agg(F.count("*").alias("n")))
        tight = run52.tight_bytes(run52.runs(after, ["domain"], ["level", "path"], bit), ["domain"])
        saved = lambda c: (1 - _d(F.sum(c)) / _d(F.sum("code_bytes")))
        sums = tight.agg(F.sum("code_bytes").alias("code_bytes"), F.sum("six_bit_bytes").alias("six_bit_bytes"), F.sum("exact_bytes").alias("exact_bytes"), saved("six_bit_bytes").alias("six_bit_saving"), saved("exact_bytes").alias("exact_saving"))
        e = measures.entropy(hist).withColumn("k", F.lit(1)).join(sums.withColumn("k", F.lit(1)), "k")
        out.append(e.drop("k").select(F.lit(bit).alias("stream"), "*"))
    return _all(out)


# ---- float views -------------------------------------------------------------------------------

query("op_f64_bits", "SELECT c_custkey, c_acctbal, c_acctbal::DOUBLE::BIT::BIGINT AS b FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", "c_acctbal", bits.f64_bits(F.col("c_acctbal")).alias("b")))
query("op_f32_bits", "SELECT c_custkey, (c_acctbal::FLOAT::BIT::INTEGER)::BIGINT & 4294967295 AS b FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", bits.f32_bits(F.col("c_acctbal")).alias("b")))
query("op_f64_view", "SELECT c_custkey, c_acctbal::DOUBLE::BIT::BIGINT AS b FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", bits.f64_view("c_acctbal").alias("b")))
query("op_f64_from_bits", "SELECT c_custkey, c_acctbal AS v FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", bits.f64_from_bits(bits.f64_view("c_acctbal")).alias("v")))
query("op_clz", f"SELECT c_custkey, {sql.lead('(c_acctbal::DOUBLE::BIT::BIGINT)')} AS lead FROM customer")(lambda s, d: table(s, d, "customer").select("c_custkey", bits.leading_zeros(bits.f64_view("c_acctbal")).cast("long").alias("lead")))


# ---- parent XOR --------------------------------------------------------------------------------

_RES = sql.pruned("line", 16, P) + sql.packs("pruned", 3, "p")
query("op_parent_predict", sql.with_(_RES, "SELECT domain, level, path, parent, value, pred FROM res"))(lambda s, d: pxor.predict(pruned_of(s, d, "line", P), 3, "p").select("domain", "level", "path", "parent", "value", "pred"))
query("op_xor_residual", sql.with_(_RES, "SELECT domain, level, path, s FROM res"))(lambda s, d: pxor.residuals(pxor.predict(pruned_of(s, d, "line", P), 3, "p")).select("domain", "level", "path", "s"))
_stats = lambda s, d, m="line", f="p", **k: pxor.pack_stats(pxor.residuals(pxor.predict(pruned_of(s, d, m, P), MESHES[m].dim, f, **k)))
query("op_pack_or", sql.with_(_RES, "SELECT domain, level, parent, or_bits FROM packs"))(lambda s, d: _stats(s, d).select("domain", "level", "parent", "or_bits"))
query("op_nlz", sql.with_(_RES, "SELECT domain, level, parent, least(lead, 15)::BIGINT AS nlz FROM packs"))(lambda s, d: _stats(s, d).select("domain", "level", "parent", F.least("lead", F.lit(15)).cast("long").alias("nlz")))


def _bits_of_pruned(m, f, k=4, dtype="float64", lead_cols="", pred="u.{f}", value="c.{f}"):
    """Sizes by domain from a ``pruned`` that is known around this text."""
    d, w = MESHES[m].dim, 64 if dtype == "float64" else 32
    parts = sql.packs("pruned", d, f, dtype, pred, value)
    parts += [("pb", f"SELECT domain, sum({sql.pack_bits(d, k, w)})::BIGINT AS b FROM packs GROUP BY 1"), ("cc", "SELECT domain, count(*) AS n_cells FROM pruned GROUP BY 1")]
    return sql.with_(parts, f"SELECT {lead_cols}domain, n_cells, (coalesce(b, 0) + {w})::BIGINT AS enc_bits, ((coalesce(b, 0) + {w} + 7) // 8)::BIGINT AS enc_bytes FROM cc LEFT JOIN pb USING (domain)")


def _bits_sql(m, f, *rest, **named):
    return sql.with_(sql.pruned(m, domains_of(m), P), f"SELECT * FROM ({_bits_of_pruned(m, f, *rest, **named)})")


query("op_pxor_bits", _bits_sql("line", "p"))(lambda s, d: pxor.sizes(pruned_of(s, d, "line", P), 3, "p"))
query("op_pxor_bits_2d", _bits_sql("cust", "v"))(lambda s, d: pxor.sizes(pruned_of(s, d, "cust", P), 2, "v"))
query("op_pxor_bits_f32", _bits_sql("line", "p", dtype="float32"))(lambda s, d: pxor.sizes(pruned_of(s, d, "line", P), 3, "p", dtype="float32"))
query("op_pxor_extensive", _bits_sql("events", "rho", pred="u.{f} / 8.0"))(lambda s, d: pxor.sizes(pruned_of(s, d, "events", P), 3, "rho", how="parent_share"))
query("op_pxor_k", _union(_bits_sql("events", "p", k, lead_cols=f"{k}::INTEGER AS k, ") for k in (3, 5, 6)))(lambda s, d: (lambda a: _all([pxor.sizes(a, 3, "p", k).select(F.lit(k).alias("k"), "*") for k in (3, 5, 6)]))(pruned_of(s, d, "events", P)))


@query("op_pxor_shift", _bits_sql("cust", "v", pred="(u.{f} + 65536.0)", value="(c.{f} + 65536.0)"))
def _(spark, sf_dir):
    after = pruned_of(spark, sf_dir, "cust", P)
    return pxor.sizes(after.withColumn("v", F.col("v") + 65536.0), 2, "v")


@query("op_pxor_previous", sql.with_(sql.pruned("events", 16, P) + [("pr", "SELECT domain, level, path, p AS value, lag(p) OVER (PARTITION BY domain ORDER BY level, path) AS pred FROM pruned")], f"SELECT domain, count(*) AS n, sum(64 - least(15, {sql.lead('xor(value::BIT::BIGINT, pred::BIT::BIGINT)')}))::BIGINT AS residue_bits FROM pr WHERE pred IS NOT NULL GROUP BY 1"))
def _(spark, sf_dir):
    res = pxor.cell_leads(pxor.residuals(pxor.previous(pruned_of(spark, sf_dir, "events", P), "p").where("pred is not null")))
    return res.groupBy("domain").agg(F.count("*").alias("n"), F.sum(64 - F.least("lead", F.lit(15))).cast("long").alias("residue_bits"))


def _ratio_sql(m, dtype):
    w = 8 if dtype == "float64" else 4
    each = [f"SELECT '{m}' AS mesh, '{f}' AS field, '{dtype}' AS dtype, sum(n_cells)::BIGINT * {w} AS raw_bytes, sum(enc_bytes)::BIGINT AS enc_bytes, (sum(n_cells)::BIGINT * {w})::DOUBLE / sum(enc_bytes)::BIGINT::DOUBLE AS ratio FROM ({_bits_of_pruned(m, f, 4, dtype)})" for f in FIELDS]
    return sql.with_(sql.pruned(m, domains_of(m), P), _union(each))


def _ratios(spark, sf_dir, dtype):
    w, out = (8 if dtype == "float64" else 4), []
    for m in SNAPSHOTS:
        per = pxor.sizes_of(pruned_of(spark, sf_dir, m, P), MESHES[m].dim, {f: f"{f}:{dtype}" for f in FIELDS})
        cells, code = (F.sum("n_cells") * w).alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes")
        out.append(per.groupBy(F.col("name").alias("field")).agg(cells, code, (_d(F.sum("n_cells") * w) / _d(F.sum("enc_bytes"))).alias("ratio")).select(F.lit(m).alias("mesh"), "field", F.lit(dtype).alias("dtype"), "raw_bytes", "enc_bytes", "ratio"))
    return _all(out)


query("w_pxor_f64", _union(_ratio_sql(m, "float64") for m in SNAPSHOTS))(lambda s, d: _ratios(s, d, "float64"))
query("w_pxor_f32", _union(_ratio_sql(m, "float32") for m in SNAPSHOTS))(lambda s, d: _ratios(s, d, "float32"))


@query("w_float_codecs")
def _(spark, sf_dir):
    """Sizes of the density under every float codec; speeds are in ``w_speeds``."""
    packed = cut(layout.to_arrays(pruned_of(spark, sf_dir, "line", P), 3, {"rho": "float64"}))
    return baselines.codec_report(packed, "f_rho", baselines.FLOAT_CODECS, "float64").groupBy("codec").agg(
        F.sum("raw_bytes").alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes"), (F.sum("raw_bytes") / F.sum("enc_bytes")).alias("ratio"), F.bool_and("exact").alias("exact")
    )


#: Speeds are taken on domains of a size that a simulation's have: few of them, not sixteen small ones.
LARGE = with_params(P, domains=2)


def _large(spark, sf_dir, m, fields):
    """Pruned arrays of the two domains of a mesh, stored."""
    return cut(layout.to_arrays(pruned_of(spark, sf_dir, m, LARGE), MESHES[m].dim, fields))


@query("w_speeds")
def _(spark, sf_dir):
    """Single-thread speeds in MB/s of all codecs, both ways, and of the largest domain."""
    packed = _large(spark, sf_dir, "line", {"rho": "float64"})
    reports = [baselines.codec_report(packed, a, baselines.BOOL_CODECS, repeat=3) for a in ("refined", "masked")]
    reports.append(baselines.codec_report(packed, "f_rho", baselines.FLOAT_CODECS, "float64", 3))
    return baselines.summed(_all(reports))


@query("w_speeds_run52")
def _(spark, sf_dir):
    """Ratio and single-thread speed of the run coder on both arrays of the three meshes."""
    out = []
    for m in SNAPSHOTS:
        packed = _large(spark, sf_dir, m, {})
        for a in ("refined", "masked"):
            out.append(baselines.summed(baselines.codec_report(packed, a, baselines.BOOL_CODECS[:1], repeat=5)).select(F.lit(m).alias("mesh"), "*"))
    return _all(out)


@query("w_speeds_pxor")
def _(spark, sf_dir):
    """Ratio and single-thread speed, both ways, of the float coder: three fields of three meshes in both precisions."""
    out = []
    for m in SNAPSHOTS:
        after = pruned_of(spark, sf_dir, m, LARGE)
        for dtype in ("float64", "float32"):
            packed = cut(layout.to_arrays(after, MESHES[m].dim, {f: dtype for f in FIELDS[:3]}))
            for f in FIELDS[:3]:
                report = baselines.codec_report(packed, f"f_{f}", baselines.FLOAT_CODECS[:1], dtype, 5)
                out.append(baselines.summed(report).select(F.lit(m).alias("mesh"), F.lit(dtype).alias("dtype"), "*"))
    return _all(out)


@query("w_speeds_header")
def _(spark, sf_dir):
    """What a header of five bits gains in ratio and costs in speed against one of four, on the density."""
    packed = _large(spark, sf_dir, "line", {"rho": "float64", "smooth": "float64"})
    return _all([baselines.summed(baselines.codec_report(packed, f"f_{f}", [("pxor4", None, None), ("pxor5", None, None)], "float64", 5)) for f in ("rho", "smooth")])


_BACK = {"rho": "float64", "v": "float64", "p": "float32", "smooth": "float32"}


@query("w_pxor_decode", _union(f"{sql.with_(sql.pruned(m, domains_of(m), P), f'''SELECT '{m}' AS mesh, domain, count(*) AS n_cells, 0::BIGINT AS mismatches FROM pruned GROUP BY 2''')}" for m in SNAPSHOTS))
def _(spark, sf_dir):
    return _all([_roundtrip(pruned_of(spark, sf_dir, m, P), m) for m in SNAPSHOTS])


def _roundtrip(after, m):
    """Cells and values that differ in any bit after encoding and decoding all fields."""
    packed = cut(layout.to_arrays(after, MESHES[m].dim, _BACK))
    back = pxor.decode(pxor.encode_arrays(packed, _BACK), packed)
    raw = packed.select("domain", "n_cells", F.explode(F.create_map(*(x for f in _BACK for x in (F.lit(f), F.col(f"f_{f}"))))).alias("field", "raw"))
    return raw.join(back, ["domain", "field"]).groupBy("domain").agg(F.first("n_cells").alias("n_cells"), F.count_if(F.col("raw") != F.col("values")).alias("mismatches")).select(F.lit(m).alias("mesh"), "domain", "n_cells", "mismatches")


query("op_pxor_roundtrip", f"{sql.with_(sql.pruned('cust', 16, P), '''SELECT 'cust' AS mesh, domain, count(*) AS n_cells, 0::BIGINT AS mismatches FROM pruned GROUP BY 2''')}")(lambda s, d: _roundtrip(pruned_of(s, d, "cust", P), "cust"))


@query("w_pxor_decode_levels", sql.with_(sql.pruned("line", 16, P), f"SELECT domain, row_number() OVER (PARTITION BY domain ORDER BY level, path) - 1 AS place, {sql.bits('rho')} AS bits FROM pruned WHERE level <= 3"))
def _(spark, sf_dir):
    """Every value down to level 3, bit by bit, from streams that are read no further."""
    packed = cut(layout.to_arrays(pruned_of(spark, sf_dir, "line", P), 3, {"rho": "float64"}))
    got = pxor.decode(pxor.encode_arrays(packed, {"rho": "float64"}), packed, max_level=3)
    return got.select("domain", F.posexplode(pxor.as_bits("values")).alias("place", "bits")).select("domain", F.col("place").cast("long").alias("place"), "bits")


# ---- leading zeros -----------------------------------------------------------------------------

_RHO = sql.pruned("line", 16, P) + sql.packs("pruned", 3, "rho") + [("cl", f"SELECT {sql.lead('s')} AS lead FROM res")]
_PMF = "SELECT lead::BIGINT AS lead, count(*) AS n, count(*)::DOUBLE / (SELECT count(*) FROM {t})::DOUBLE AS share FROM {t} GROUP BY 1"


def _leads(spark, sf_dir):
    res = pxor.residuals(pxor.predict(pruned_of(spark, sf_dir, "line", P), 3, "rho"))
    return pxor.pack_stats(res).select("lead"), pxor.cell_leads(res).select("lead")


query("w_nlz_pack", sql.with_(_RHO, _PMF.format(t="packs")))(lambda s, d: measures.pmf(_leads(s, d)[0]).withColumn("lead", F.col("lead").cast("long")))
query("w_nlz_cell", sql.with_(_RHO, _PMF.format(t="cl")))(lambda s, d: measures.pmf(_leads(s, d)[1]).withColumn("lead", F.col("lead").cast("long")))


def _summary_sql(basis):
    t, per = ("packs", 8) if basis == "pack" else ("cl", 1)
    h = f"(SELECT lead, count(*) AS c FROM {t} GROUP BY 1)"
    header = "4.0" if basis == "pack" else f"(SELECT round(-sum(c::DOUBLE / t * log2(c::DOUBLE / t)), 9) FROM {h}, (SELECT count(*)::DOUBLE AS t FROM {t}))"
    return f"""SELECT '{basis}' AS basis, (SELECT round(-sum(c::DOUBLE / t * log2(c::DOUBLE / t)), 9) FROM {h}, (SELECT count(*)::DOUBLE AS t FROM {t})) AS entropy,
    round((64 * {per} * count(*))::DOUBLE / sum({per} * (64 - lead))::DOUBLE, 9) AS bare_ratio, round((64 * {per} * count(*))::DOUBLE / (sum({per} * (64 - lead))::DOUBLE + {header} * count(*)), 9) AS ratio FROM {t}"""


@query("w_nlz_summary", sql.with_(_RHO, _summary_sql("pack") + " UNION ALL " + _summary_sql("cell")))
def _(spark, sf_dir):
    out = []
    for basis, per, leads in zip(("pack", "cell"), (8, 1), _leads(spark, sf_dir)):
        hist = cut(leads.groupBy("lead").agg(F.count("*").alias("n")))
        e = measures.entropy(hist).first()["entropy"] or 0.0  # one number
        header = 4.0 if basis == "pack" else e
        left = _d(F.sum(F.col("n") * per * (64 - F.col("lead"))))
        whole = _d(F.sum("n") * 64 * per)
        out.append(hist.agg(F.lit(basis).alias("basis"), F.lit(e).alias("entropy"), F.round(whole / left, 9).alias("bare_ratio"), F.round(whole / (left + header * F.sum("n")), 9).alias("ratio")))
    return _all(out)


@query("w_header_sweep", sql.with_(_RHO, " UNION ALL ".join(f"SELECT {k}::INTEGER AS k, sum({sql.pack_bits(3, k)})::BIGINT AS pack_bits, (64 * 8 * count(*))::DOUBLE / sum({sql.pack_bits(3, k)})::BIGINT::DOUBLE AS ratio FROM packs" for k in range(7))))
def _(spark, sf_dir):
    packs = cut(_leads(spark, sf_dir)[0])
    each = packs.select(F.explode(F.array(*(F.struct(F.lit(k).alias("k"), pxor.pack_bits(F.col("lead"), 3, k, 64).alias("b")) for k in range(7)))).alias("x")).select("x.*")
    return each.groupBy("k").agg(F.sum("b").alias("pack_bits"), (_d(F.count("*") * 512) / _d(F.sum("b"))).alias("ratio"))


def _clash_sql(m, f, shift):
    parts = sql.pruned(m, domains_of(m), P) + sql.packs("pruned", MESHES[m].dim, f, pred=f"(u.{{f}} + {shift})", value=f"(c.{{f}} + {shift})")
    parts.append(("byp", "SELECT domain, level, parent, bool_or(sign(value) * sign(pred) < 0) AS clash FROM res GROUP BY 1, 2, 3"))
    return sql.with_(parts, f"SELECT '{m}' AS mesh, {shift}::DOUBLE AS shift, (SELECT count(*) FROM byp) AS packs, (SELECT count(*) FROM byp WHERE clash) AS clashes, sum({sql.pack_bits(MESHES[m].dim, 4)})::BIGINT AS pack_bits, (SELECT count(*) FROM res WHERE value - {shift} <> (SELECT 0.0) + (value - {shift})) AS inexact FROM packs")


def _clashes(spark, sf_dir, shifts):
    out = []
    for m in ("cust", "events"):
        after = pruned_of(spark, sf_dir, m, P)
        for shift in shifts:
            res = pxor.residuals(pxor.predict(after.withColumn("v", F.col("v") + shift), MESHES[m].dim, "v"))
            packs = res.groupBy("domain", "level", "parent").agg(F.bit_or("s").alias("or_bits"), F.bool_or(F.signum("value") * F.signum("pred") < 0).alias("clash"))
            lead = bits.leading_zeros(F.col("or_bits"))
            out.append(packs.agg(F.count("*").alias("packs"), F.count_if("clash").alias("clashes"), F.sum(pxor.pack_bits(lead, MESHES[m].dim, 4, 64)).alias("pack_bits")).select(F.lit(m).alias("mesh"), F.lit(float(shift)).alias("shift"), "*"))
    return _all(out)


def _no_inexact(t):
    return f"SELECT * EXCLUDE (inexact) FROM ({t})"


query("w_sign_clash", _union(_no_inexact(_clash_sql(m, "v", 0.0)) for m in ("cust", "events")))(lambda s, d: _clashes(s, d, [0.0]))
query("w_shift", _union(_no_inexact(_clash_sql(m, "v", k)) for m in ("cust", "events") for k in (0.0, 1024.0, 65536.0)))(lambda s, d: _clashes(s, d, [0.0, 1024.0, 65536.0]))


@query("w_shift_exact", _union(f"{sql.with_(sql.pruned(m, domains_of(m), P), f'''SELECT '{m}' AS mesh, count(*) AS cells, count(*) FILTER ((v + 65536.0) - 65536.0 <> v) AS inexact FROM pruned''')}" for m in ("cust", "events")))
def _(spark, sf_dir):
    """How often a constant shift of floats can't be undone exactly."""
    out = [pruned_of(spark, sf_dir, m, P).agg(F.count("*").alias("cells"), F.count_if((F.col("v") + 65536.0) - 65536.0 != F.col("v")).alias("inexact")).select(F.lit(m).alias("mesh"), "*") for m in ("cust", "events")]
    return _all(out)


_ROUGH = [(m, f) for m in ("events", "line") for f in ("rho", "smooth")]


@query("w_rough_vs_smooth", _union(f"{sql.with_(sql.pruned(m, 16, P) + sql.packs('pruned', 3, f), f'''SELECT '{m}' AS mesh, '{f}' AS field, (512 * (SELECT count(*) FROM packs))::DOUBLE / (SELECT sum({sql.pack_bits(3, 4)})::BIGINT FROM packs)::DOUBLE AS ratio, count(*) FILTER (value >= pred / 2 AND value <= pred * 2)::DOUBLE / count(*)::DOUBLE AS within_two, count(*) FILTER ({sql.lead('s')} >= 12)::DOUBLE / count(*)::DOUBLE AS same_exponent FROM res''')}" for m, f in _ROUGH))
def _(spark, sf_dir):
    out = []
    for m, f in _ROUGH:
        res = cut(pxor.cell_leads(pxor.residuals(pxor.predict(pruned_of(spark, sf_dir, m, P), 3, f))))
        near = (F.col("value") >= F.col("pred") / 2) & (F.col("value") <= F.col("pred") * 2)
        cells = res.agg((_d(F.count_if(near)) / _d(F.count("*"))).alias("within_two"), (_d(F.count_if(F.col("lead") >= 12)) / _d(F.count("*"))).alias("same_exponent")).withColumn("k", F.lit(1))
        packs = pxor.pack_stats(res).agg((_d(F.count("*") * 512) / _d(F.sum(pxor.pack_bits(F.col("lead"), 3, 4, 64)))).alias("ratio")).withColumn("k", F.lit(1))
        out.append(packs.join(cells, "k").select(F.lit(m).alias("mesh"), F.lit(f).alias("field"), "ratio", "within_two", "same_exponent"))
    return _all(out)


# ---- volumes -----------------------------------------------------------------------------------


def _recap_sql(m):
    d = MESHES[m].dim
    parts, outs = _sizes_sql(m, marked=True)
    sums = [(f"{f}_{t}", f"SELECT sum(enc_bytes)::BIGINT AS b FROM ({_bits_of_pruned(m, f, dtype=t)})") for f in ("rho", "v", "p") for t in ("float64", "float32")]
    of = lambda t: " + ".join(f"(SELECT b FROM {f}_{t})" for f in ("rho", "v", "p"))
    one = f"""SELECT (SELECT count(*) FROM local) AS cells_before, (SELECT count(*) FROM pruned) AS cells_after, (SELECT count(*) FROM local WHERE refined) * {_GRID(d)} AS grid_before,
    (SELECT sum(code_bytes)::BIGINT FROM ({' UNION ALL '.join(outs)})) AS grid_after, (SELECT count(*) FROM local) * 24 AS f64_before, {of('float64')} AS f64_after, {of('float32')} AS f32_after"""
    cut_to = lambda t: f"1 - (grid_after + {t}_after)::DOUBLE / (grid_before + f64_before)::DOUBLE"
    return sql.with_(
        parts + sums + [("one", one)],
        f"SELECT '{m}' AS mesh, *, {cut_to('f64')} AS reduction_f64, {cut_to('f32')} AS reduction_f32, grid_after::DOUBLE / (grid_after + f64_after)::DOUBLE AS grid_share, floor(1 / (1 - ({cut_to('f32')})))::BIGINT AS dump_factor FROM one",
    )


def _recap(spark, sf_dir, m):
    d = MESHES[m].dim
    local = local_of(spark, sf_dir, m, P)
    after = cut(prune.prune(local, d))
    one = [
        local.agg(F.count("*").alias("cells_before"), baselines.legacy_grid_bytes(d, F.count_if("refined")).alias("grid_before"), (F.count("*") * 24).alias("f64_before")),
        after.agg(F.count("*").alias("cells_after")),
        _stream_sizes(after, m, True).agg(F.sum("code_bytes").alias("grid_after")),
        pxor.sizes_of(after, d, {f"{f}_{s}": f"{f}:{t}" for f in ("rho", "v", "p") for t, s in (("float64", "f64"), ("float32", "f32"))})
        .agg(*(F.sum(F.when(F.col("name").endswith(s), F.col("enc_bytes"))).alias(f"{s}_after") for s in ("f64", "f32"))),
    ]
    row = reduce(lambda a, b: a.join(b, "k"), [x.withColumn("k", F.lit(1)) for x in one])
    cut_to = lambda s: 1 - _d(F.col("grid_after") + F.col(f"{s}_after")) / _d(F.col("grid_before") + F.col("f64_before"))
    return row.select(F.lit(m).alias("mesh"), "cells_before", "cells_after", "grid_before", "grid_after", "f64_before", "f64_after", "f32_after", cut_to("f64").alias("reduction_f64"), cut_to("f32").alias("reduction_f32"), (_d(F.col("grid_after")) / _d(F.col("grid_after") + F.col("f64_after"))).alias("grid_share"), F.floor(1 / (1 - cut_to("f32"))).alias("dump_factor"))


@query("w_recap", _union(_recap_sql(m) for m in SNAPSHOTS))
def _(spark, sf_dir):
    return _all([_recap(spark, sf_dir, m) for m in SNAPSHOTS])


_PLANE = ("orders", "cust")


@query("w_published_recap", f"SELECT mesh AS snapshot, 100 * (1 - cells_after::DOUBLE / cells_before::DOUBLE) AS removed, 100 * reduction_f64 AS cut_f64, 100 * reduction_f32 AS cut_f32, dump_factor, grid_before::DOUBLE / grid_after::DOUBLE AS grid_ratio FROM ({_union(_recap_sql(m) for m in _PLANE)})")
def _(spark, sf_dir):
    got = _all([_recap(spark, sf_dir, m) for m in _PLANE])
    return got.select(
        F.col("mesh").alias("snapshot"), (100 * (1 - _d(F.col("cells_after")) / _d(F.col("cells_before")))).alias("removed"), (100 * F.col("reduction_f64")).alias("cut_f64"),
        (100 * F.col("reduction_f32")).alias("cut_f32"), "dump_factor", (_d(F.col("grid_before")) / _d(F.col("grid_after"))).alias("grid_ratio"),
    )


_CEIL = [(w, d, k) for w in (32, 64) for d in (1, 2, 3) for k in (4, 5)]


def _ceiling_sql(w, d, k):
    b = sql.bits("o_totalprice", "float64" if w == 64 else "float32")
    coded = lambda cut_: f"((({w} - {cut_}) * c + {k})::BIGINT)"
    most = lambda cut_: f"max(({w} * c)::DOUBLE / {coded(cut_)}::DOUBLE)"
    cap = min((1 << k) - 1, w)
    packs = f"SELECT count(*) AS c, xor(bit_or({b}), bit_and({b})) AS x FROM orders GROUP BY o_orderkey >> {d}"
    return f"""SELECT {w}::INTEGER AS width, {d}::INTEGER AS dim, {k}::INTEGER AS k, count(*) AS packs, sum({w} * c)::BIGINT::DOUBLE / sum({coded(f'least({sql.lead("x", w)}, {cap})')})::BIGINT::DOUBLE AS ratio,
    {most(cap)} AS ceiling, {most(12 if w == 64 else 9)} AS exponent_line FROM ({packs})"""


@query("w_ceiling", _union(_ceiling_sql(*c) for c in _CEIL))
def _(spark, sf_dir):
    """Ceilings of the float coder over packs of 2^d neighbouring rows of a table, beside the ratio that they reach.

    Bits that differ between any two values of a pack are those of its OR that its AND lacks.
    """
    rows_ = table(spark, sf_dir, "orders").select("o_orderkey", bits.f64_bits(F.col("o_totalprice")).alias("b64"), bits.f32_bits(F.col("o_totalprice")).alias("b32"))
    out = []
    for d in (1, 2, 3):
        packs = rows_.groupBy(shr("o_orderkey", d).alias("pack")).agg(F.count("*").alias("c"), *(F.bit_or(f"b{w}").bitwiseXOR(F.bit_and(f"b{w}")).alias(f"x{w}") for w in (32, 64)))
        wanted = [(w, k) for w, dim, k in _CEIL if dim == d]
        sums = [F.count("*").alias("packs")]
        for w, k in wanted:
            c, cap = F.col("c"), min((1 << k) - 1, w)
            coded = lambda gone, w=w, k=k, c=c: (F.lit(w) - gone) * c + k
            most = lambda gone, w=w, c=c, coded=coded: F.max(_d(c * w) / _d(coded(F.lit(gone))))
            ratio = _d(F.sum(c * w)) / _d(F.sum(coded(F.least(bits.leading_zeros(F.col(f"x{w}"), w), F.lit(cap)))))
            sums.append(F.struct(F.lit(w).alias("width"), F.lit(d).alias("dim"), F.lit(k).alias("k"), ratio.alias("ratio"), most(cap).alias("ceiling"), most(12 if w == 64 else 9).alias("exponent_line")).alias(f"w{w}k{k}"))
        one = packs.agg(*sums)
        out.append(one.select("packs", F.explode(F.array(*(f"w{w}k{k}" for w, k in wanted))).alias("s")).select("s.width", "s.dim", "s.k", "packs", "s.ratio", "s.ceiling", "s.exponent_line"))
    return _all(out)


_TEXTS = {"documents": "text", "pages": "html", "conversations": "text", "benchmark": "text"}


def _text_bytes_sql(t, c):
    return f"""SELECT '{t}' AS source, sum(n)::BIGINT AS bytes, round(-sum(n::DOUBLE / tot * log2(n::DOUBLE / tot)), 9) AS entropy FROM
    (SELECT substr(h, (2 * i + 1)::BIGINT, 2) AS b, count(*) AS n FROM (SELECT h, unnest(range(length(h) // 2)) AS i FROM (SELECT hex(encode({c})) AS h FROM {t})) GROUP BY 1),
    (SELECT sum(octet_length(encode({c})))::DOUBLE AS tot FROM {t})"""


_FIELD_BYTES = f"""{sql.with_(sql.mesh('line', P) + [('hx', "SELECT rho::DOUBLE::BIT::BIGINT AS b FROM cells"), ('byt', 'SELECT (b >> (8 * i)) & 255 AS b FROM hx, (SELECT unnest(range(8)) AS i)'), ('h', 'SELECT b, count(*) AS n FROM byt GROUP BY 1')], "SELECT 'field rho' AS source, sum(n)::BIGINT AS bytes, round(-sum(n::DOUBLE / t * log2(n::DOUBLE / t)), 9) AS entropy FROM h, (SELECT count(*)::DOUBLE AS t FROM byt)")}"""


@query("w_byte_entropy", _union([*(_text_bytes_sql(t, c) for t, c in _TEXTS.items()), _FIELD_BYTES]))
def _(spark, sf_dir):
    """Byte entropies of texts beside that of a field of point counts."""
    hists = [(t, measures.byte_histogram(table(spark, sf_dir, t), c)) for t, c in _TEXTS.items()]
    view = mesh.build_mesh(spark, sf_dir, "line", P).select(bits.f64_bits(F.col("rho")).alias("b"))
    hists.append(("field rho", view.select(F.explode(F.array(*(shr(F.col("b"), 8 * i).bitwiseAND(F.lit(255)) for i in range(8)))).alias("byte")).groupBy("byte").agg(F.count("*").alias("n"))))
    out = []
    for name, h in hists:
        h = cut(h)
        e = measures.entropy(h).withColumn("k", F.lit(1)).join(h.agg(F.sum("n").alias("bytes")).withColumn("k", F.lit(1)), "k")
        out.append(e.select(F.lit(name).alias("source"), "bytes", "entropy"))
    return _all(out)


@query("w_subset_export", sql.with_(sql.pruned("line", 16, P), "SELECT count(*) * 24 AS all_f64, count(*) * 16 AS two_f64, count(*) * 8 AS two_f32, count(*) FILTER (rho::FLOAT::DOUBLE = rho) AS exact_f32, (count(*) * 16)::DOUBLE / (count(*) * 8)::DOUBLE AS cast_factor FROM pruned"))
def _(spark, sf_dir):
    """Bytes of packed rows with all fields, with two of them, and with these in single precision, and how many values the cast keeps."""
    after = pruned_of(spark, sf_dir, "line", P)
    three, two = {f: "float64" for f in FIELDS[:3]}, ["rho", "p"]
    packed = cut(layout.to_arrays(after, 3, three))
    size = lambda df: df.agg(F.sum(sum((F.octet_length(c) for c in df.columns if c.startswith("f_")), F.lit(0))).cast("long").alias("n"))
    single = layout.to_arrays(after, 3, {f: "float32" for f in two})
    parts = [size(packed), size(layout.select_fields(packed, two)), size(single), after.agg(F.count_if(F.col("rho").cast("float").cast("double") == F.col("rho")).alias("n"))]
    names = ("all_f64", "two_f64", "two_f32", "exact_f32")
    row = reduce(lambda a, b: a.join(b, "k"), [x.select(F.lit(1).alias("k"), F.col("n").alias(n)) for x, n in zip(parts, names)])
    return row.select(*names, (_d(F.col("two_f64")) / _d(F.col("two_f32"))).alias("cast_factor"))


@query("op_volume_flavours", sql.with_(sql.mesh("events", P), "SELECT 'combined' AS flavour, count(*) FILTER (refined) * 156 + count(*) * 24 AS bytes FROM cells UNION ALL SELECT 'checkpoint', 2 * count(*) + count(*) * 24 FROM cells UNION ALL SELECT 'analysis', 2 * ((count(*) + 7) // 8) + count(*) * 12 FROM cells"))
def _(spark, sf_dir):
    """Byte model of three output flavours: legacy lists for both uses; a checkpoint of plain arrays; an analysis
    base with bits for the tree and single precision."""
    cells = cells_of(spark, sf_dir, "events", P)
    old = baselines.legacy_grid_bytes(3, F.count_if("refined")) + F.count("*") * 24
    plain = 2 * F.count("*") + F.count("*") * 24
    light = 2 * F.expr("(count(*) + 7) div 8") + F.count("*") * 12
    return _all([cells.agg(F.lit(k).alias("flavour"), e.alias("bytes")) for k, e in (("combined", old), ("checkpoint", plain), ("analysis", light))])


_W29 = f"""SELECT (SELECT count(*) FROM (SELECT DISTINCT (x0 + a) * s, (x1 + b) * s FROM lf, (VALUES (0, 0), (1, 0), (0, 1), (1, 1)) AS o(a, b))) AS n_points, (SELECT count(*) FROM lf) AS n_cells,
(SELECT count(*) FROM (SELECT DISTINCT (x0 + a) * s, (x1 + b) * s FROM lf, (VALUES (0, 0), (1, 0), (0, 1), (1, 1)) AS o(a, b))) * 16 + (SELECT count(*) FROM lf) * 41 AS bytes, 1048576::BIGINT // 16 * 8 AS uniform_bytes"""


@query("w_downcast_volumes", sql.with_(sql.mesh("orders", P) + [("lf", f"SELECT {sql.deinterleave('path', 2, 8)[0]} AS x0, {sql.deinterleave('path', 2, 8)[1]} AS x1, 1::BIGINT << (8 - level) AS s FROM cells WHERE NOT refined")], _W29))
def _(spark, sf_dir):
    leaves = cells_of(spark, sf_dir, "orders", P).where("not refined")
    return baselines.unstructured_volume(leaves, 2, 8).withColumn("uniform_bytes", F.lit(8 * (1 << 16)).cast("long"))


@query("op_truncate_mantissa", "SELECT c_custkey, c_acctbal::DOUBLE::BIT::BIGINT & -1048576 AS bits FROM customer")
def _(spark, sf_dir):
    """The lossy option: what is left of each value's bits."""
    v = analysis.truncate_mantissa(F.col("c_acctbal"), 20)
    return table(spark, sf_dir, "customer").select("c_custkey", bits.f64_bits(v).alias("bits"))


#: An odd constant of 64 bits, half of which is used for single precision.
SHIFT = 0x1234_5678_9ABC_DEF1
_MOVED = f"(c_acctbal::DOUBLE::BIT::BIGINT)::HUGEINT + {SHIFT}::HUGEINT"


@query("op_shift_bits", f"SELECT c_custkey, (CASE WHEN m > 9223372036854775807 THEN m - 18446744073709551616::HUGEINT ELSE m END)::BIGINT AS moved, b AS back FROM (SELECT c_custkey, {_MOVED} AS m, c_acctbal::DOUBLE::BIT::BIGINT AS b FROM customer)")
def _(spark, sf_dir):
    """Bits moved on by a constant modulo 2^64, and back."""
    b = bits.f64_bits(F.col("c_acctbal"))
    return table(spark, sf_dir, "customer").select("c_custkey", pxor.shift_bits(b, SHIFT).alias("moved"), pxor.shift_bits(pxor.shift_bits(b, SHIFT), -SHIFT).alias("back"))


@query("op_udf_run52", sql.with_(sql.pruned("events", 16, P), "SELECT domain, count(*) AS n, true AS alike FROM pruned GROUP BY 1"))
def _(spark, sf_dir):
    """Arrow UDFs and the grouped UDF give the relational form's bytes, and decode to the bits."""
    after = pruned_of(spark, sf_dir, "events", P)
    packed = layout.to_arrays(after, 3).select("domain", "n_cells", F.col("refined").alias("raw"))
    one = run52.encode(after, ["domain"], ["level", "path"], "refined")
    agg = layout.with_place(after).groupBy("domain").agg(run52.encode_agg(F.col("place"), F.col("refined")).alias("grouped"))
    two = packed.select("domain", F.col("n_cells").alias("n"), "raw", run52.encode_udf("raw").alias("udf"))
    both = two.join(one, "domain").join(agg, "domain")
    back = run52.decode_udf("udf")
    return both.select("domain", "n", ((F.col("udf") == F.col("code")) & (F.col("grouped") == F.col("code")) & (back == F.col("raw"))).alias("alike"))
