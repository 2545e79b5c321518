"""Reading meshes, particles, snapshots over time, and the operators around the methods."""

from __future__ import annotations

import uuid
from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.curves import morton_encode
from ..operators import analysis, baselines, layout, measures
from ..operators.mesh import Params
from ..operators.storage import cut, shared_dir
from ..plans import pipeline
from ..sources.tables import MESHES, grid_points, points, table
from ..streaming import snapshots
from . import sql
from .base import SNAPSHOTS, cells_of, domains_of, local_of, pruned_of, query

P = Params()
L = P.level_max


# ---- levels of detail, boxes, images -----------------------------------------------------------

_AT4 = "SELECT level, path, n FROM cells WHERE level <= 4 AND (level = 4 OR NOT refined)"
query("op_lod", sql.with_(sql.mesh("events", P), _AT4))(lambda s, d: analysis.at_level(cells_of(s, d, "events", P), 4).select("level", "path", "n"))

_X2 = sql.deinterleave("path", 2, L)
_BOX = " AND ".join(f"{x} * (1::BIGINT << (8 - level)) < {hi} AND ({x} + 1) * (1::BIGINT << (8 - level)) > {lo}" for x, lo, hi in zip(_X2, (40, 100), (90, 140)))
query("op_box_query", sql.with_(sql.mesh("orders", P), f"SELECT level, path, n FROM cells WHERE NOT refined AND {_BOX}"))(
    lambda s, d: analysis.box(cells_of(s, d, "orders", P).where("not refined"), 2, L, [40, 100], [90, 140]).select("level", "path", "n")
)


def _image_sql(m, level, axis):
    dim = MESHES[m].dim
    x = sql.deinterleave("path", dim, L)
    keep = [a for a in range(dim) if a != axis]
    sub = "".join(f", (SELECT unnest(range({1 << level}))::BIGINT AS s{a})" for a in keep)
    ok = " AND ".join(f"s{a} < (1::BIGINT << ({level} - level))" for a in keep)
    at = ", ".join(f"({x[a]} << ({level} - level)) + s{a} AS i{a}" for a in keep)
    return sql.with_(
        sql.mesh(m, P) + [("view_", f"SELECT * FROM cells WHERE level <= {level} AND (level = {level} OR NOT refined)")],
        f"SELECT {', '.join(f'i{a}' for a in keep)}, sum(n)::BIGINT AS weight, count(*) AS cells, max(p) AS peak FROM (SELECT {at}, n, p FROM view_{sub} WHERE {ok}) GROUP BY ALL",
    )


query("op_projection", _image_sql("orders", 5, 0))(lambda s, d: analysis.image(cells_of(s, d, "orders", P), 2, 5, 0, "n", "p"))
query("w_lod_image", _image_sql("events", 4, 2))(lambda s, d: analysis.image(cells_of(s, d, "events", P), 3, 4, 2, "n", "p"))

_UNI = f"SELECT (path << (2 * (6 - level))) | c AS path, {', '.join(f'{x} AS i{a}' for a, x in enumerate(sql.deinterleave('((path << (2 * (6 - level))) | c)', 2, 6)))}, p FROM cells, (SELECT unnest(range(4096))::BIGINT AS c) WHERE level <= 6 AND (level = 6 OR NOT refined) AND c < (1::BIGINT << (2 * (6 - level)))"
query("op_uniform_resample", sql.with_(sql.mesh("orders", P), _UNI))(lambda s, d: baselines.resample(cells_of(s, d, "orders", P), 2, 6, ["p"]))
_CORN = "SELECT level, path, " + ", ".join(f"({x} + ((c >> {a}) & 1)) * (1::BIGINT << (8 - level)) AS x{a}" for a, x in enumerate(_X2)) + " FROM cells, (SELECT unnest(range(4)) AS c) WHERE NOT refined"
query("op_leaf_corners", sql.with_(sql.mesh("orders", P), _CORN))(lambda s, d: baselines.corners(cells_of(s, d, "orders", P).where("not refined"), 2, L))


def _neigh_sql():
    x = _X2
    probes = []
    for a in range(2):
        for side in (-1, 1):
            moved = [f"({x[b]} + {side})" if b == a else x[b] for b in range(2)]
            ok = f"({x[a]} + {side}) >= 0 AND ({x[a]} + {side}) < (1::BIGINT << level)"
            probes.append(f"SELECT level, path, {a}::INTEGER AS axis, {side}::INTEGER AS side, {sql.interleave(moved, L)} AS other FROM cells WHERE {ok}")
    return sql.with_(sql.mesh("orders", P) + [("probes", " UNION ALL ".join(probes))], "SELECT p.* FROM probes p JOIN cells c ON c.level = p.level AND c.path = p.other")


query("op_neighbours", _neigh_sql())(lambda s, d: analysis.face_neighbours(cells_of(s, d, "orders", P), 2))
query("op_centres", sql.with_(sql.mesh("orders", P), "SELECT level, path, " + ", ".join(f"(2 * {x} + 1)::DOUBLE / (1::BIGINT << (level + 1))::DOUBLE AS c{a}" for a, x in enumerate(_X2)) + " FROM cells"))(
    lambda s, d: analysis.centres(cells_of(s, d, "orders", P), 2)
)

# ---- particles ---------------------------------------------------------------------------------

_BIND = "SELECT key, count(*) AS n, any_value(c.level) AS level, any_value(c.path) AS path FROM keyed k JOIN cells c ON NOT c.refined AND c.path = (k.key >> ({d} * (8 - c.level))) GROUP BY 1"


def _bound(how, m):
    dim = MESHES[m].dim

    def run(spark, sf_dir):
        cells = cells_of(spark, sf_dir, m, P)
        at = points(spark, sf_dir, m, L).select(morton_encode([F.col(f"q{a}") for a in range(dim)], L).alias("key"), F.lit(1).alias("one"))
        return how(at, cells, dim, L).groupBy("key").agg(F.count("*").alias("n"), F.first("level").alias("level"), F.first("path").alias("path"))

    return run


query("op_particle_bind_equi", sql.with_(sql.mesh("events", P), _BIND.format(d=3)))(_bound(analysis.bind, "events"))
query("op_particle_bind_asof", sql.with_(sql.mesh("events", P), _BIND.format(d=3)))(_bound(analysis.bind_asof, "events"))
query("w_particle_bind", sql.with_(sql.mesh("line", P), _BIND.format(d=3)))(_bound(analysis.bind, "line"))

_FLAT = "SELECT event_type, event_id, user_id::DOUBLE AS x, value AS y, value * 2 AS z FROM events"
query("op_particle_flatten", f"SELECT event_type, count(*) * 3 AS size, sum(event_id)::BIGINT AS ids FROM ({_FLAT}) GROUP BY 1")(
    lambda s, d: analysis.flat_positions(table(s, d, "events").selectExpr("event_type", "event_id", "double(user_id) AS x", "value AS y", "value * 2 AS z"), "event_type", ["event_id"], ["x", "y", "z"])
    .select("event_type", F.size("flat").cast("long").alias("size"))
    .join(table(s, d, "events").groupBy("event_type").agg(F.sum("event_id").alias("ids")), "event_type")
)
query("w_particle_flat", f"SELECT event_type, row_number() OVER (PARTITION BY event_type ORDER BY event_id) - 1 AS place, x, y, z FROM ({_FLAT})")(
    lambda s, d: analysis.from_flat(analysis.flat_positions(table(s, d, "events").selectExpr("event_type", "event_id", "double(user_id) AS x", "value AS y", "value * 2 AS z"), "event_type", ["event_id"], ["x", "y", "z"]), "event_type", ["x", "y", "z"])
)

# ---- the whole chain ---------------------------------------------------------------------------

_ALL = {"rho": "float64", "v": "float64", "p": "float64", "smooth": "float64"}


def _chain(m):
    def run(spark, sf_dir):
        local = local_of(spark, sf_dir, m, P)
        return pipeline.decompress(pipeline.compress(local, MESHES[m].dim, _ALL), _ALL)

    return run


for _m in (*SNAPSHOTS, "orders"):
    query("op_compress_roundtrip" if _m == "events" else f"op_compress_roundtrip_{_m}", sql.with_(sql.pruned(_m, domains_of(_m), P), "SELECT domain, level, path, refined, masked, rho, v, p, smooth FROM pruned"))(_chain(_m))

query("op_decompress_levels", sql.with_(sql.pruned("events", 16, P), "SELECT domain, level, path, refined, masked, p FROM pruned WHERE level <= 3"))(
    lambda s, d: pipeline.decompress(pipeline.compress(local_of(s, d, "events", P), 3, {"p": "float64"}), {"p": "float64"}, max_level=3)
)


@query("op_packed_source", sql.with_(sql.pruned("events", 16, P), "SELECT domain, level, path, refined, masked, rho FROM pruned WHERE level <= 2"))
def _(spark, sf_dir):
    """Packed files through the data source, with the level bound pushed into the decoder."""
    from ..sources.packed import PackedSource

    place = f"{shared_dir(spark).rstrip('/')}/packed-{uuid.uuid4().hex}"
    pipeline.compress(local_of(spark, sf_dir, "events", P), 3, {"rho": "float64"}).write.parquet(place)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(PackedSource)
    return spark.read.format("meshpack").option("path", place).option("fields", "rho:float64").load().where("level <= 2")


@query("op_udtf_decode", sql.with_(sql.pruned("emb", 4, P), "SELECT domain, level, path, refined FROM pruned"))
def _(spark, sf_dir):
    """A table function over run-coded grids, called from SQL."""
    grids = pipeline.compress(local_of(spark, sf_dir, "emb", P), 3, {}).select("domain", "dim", "root_level", "roots", "level_cells", "grid")
    grids.createOrReplaceTempView("meshpack_grids")
    spark.udtf.register("decode_grid", DecodeGrid)
    return spark.sql("SELECT g.domain, t.level, t.path, t.refined FROM meshpack_grids g, LATERAL decode_grid(g.dim, g.root_level, g.roots, g.level_cells, g.grid) t")


@F.udtf(returnType=T.StructType([T.StructField("level", T.IntegerType()), T.StructField("path", T.LongType()), T.StructField("refined", T.BooleanType())]), useArrow=True)
class DecodeGrid:
    """Cells of one grid stream."""

    def eval(self, dim: int, root_level: int, roots: list, level_cells: list, grid: bytes):
        from ..functions import codecs

        refined = codecs.run52_decode(bytes(grid))
        level, path = codecs.paths_of(refined, list(level_cells), list(roots), int(dim), int(root_level))
        yield from zip(level.tolist(), path.tolist(), (refined != 0).tolist())


@query("op_sql_views", sql.with_(sql.pruned("events", 16, P), "SELECT level, count(*) AS cells, count(*) FILTER (NOT refined AND NOT masked) AS leaves FROM pruned GROUP BY 1"))
def _(spark, sf_dir):
    """The same question in SQL text over registered cells."""
    pruned_of(spark, sf_dir, "events", P).createOrReplaceTempView("meshpack_cells")
    return spark.sql("SELECT level, count(*) AS cells, count_if(NOT refined AND NOT masked) AS leaves FROM meshpack_cells GROUP BY level")


# ---- snapshots over time -----------------------------------------------------------------------

_DEPTH = 6
_DAYS = f"SELECT (ts::DATE - DATE '1970-01-01')::BIGINT AS day, {sql.interleave(['q1', 'q2'], _DEPTH)} AS path, count(*) AS n FROM ({sql.points('events', _DEPTH)[0][1].replace('SELECT ', 'SELECT ts, ', 1)}) GROUP BY 1, 2"
_PAIR = [
    ("days", _DAYS),
    ("was", "SELECT day + 1 AS day, path, n AS n_before FROM days WHERE day < (SELECT max(day) FROM days)"),
    ("now", "SELECT day, path, n AS n_after FROM days WHERE day > (SELECT min(day) FROM days)"),
]


def _pairs(spark, sf_dir):
    """(day, path, n_before) and (day, path, n_after): the filled cells of every day but the first, and of the day before it."""
    spec = MESHES["events"]
    full = table(spark, sf_dir, "events")
    hi = int(full.agg(F.max("user_id")).first()[0] or 0) + 1
    box = replace(spec, axes=tuple(a if a.hi is not None else replace(a, hi=hi) for a in spec.axes))
    pts = grid_points(full, box, _DEPTH, keep=("ts",))
    days = cut(pts.groupBy(F.datediff(F.to_date("ts"), F.lit("1970-01-01").cast("date")).cast("long").alias("day"), morton_encode([F.col("q1"), F.col("q2")], _DEPTH).alias("path")).agg(F.count("*").alias("n")))
    first, last = days.agg(F.min("day"), F.max("day")).first()
    was = days.where(F.col("day") < last).select((F.col("day") + 1).alias("day"), "path", F.col("n").alias("n_before"))
    return was, days.where(F.col("day") > first).select("day", "path", F.col("n").alias("n_after"))


query("op_snapshot_diff", sql.with_(_PAIR, "SELECT day, path, coalesce(n_before, 0) AS n_before, coalesce(n_after, 0) AS n_after FROM was FULL JOIN now USING (day, path)"))(
    lambda s, d: (lambda was, now: was.join(now, ["day", "path"], "full").na.fill(0, ["n_before", "n_after"]))(*_pairs(s, d))
)
query("op_snapshot_common", sql.with_(_PAIR, "SELECT day, path FROM was INTERSECT SELECT day, path FROM now"))(lambda s, d: (lambda was, now: was.select("day", "path").intersect(now.select("day", "path")))(*_pairs(s, d)))
query("op_snapshot_except", sql.with_(_PAIR, "SELECT day, path FROM was EXCEPT SELECT day, path FROM now"))(lambda s, d: (lambda was, now: was.select("day", "path").exceptAll(now.select("day", "path")))(*_pairs(s, d)))

_us = lambda: F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', w.start)").alias("start")
_at = lambda s, d: table(s, d, "events").withColumn("at", F.col("ts"))
_SUMS = "count(*) AS n, sum(round(value * 100)::BIGINT)::BIGINT AS cents"
query("op_tumbling", f"SELECT epoch_us(time_bucket(INTERVAL 1 day, ts)) AS start, {_SUMS} FROM events GROUP BY 1")(lambda s, d: snapshots.windowed(_at(s, d)).select(_us(), "n", "cents"))
query("op_sliding", f"SELECT epoch_us(t) AS start, {_SUMS} FROM (SELECT *, unnest([time_bucket(INTERVAL 12 hours, ts), time_bucket(INTERVAL 12 hours, ts) - INTERVAL 12 hours]) AS t FROM events) GROUP BY 1")(
    lambda s, d: snapshots.windowed(_at(s, d), "24 hours", "12 hours").select(_us(), "n", "cents")
)
query("op_session", "SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM (SELECT *, sum(g) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 hours THEN 0 ELSE 1 END AS g FROM events)) GROUP BY user_id, s")(
    lambda s, d: snapshots.sessions(_at(s, d)).select("user_id", _us(), "n")
)


@query("w_stream_snapshots", f"SELECT epoch_us(time_bucket(INTERVAL 1 day, ts)) AS start, {_SUMS} FROM events GROUP BY 1")
def _(spark, sf_dir):
    """The tumbling windows by a stream that runs to the end of its input; equal to the batch form.

    Complete mode, as the last windows never close on a finite input.
    """
    name = f"meshpack_stream_{uuid.uuid4().hex}"
    # the table as a folder of one file: a stream reads folders
    folder = f"{shared_dir(spark).rstrip('/')}/{name}"
    table(spark, sf_dir, "events").write.parquet(folder)
    raw = snapshots.read_events(spark, folder).withColumn("at", F.col("ts"))
    sums = raw.groupBy(F.window("at", "1 day").alias("w")).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    q = sums.writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", f"{folder}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).select(_us(), "n", "cents")


@query("op_stream_late", f"SELECT epoch_us(time_bucket(INTERVAL 1 day, ts)) AS start, {_SUMS} FROM events WHERE time_bucket(INTERVAL 1 day, ts) + INTERVAL 1 day <= (SELECT max(ts) - INTERVAL 2 days FROM events) GROUP BY 1")
def _(spark, sf_dir):
    """Windows that ended two days or more before the last event, the lateness that the watermark grants.

    Rows behind the watermark are dropped; what one micro-batch brings is not late.  Files written in parallel have no order, so the stream takes them together; by several batches rows
    of earlier days could come behind the watermark and be lost.
    """
    name = f"meshpack_late_{uuid.uuid4().hex}"
    folder = f"{shared_dir(spark).rstrip('/')}/{name}"
    table(spark, sf_dir, "events").repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(folder)
    closed = snapshots.windowed(snapshots.distinct_events(snapshots.read_events(spark, folder, 2**31 - 1)), late=None)
    q = closed.writeStream.format("memory").queryName(name).outputMode("append").option("checkpointLocation", f"{folder}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).select(_us(), "n", "cents")


@query("w_stream_encode")
def _(spark, sf_dir):
    """Closed daily windows as meshes, pruned, coded and written; the stored domains are returned.

    The last day stays open, as no later row closes it.  All files are one micro-batch: files written in
    parallel have no order, and by several batches rows of earlier days could come behind the watermark.
    """
    folder = f"{shared_dir(spark).rstrip('/')}/meshpack_encode_{uuid.uuid4().hex}"
    events = table(spark, sf_dir, "events")
    users = int(events.agg(F.max("user_id")).first()[0] or 0) + 1  # the stream's box, stated before it starts
    events.write.parquet(f"{folder}/in")
    counts = snapshots.cell_counts(snapshots.read_events(spark, f"{folder}/in", 2**31 - 1), p=P, late="1 hour", users=users)
    q = snapshots.write_snapshots(counts, f"{folder}/out", f"{folder}/state", 4, P).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{folder}/out").select("snapshot", "domain", "field", "raw_bytes", F.octet_length("data").cast("long").alias("enc_bytes"))


# ---- joins, aggregation, windows, functions ----------------------------------------------------

query("op_join_broadcast", "SELECT r_name, n_name, count(*) AS customers, sum(round(c_acctbal * 100)::BIGINT)::BIGINT AS cents FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")(
    lambda s, d: table(s, d, "customer").groupBy("c_nationkey").agg(F.count("*").alias("customers"), F.sum(F.round(F.col("c_acctbal") * 100).cast("long")).alias("cents"))
    .join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    .select("r_name", "n_name", "customers", "cents")
)
query("op_join_semi", "SELECT o_orderkey, o_totalprice FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)")(
    lambda s, d: table(s, d, "orders").join(table(s, d, "lineitem").where("l_quantity > 45").withColumnRenamed("l_orderkey", "o_orderkey"), "o_orderkey", "left_semi").select("o_orderkey", "o_totalprice")
)
query("op_join_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")(
    lambda s, d: table(s, d, "orders").join(table(s, d, "lineitem").withColumnRenamed("l_orderkey", "o_orderkey"), "o_orderkey", "left_anti").select("o_orderkey")
)
_RANGE = "SELECT k * 4 AS lo, k * 4 + 6 AS hi FROM (SELECT unnest(range(12))::BIGINT AS k)"


@query("op_join_range", f"SELECT lo, count(*) AS n FROM lineitem JOIN ({_RANGE}) ON l_quantity::BIGINT >= lo AND l_quantity::BIGINT < hi GROUP BY 1")
def _(spark, sf_dir):
    """A range join by buckets of two: an equi-join, then the exact bounds."""
    ranges = spark.range(12).select((F.col("id") * 4).alias("lo"), (F.col("id") * 4 + 6).alias("hi")).withColumn("b", F.explode(F.sequence(F.floor(F.col("lo") / 2), F.floor((F.col("hi") - 1) / 2))))
    q = table(spark, sf_dir, "lineitem").groupBy(F.col("l_quantity").cast("long").alias("q")).agg(F.count("*").alias("m")).withColumn("b", F.floor(F.col("q") / 2))
    return q.join(ranges, "b").where("q >= lo and q < hi").groupBy("lo").agg(F.sum("m").alias("n"))


query("op_join_cross_params", "SELECT k::INTEGER AS k, count(*) AS n FROM nation, (SELECT unnest([2, 4, 8]) AS k) WHERE n_nationkey % k = 0 GROUP BY 1")(
    lambda s, d: table(s, d, "nation").withColumn("k", F.explode(F.array(F.lit(2), F.lit(4), F.lit(8)))).where("n_nationkey % k = 0").groupBy("k").agg(F.count("*").alias("n"))
)

_LV = sql.threads("events", 16, P)
_GRP = "SELECT coalesce(t.level, -1)::INTEGER AS level, coalesce(t.masked, false) AS masked, count(*) AS n, grouping(t.level)::BIGINT * 2 + grouping(t.masked)::BIGINT AS g FROM local AS t GROUP BY "


def _grouped(how):
    def run(spark, sf_dir):
        local = local_of(spark, sf_dir, "events", P)
        if how == "sets":
            local.createOrReplaceTempView("meshpack_local")
            out = spark.sql("SELECT level, masked, count(*) AS n, grouping_id(level, masked) AS g FROM meshpack_local GROUP BY GROUPING SETS ((level, masked), (masked))")
        else:
            out = getattr(local, how)("level", "masked").agg(F.count("*").alias("n"), F.grouping_id().alias("g"))
        return out.withColumns({"level": F.coalesce("level", F.lit(-1)), "masked": F.coalesce("masked", F.lit(False))})

    return run


query("op_rollup_report", sql.with_(_LV, _GRP + "ROLLUP (t.level, t.masked)"))(_grouped("rollup"))
query("op_cube_report", sql.with_(_LV, _GRP + "CUBE (t.level, t.masked)"))(_grouped("cube"))
query("op_grouping_sets", sql.with_(_LV, _GRP + "GROUPING SETS ((t.level, t.masked), (t.masked))"))(_grouped("sets"))
query("op_distinct_cells", sql.with_(_LV, "SELECT count(*) AS cells, count(DISTINCT (level, path)) AS distinct_cells FROM local"))(lambda s, d: local_of(s, d, "events", P).agg(F.count("*").alias("cells"), F.count_distinct("level", "path").alias("distinct_cells")))
query("op_topk_domains", sql.with_(_LV, "SELECT domain, count(*) AS cells FROM local GROUP BY 1 ORDER BY cells DESC, domain LIMIT 5"))(
    lambda s, d: local_of(s, d, "events", P).groupBy("domain").agg(F.count("*").alias("cells")).orderBy(F.desc("cells"), "domain").limit(5)
)
query("op_window_offsets", sql.with_(_LV, "SELECT domain, level, count(*) AS cells, (sum(count(*)) OVER (PARTITION BY domain ORDER BY level) - count(*))::BIGINT AS first_place FROM local GROUP BY 1, 2"))(
    lambda s, d: (lambda c: c.withColumn("first_place", F.sum("cells").over(Window.partitionBy("domain").orderBy("level")) - F.col("cells")))(local_of(s, d, "events", P).groupBy("domain", "level").agg(F.count("*").alias("cells")))
)
_INH = "SELECT domain, level, path, last_value(CASE WHEN n > 0 THEN n END IGNORE NULLS) OVER (PARTITION BY domain ORDER BY level, path ROWS UNBOUNDED PRECEDING) AS near FROM local"
query("op_window_inherit", sql.with_(_LV, _INH))(
    lambda s, d: local_of(s, d, "events", P).select("domain", "level", "path", F.last(F.when(F.col("n") > 0, F.col("n")), ignorenulls=True).over(Window.partitionBy("domain").orderBy("level", "path").rowsBetween(Window.unboundedPreceding, 0)).alias("near"))
)
query("op_window_rank", sql.with_(_LV, "SELECT domain, level, path, rank() OVER w::INTEGER AS r, dense_rank() OVER w::INTEGER AS dr, ntile(4) OVER (PARTITION BY domain ORDER BY level, path)::INTEGER AS q FROM local WINDOW w AS (PARTITION BY domain ORDER BY level)".replace("rank() OVER w::INTEGER", "(rank() OVER w)::INTEGER").replace("dense_(rank()", "(dense_rank()").replace("ntile(4) OVER (PARTITION BY domain ORDER BY level, path)::INTEGER", "(ntile(4) OVER (PARTITION BY domain ORDER BY level, path))::INTEGER")))(
    lambda s, d: local_of(s, d, "events", P).select(
        "domain", "level", "path", F.rank().over(Window.partitionBy("domain").orderBy("level")).alias("r"), F.dense_rank().over(Window.partitionBy("domain").orderBy("level")).alias("dr"),
        F.ntile(4).over(Window.partitionBy("domain").orderBy("level", "path")).alias("q"),
    )
)

query("op_json_props", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k")))
query("op_date_axis", "SELECT o_orderkey, date_diff('day', date '1995-01-01', o_orderdate::DATE)::INTEGER AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month FROM orders")(
    lambda s, d: table(s, d, "orders").select("o_orderkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date")).alias("days"), F.date_format("o_orderdate", "yyyy-MM").alias("month"))
)
query("op_string_hex", "SELECT n_nationkey, hex(encode(n_name)) AS h, lpad(hex(n_nationkey::BIGINT), 2, '0') AS k FROM nation")(lambda s, d: table(s, d, "nation").select("n_nationkey", F.hex(F.encode("n_name", "utf-8")).alias("h"), F.lpad(F.hex(F.col("n_nationkey").cast("long")), 2, "0").alias("k")))
query("op_array_digits", f"SELECT o_orderkey, {sql.digits('o_orderkey')}::INTEGER AS n, (o_orderkey // 52) % 52 AS second FROM orders")(
    lambda s, d: table(s, d, "orders").select("o_orderkey", F.size(F.filter(F.array(*(F.lit(52**j).cast("long") for j in range(7))), lambda p: p <= F.greatest(F.col("o_orderkey"), F.lit(1)))).alias("n"), F.expr("(o_orderkey div 52) % 52").alias("second"))
)
query("op_map_meta", sql.with_(sql.threads("emb", 4, P), "SELECT domain, level, count(*) AS cells FROM local GROUP BY 1, 2"))(
    lambda s, d: layout.level_counts(local_of(s, d, "emb", P)).groupBy("domain").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("level", "cells")))).alias("m")).select("domain", F.explode("m").alias("level", "cells"))
)


@query("w_parquet_volume")
def _(spark, sf_dir):
    """Bytes of the pruned cells as Parquet under container codecs, beside the raw size."""
    after = cut(pruned_of(spark, sf_dir, "events", P).sortWithinPartitions("domain", "level", "path"))
    place = f"{shared_dir(spark).rstrip('/')}/volume-{uuid.uuid4().hex}"
    sizes = [(c, baselines.parquet_volume(after, c, f"{place}/{c}")) for c in ("none", "snappy", "lz4", "zstd", "gzip")]
    return spark.createDataFrame(sizes, "codec string, bytes long")


@query("w_file_counts", sql.with_(sql.threads("events", 16, P), "SELECT 'published' AS dump, processes, 4 * processes AS legacy_files, 100::BIGINT AS packed_files FROM (VALUES (10000::BIGINT), (12800)) AS t(processes) UNION ALL SELECT 'events', count(DISTINCT domain), 4 * count(DISTINCT domain), 2 FROM local"))
def _(spark, sf_dir):
    """Files of a dump: the published model, and a mesh that is written as packed rows and counted where it lies."""
    place = f"{shared_dir(spark).rstrip('/')}/files-{uuid.uuid4().hex}"
    packed = pipeline.compress(local_of(spark, sf_dir, "events", P), 3, {"rho": "float64"})
    packed.repartitionByRange(2, "domain").write.parquet(place)
    back = spark.read.parquet(place).select("domain", F.input_file_name().alias("file"))
    own = back.agg(F.lit("events").alias("dump"), F.count_distinct("domain").alias("processes"), (4 * F.count_distinct("domain")).alias("legacy_files"), F.count_distinct("file").alias("packed_files"))
    made = [("published", n, *measures.file_count_model(n, target_files=100).values()) for n in (10_000, 12_800)]
    return spark.createDataFrame(made, "dump string, processes long, legacy_files long, packed_files long").unionByName(own)
