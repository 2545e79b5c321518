"""Snapshots from a stream of events: windowed counts, late rows, and one mesh for each closed window."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.curves import morton_encode
from ..functions.shifts import shl, shr
from ..operators import domains, mesh, prune
from ..operators.mesh import Params
from ..operators.pxor import encode
from ..operators.storage import cut
from ..sources.tables import MESHES, grid_points

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files as a stream; times as UTC instants, as watermarks need them."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(folder)
    return raw.withColumn("at", F.to_timestamp(F.col("ts").cast("string")))


def windowed(events: DataFrame, size: str = "1 day", slide: str | None = None, late: str | None = "2 days", time: str = "at") -> DataFrame:
    """Counts and sums by tumbling or sliding window; the same call serves batches.  ``late`` None: the
    stream has its watermark already."""
    some = events.withWatermark(time, late) if events.isStreaming and late else events
    w = F.window(time, size, slide) if slide else F.window(time, size)
    return some.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "2 days", time: str = "at") -> DataFrame:
    some = events.withWatermark(time, late) if events.isStreaming else events
    return some.groupBy("user_id", F.session_window(time, gap).alias("w")).agg(F.count("*").alias("n"))


def distinct_events(events: DataFrame, late: str = "2 days") -> DataFrame:
    return events.withWatermark("at", late).dropDuplicatesWithinWatermark(["event_id"])


def cell_counts(events: DataFrame, size: str = "1 day", p: Params = Params(), late: str = "2 days", users: int = 1 << 20) -> DataFrame:
    """(window, path, n, sv, sp): finest-cell sums of each window, kept as state until it closes.

    ``users`` bounds the box: user ids from there on fall in its last cells.
    """
    spec = MESHES["events"]
    some = events.withWatermark("at", late) if events.isStreaming else events
    pts = grid_points(some, _fixed_box(spec, users), p.level_max, keep=("at",))


    key = morton_encode([F.col(f"q{a}") for a in range(spec.dim)], p.level_max)
    return pts.groupBy(F.window("at", size).alias("w"), key.alias("path")).agg(F.count("*").alias("n"), F.sum("sv").alias("sv"), F.sum("sp").alias("sp"))


def _fixed_box(spec, users: int):
    """A stream's box is stated, not looked up."""
    from dataclasses import replace

    axes = tuple(a if a.hi is not None else replace(a, hi=users) for a in spec.axes)
    return replace(spec, axes=axes)


def snapshot_trees(counts: DataFrame, n: int, p: Params = Params(), roots: int = 1) -> DataFrame:
    """Pruned local trees of one window's finest cells (path, n, sv, sp).

    With several windows in one pass, window i has the root i, whose number stands above the bits of
    the finest paths, and the domains from i * n on.
    """
    spec = MESHES["events"]
    every = counts.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(p.level_max))))
    at = shr("path", ((F.lit(p.level_max) - F.col("level")) * spec.dim).cast("int"))
    levels = every.groupBy("level", at.alias("path")).agg(F.sum("n").alias("n"), F.sum("sv").alias("sv"), F.sum("sp").alias("sp"))


    levels = cut(levels)
    cells = cut(mesh.with_fields(mesh.tree_of(mesh.refined_cells(levels, spec.dim, p, roots), spec.dim, roots), levels, spec, roots))
    parts = min(n * roots, max(n, 4 * counts.sparkSession.sparkContext.defaultParallelism))
    return prune.prune(domains.stored(domains.thread_trees(cells, spec.dim, p, n, roots=roots), parts), spec.dim)


def write_snapshots(counts: DataFrame, folder: str, checkpoint: str, n: int = 4, p: Params = Params()):
    """A query that encodes each closed window and writes its domains, replacing what a retry left.

    Windows of a micro-batch, those that the watermark has just closed, are taken in one pass, as
    roots of a forest: the number of jobs does not grow with theirs.
    """
    dim = MESHES["events"].dim

    def batch(df: DataFrame, _epoch: int) -> None:
        df = df.persist()
        starts = sorted(df.select("w.start", F.unix_micros("w.start")).distinct().collect(), key=lambda r: r[1])
        if starts:
            known = [(i, at, f"{start:%Y-%m-%dT%H-%M-%S}") for i, (start, at) in enumerate(starts)]
            windows = F.broadcast(df.sparkSession.createDataFrame(known, "root long, at long, snapshot string"))
            path = shl("root", dim * p.level_max).bitwiseOR(F.col("path"))
            counts = df.withColumn("at", F.unix_micros("w.start")).join(windows, "at").select(path.alias("path"), "n", "sv", "sp")
            packed = encode(snapshot_trees(counts, n, p, len(starts)), dim, {"rho": "float64"})
            named = packed.withColumn("root", F.expr(f"domain div {n}")).join(windows, "root").withColumn("domain", F.col("domain") % n).drop("root", "at")
            named.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("snapshot").parquet(folder)
        df.unpersist()

    return counts.writeStream.foreachBatch(batch).outputMode("append").option("checkpointLocation", checkpoint)
