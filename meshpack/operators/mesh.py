"""Meshes from points: counts on all levels, refinement, fields, and balance.

Several meshes of one kind can be made at once: mesh ``i`` of ``roots`` has the root cell of path
``i``, and that number stands above the bits of the place within the mesh in all paths below it.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import curves
from ..sources.tables import MESHES, MeshSpec, points
from ..functions.shifts import shl, shr


@dataclass(frozen=True)
class Params:
    """Depth and refinement rule of a mesh, and how it is dealt out."""

    level_max: int = 8
    level_min: int = 2
    threshold: int = 4
    domains: int | None = None
    halo: int = 1
    curve: str = "morton"
    align: str = "leaf"
    balance: str | None = None


def parent(path: Column, dim: int) -> Column:
    return shr(path, dim)


def within(level: Column, path: Column, dim: int, roots: int) -> Column:
    """Path within the mesh that a cell belongs to."""
    return path if roots == 1 else path.bitwiseAND(shl(F.lit(1).cast("long"), (level * dim).cast("int")) - 1)


def counts_by_level(pts: DataFrame, dim: int, level_max: int) -> DataFrame:
    """(level, path, n, sv, sp) of every non-empty cell.

    Points are summed in the finest cells first; these, not the points, are dealt out to the
    levels above, and summed before the shuffle.
    """
    key = curves.morton_encode([F.col(f"q{a}") for a in range(dim)], level_max)
    finest = pts.groupBy(key.alias("path")).agg(F.count("*").alias("n"), F.sum("sv").alias("sv"), F.sum("sp").alias("sp"))
    every = finest.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(level_max))))
    at = shr("path", ((F.lit(level_max) - F.col("level")) * dim).cast("int"))
    return every.groupBy("level", at.alias("path")).agg(F.sum("n").alias("n"), F.sum("sv").alias("sv"), F.sum("sp").alias("sp"))


def refined_cells(counts: DataFrame, dim: int, p: Params, roots: int = 1) -> DataFrame:
    """(level, path) of refined cells; closed under parents, as counts grow upwards."""
    spark = counts.sparkSession
    top = spark.range(1).select(F.explode(F.sequence(F.lit(0), F.lit(max(p.level_min - 1, 0)))).alias("level"))
    top = top.where(F.col("level") < p.level_min).select("level", F.explode(F.sequence(F.lit(0).cast("long"), shl(F.lit(roots).cast("long"), (F.col("level") * dim).cast("int")) - 1)).alias("path"))
    deep = counts.where((F.col("level") >= p.level_min) & (F.col("level") < p.level_max) & (F.col("n") > p.threshold)).select("level", "path")
    return top.union(deep)


def children(cells: DataFrame, dim: int, *keep: str) -> DataFrame:
    """All children of ``cells``: (level, path), and what is kept."""
    return cells.select(
        *keep, (F.col("level") + 1).alias("level"),
        F.explode(F.transform(F.sequence(F.lit(0), F.lit((1 << dim) - 1)), lambda c: shl("path", dim).bitwiseOR(c.cast("long")))).alias("path"),
    )


def tree_of(refined: DataFrame, dim: int, roots: int = 1) -> DataFrame:
    """(level, path, refined) of the root and all children of refined cells."""
    spark = refined.sparkSession
    root = spark.range(roots).select(F.lit(0).alias("level"), F.col("id").alias("path"))
    cells = root.union(children(refined, dim))
    marked = refined.select("level", "path", F.lit(True).alias("refined"))
    return cells.join(marked, ["level", "path"], "left").select("level", "path", F.coalesce("refined", F.lit(False)).alias("refined"))


def neighbours(cells: DataFrame, dim: int, reach: int, face: bool, bits: int, *keep: str, roots: int = 1) -> DataFrame:
    """Same-level cells within ``reach`` of each cell, itself included, inside the box."""
    from itertools import product

    around = [o for o in product(range(-reach, reach + 1), repeat=dim) if not face or sum(map(abs, o)) <= reach]
    spread = cells.withColumns({f"_x{a}": x for a, x in enumerate(curves.morton_decode(within(F.col("level"), F.col("path"), dim, roots), dim, bits))})
    offsets = F.array(*(F.struct(*(F.lit(v).alias(f"o{a}") for a, v in enumerate(o))) for o in around))
    moved = spread.withColumn("_o", F.explode(offsets)).withColumns({f"_y{a}": F.col(f"_x{a}") + F.col(f"_o.o{a}") for a in range(dim)})
    side = shl(F.lit(1).cast("long"), F.col("level"))
    inside = moved.where(" and ".join(f"_y{a} >= 0" for a in range(dim)))
    for a in range(dim):
        inside = inside.where(F.col(f"_y{a}") < side)
    to = curves.morton_encode([F.col(f"_y{a}") for a in range(dim)], bits)
    if roots > 1:
        deep = (F.col("level") * dim).cast("int")
        to = to.bitwiseOR(shl(shr("path", deep), deep))
    return inside.select(*keep, "level", to.alias("path"))


def balanced(refined: DataFrame, dim: int, level_max: int, face: bool = True) -> DataFrame:
    """The least set around ``refined`` in which neighbouring leaves differ by a level at most.

    A refined cell asks that the parents of its neighbours be refined.  One sweep from the
    deepest level up, one distinct for each level.
    """
    from .storage import cut

    out = cut(refined.distinct())
    for level in range(level_max - 1, 0, -1):
        here = out.where(F.col("level") == level)
        asked = neighbours(here, dim, 1, face, level_max).select((F.col("level") - 1).alias("level"), parent(F.col("path"), dim).alias("path"))
        out = out.union(asked).distinct()
        if level % 4 == 0:
            out = cut(out)
    return out


def with_fields(cells: DataFrame, counts: DataFrame, spec: MeshSpec, roots: int = 1) -> DataFrame:
    """``cells`` with n, rho, v, p and smooth.  Empty cells take v and p of the nearest ancestor with points."""
    dim = spec.dim
    joined = cells.join(counts, ["level", "path"], "left")
    empty = joined.where("n is null").select("level", "path")
    above = (
        empty.where("level > 0").withColumn("up", F.explode(F.sequence(F.lit(1), F.col("level"))))
        .select("level", "path", (F.col("level") - F.col("up")).alias("l"), shr("path", (F.col("up") * dim).cast("int")).alias("k"))
        .join(counts.select(F.col("level").alias("l"), F.col("path").alias("k"), F.struct("n", "sv", "sp").alias("w")), ["l", "k"])
        .groupBy("level", "path").agg(F.max_by("w", "l").alias("w"))
    )
    full = joined.join(above, ["level", "path"], "left")
    n = F.coalesce("n", "w.n")
    q = shl(F.lit(1).cast("long"), F.col("level"))
    centre = curves.morton_decode(within(F.col("level"), F.col("path"), dim, roots), dim)
    gap = [(2 * x + 1 - q) for x in centre]
    r2 = sum((g * g for g in gap[1:]), gap[0] * gap[0])
    off, scale = spec.v
    return full.select(
        "level", "path", "refined", F.coalesce("n", F.lit(0)).alias("n"),
        (F.coalesce("n", F.lit(0)).cast("double") * shl(F.lit(1).cast("long"), (F.col("level") * dim).cast("int")).cast("double")).alias("rho"),
        F.coalesce((F.coalesce("sv", "w.sv") - off * n).cast("double") / (scale * n).cast("double"), F.lit(0.0)).alias("v"),
        F.coalesce(F.coalesce("sp", "w.sp").cast("double") / (spec.p_scale * n).cast("double"), F.lit(0.0)).alias("p"),
        ((q * q).cast("double") / (q * q + r2).cast("double")).alias("smooth"),
    )


def build_mesh(spark: SparkSession, sf_dir: str, mesh: str, p: Params = Params(), pts: DataFrame | None = None) -> DataFrame:
    """Global cells of a catalogued mesh with their fields.

    Counts are stored: refinement and fields each read them, and the points are read once.
    """
    from .storage import cut

    spec = MESHES[mesh]
    counts = cut(counts_by_level(points(spark, sf_dir, mesh, p.level_max) if pts is None else pts, spec.dim, p.level_max))
    refined = refined_cells(counts, spec.dim, p)
    if p.balance:
        refined = balanced(refined, spec.dim, p.level_max, p.balance == "face")
    return with_fields(tree_of(refined, spec.dim), counts, spec)
