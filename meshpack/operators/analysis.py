"""Reading a stored mesh: leaves, levels of detail, boxes, images, neighbours, particles."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.curves import morton_decode, morton_encode
from ..functions.shifts import shl, shr


def leaves(local: DataFrame) -> DataFrame:
    """Owned leaves: each part of the box exactly once over all domains."""
    return local.where("not refined and not masked")


def at_level(cells: DataFrame, level: int) -> DataFrame:
    """A coarser view: cells of ``level`` and the leaves above it.  The level bound reaches the scan."""
    return cells.where((F.col("level") <= level) & ((F.col("level") == level) | ~F.col("refined")))


def box(cells: DataFrame, dim: int, level_max: int, low: list[int], high: list[int]) -> DataFrame:
    """Cells that touch the box [low, high) of finest coordinates.

    Morton order keeps cells of a box within the keys of its two corners, a bound that range
    statistics can use; the coordinates decide.
    """
    side = shl(F.lit(1).cast("long"), (F.lit(level_max) - F.col("level")).cast("int"))
    x = morton_decode(F.col("path"), dim)
    hit = F.lit(True)
    for a in range(dim):
        hit = hit & (x[a] * side < high[a]) & ((x[a] + 1) * side > low[a])
    return cells.where(hit)


def image(cells: DataFrame, dim: int, level: int, axis: int, weight: str, value: str) -> DataFrame:
    """Projection along an axis at a level of detail: pixel sums of an integer weight and of cells."""
    view = at_level(cells, level)
    shift = (F.lit(level) - F.col("level")).cast("int")
    x = morton_decode(F.col("path"), dim)
    keep = [a for a in range(dim) if a != axis]
    spread = F.sequence(F.lit(0).cast("long"), shl(F.lit(1).cast("long"), shift * len(keep)) - 1)
    at = view.select(value, weight, shift.alias("_s"), *(x[a].alias(f"_x{a}") for a in keep), F.explode(spread).alias("_c"))
    # coarse leaves cover several pixels; each takes the leaf's value
    sub = [at["_c"]] if len(keep) == 1 else morton_decode(F.col("_c"), len(keep))
    pixels = at.select(*((F.expr(f"shiftleft(_x{a}, _s)") + sub[i]).alias(f"i{a}") for i, a in enumerate(keep)), weight, value)
    return pixels.groupBy(*(f"i{a}" for a in keep)).agg(F.sum(weight).alias("weight"), F.count("*").alias("cells"), F.max(value).alias("peak"))


def face_neighbours(cells: DataFrame, dim: int) -> DataFrame:
    """(level, path, axis, side, other) for same-level face neighbours that exist: probes, not stored links."""
    x = morton_decode(F.col("path"), dim)
    spread = cells.select("level", "path", *(x[a].alias(f"_x{a}") for a in range(dim)))
    probes = F.array(*(F.struct(F.lit(a).alias("axis"), F.lit(s).alias("side")) for a in range(dim) for s in (-1, 1)))
    asked = spread.withColumn("_p", F.explode(probes)).select("*", "_p.axis", "_p.side")
    moved = [F.col(f"_x{a}") + F.when(F.col("axis") == a, F.col("side")).otherwise(0) for a in range(dim)]
    size = shl(F.lit(1).cast("long"), F.col("level"))
    ok = F.lit(True)
    for m in moved:
        ok = ok & (m >= 0) & (m < size)
    probe = asked.where(ok).select("level", "path", "axis", "side", morton_encode(moved).alias("other"))
    there = cells.select("level", F.col("path").alias("other"))
    return probe.join(there, ["level", "other"]).select("level", "path", "axis", "side", "other")


def centres(cells: DataFrame, dim: int) -> DataFrame:
    """Centres in units of the box."""
    x = morton_decode(F.col("path"), dim)
    size = shl(F.lit(1).cast("long"), F.col("level") + 1).cast("double")
    return cells.select("level", "path", *(((2 * x[a] + 1).cast("double") / size).alias(f"c{a}") for a in range(dim)))


def bind(particles: DataFrame, cells: DataFrame, dim: int, level_max: int, key: str = "key") -> DataFrame:
    """Particles (finest key) with the leaf that holds them: an equi-join on level and prefix,
    over the levels that leaves have."""
    tree = cells.where("not refined").select("level", "path")
    levels = sorted(r["level"] for r in tree.select("level").distinct().collect())  # at most level_max + 1
    tried = particles.withColumn("level", F.explode(F.array(*map(F.lit, levels)))).withColumn("path", shr(key, ((F.lit(level_max) - F.col("level")) * dim).cast("int")))
    return tried.join(tree, ["level", "path"])


def bind_asof(particles: DataFrame, cells: DataFrame, dim: int, level_max: int, key: str = "key", parts: int = 64) -> DataFrame:
    """The same by an as-of join on first keys: union, sort, and the last leaf at or before each key.

    Work is split by ranges of the key; each leaf is put in every range it reaches into, so ranges
    are independent.
    """
    bits = dim * level_max
    up = max(0, bits - max(1, parts.bit_length() - 1))
    tree = cells.where("not refined")
    shift = ((F.lit(level_max) - F.col("level")) * dim).cast("int")
    first, stop = shl("path", shift), shl(F.col("path") + 1, shift)
    names = [c for c in particles.columns if c != key]
    starts = tree.select(first.alias("_k"), F.lit(0).alias("_t"), "level", "path", F.explode(F.sequence(shr(first, up), shr(stop - 1, up))).alias("_r"), *(F.lit(None).cast(particles.schema[c].dataType).alias(c) for c in names))
    asked = particles.select(F.col(key).alias("_k"), F.lit(1).alias("_t"), F.lit(None).cast("int").alias("level"), F.lit(None).cast("long").alias("path"), shr(key, up).alias("_r"), *names)
    w = Window.partitionBy("_r").orderBy("_k", "_t").rowsBetween(Window.unboundedPreceding, 0)
    both = starts.unionByName(asked).withColumn("_leaf", F.last(F.when(F.col("_t") == 0, F.struct("level", "path")), ignorenulls=True).over(w))
    return both.where("_t = 1").select(*names, F.col("_k").alias(key), "_leaf.level", "_leaf.path")


def flat_positions(rows: DataFrame, by: str, order: list[str], cols: list[str]) -> DataFrame:
    """(by, flat): positions of a group's particles interleaved in one array."""
    each = F.array_sort(F.collect_list(F.struct(*order, F.array(*cols).alias("_p"))))
    return rows.groupBy(by).agg(F.flatten(F.transform(each, lambda x: x["_p"])).alias("flat"))


def from_flat(flat: DataFrame, by: str, cols: list[str]) -> DataFrame:
    """(by, place, cols) again."""
    n = len(cols)
    each = flat.select(by, F.posexplode("flat").alias("_i", "_v"))
    return each.groupBy(by, F.floor(F.col("_i") / n).alias("place")).agg(*(F.max(F.when(F.col("_i") % n == i, F.col("_v"))).alias(c) for i, c in enumerate(cols)))


def truncate_mantissa(v, bits: int):
    """Lossy option, off by default: a double with its lowest mantissa bits cleared (relative error below 2^(bits - 52))."""
    from ..functions.bits import f64_bits, f64_from_bits

    return f64_from_bits(f64_bits(v).bitwiseAND(F.lit(-(1 << bits))))
