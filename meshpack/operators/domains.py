"""Domain decomposition along a curve, fully threaded local trees, ownership, and merging."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import curves
from .mesh import Params, children, neighbours, within
from .storage import cut
from ..functions.shifts import shl, shr

#: Cells that a domain should hold at most: what one task packs and codes at once.
CELLS_A_DOMAIN = 10_000_000


def domains_for(cells: int, least: int = 1, most_cells: int = CELLS_A_DOMAIN) -> int:
    """Number of domains that keeps each near ``most_cells``."""
    return max(least, -(-cells // most_cells))


def curve_start(dim: int, level_max: int, curve: str, roots: int = 1) -> Column:
    """First key of a cell at the finest level; keys of its descendants follow it."""
    key = F.col("path")
    if curve != "morton":
        inner, deep = within(F.col("level"), key, dim, roots), (F.col("level") * dim).cast("int")
        inner = curves.hilbert_of_morton(inner, dim, F.col("level"))
        key = inner if roots == 1 else inner.bitwiseOR(shl(shr("path", deep), deep))
    return shl(key, ((F.lit(level_max) - F.col("level")) * dim).cast("int"))


def leaf_boundaries(leaves: DataFrame, n: int, roots: int = 1, shift: int = 62) -> list[int]:
    """First keys of domains 1 .. n-1 so that the leaf of rank r belongs to domain r * n div total.

    With several roots, whose numbers stand ``shift`` bits up in the keys, each has ``n`` domains of
    its own, and a bound is put between roots.

    Keys are dealt out by ranges, sorted and stored; the sizes of the ranges tell in which one, and
    at which place there, each boundary stands.  The driver sees a count for each partition and
    n - 1 keys, whatever the number of leaves.
    """
    if n * roots < 2:
        return []
    placed = cut(leaves.select("key").repartitionByRange("key").sortWithinPartitions("key").select("key", F.monotonically_increasing_id().alias("at")))
    of_root = shr("key", shift) if roots > 1 else F.lit(0)
    sizes = sorted((r["part"], r["root"], r["n"]) for r in placed.groupBy(shr("at", 33).alias("part"), of_root.alias("root")).agg(F.count("*").alias("n")).collect())
    if not sizes:
        return [0] * (n * roots - 1)
    total, seen, due = [0] * roots, [0] * roots, [1] * roots
    for _, root, count in sizes:
        total[root] += count
    wanted, before, place = [], None, 0
    for part, root, count in sizes:
        place = place if part == before else 0
        # rank of the first leaf of domain d: least r with r * n div total >= d
        while due[root] < n and (rank := -(-due[root] * total[root] // n)) < seen[root] + count:
            wanted.append((root * n + due[root], (part << 33) + place + rank - seen[root]))
            due[root] += 1
        seen[root] += count
        before, place = part, place + count
    asked = placed.sparkSession.createDataFrame(wanted, "d int, at long")
    found = {r["d"]: r["key"] for r in placed.join(F.broadcast(asked), "at").select("d", "key").collect()}
    # with fewer leaves than domains the last own nothing
    return [found.get(d, (-(-d // n)) << shift) for d in range(1, n * roots)]


def coarse_boundaries(leaves: DataFrame, n: int, dim: int, p: Params, roots: int = 1) -> list[int]:
    """As above, with bounds only between cells of level_min: at most 2^(dim * level_min) counts."""
    shift = (p.level_max - p.level_min) * dim
    found = sorted(leaves.groupBy(shr("key", shift).alias("k")).count().collect())
    total, seen, due = [0] * roots, [0] * roots, [1] * roots
    end = p.level_max * dim
    out = [(-(-d // n)) << end for d in range(1, n * roots)]
    for k, count in found:
        total[(k << shift) >> end] += count
    for k, count in found:
        root = (k << shift) >> end
        while due[root] <= seen[root] * n // total[root]:
            out[root * n + due[root] - 1] = k << shift
            due[root] += 1
        seen[root] += count
    return out


def owner_of(key: Column, bounds: list[int]) -> Column:
    """Number of boundaries at or below the key, by a search whose depth is log2 of their number."""
    if len(bounds) > 64:  # too many for a tree of branches: the same search over an array, one literal
        known = F.split(F.lit(",".join(map(str, bounds))), ",").cast("array<bigint>")
        steps = F.array(*(F.lit(1 << k) for k in reversed(range(len(bounds).bit_length()))))

        def jump(at, step):
            to = at + step
            return F.when((to <= len(bounds)) & (F.element_at(known, F.least(to, F.lit(len(bounds)))) <= key), to).otherwise(at)

        return F.aggregate(steps, F.lit(0), jump)

    def among(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(lo)
        mid = (lo + hi) // 2
        return F.when(key < bounds[mid], among(lo, mid)).otherwise(among(mid + 1, hi))

    return among(0, len(bounds))


def split(cells: DataFrame, dim: int, n: int, p: Params, roots: int = 1) -> list[int]:
    """Boundaries of ``n`` domains, of each root if there are several, with equal numbers of leaves along the curve."""
    leaves = cells.where("not refined").select(curve_start(dim, p.level_max, p.curve, roots).alias("key"))
    if p.align == "coarse":
        return coarse_boundaries(leaves, n, dim, p, roots)
    return leaf_boundaries(leaves, n, roots, p.level_max * dim)


def owned_paths(cells: DataFrame, dim: int, bounds: list[int], p: Params, roots: int = 1) -> DataFrame:
    """(domain, level, path) of all leaves of each domain and of their ancestors."""
    leaves = cells.where("not refined").select("level", "path", owner_of(curve_start(dim, p.level_max, p.curve, roots), bounds).alias("domain"))
    up = leaves.withColumn("up", F.explode(F.sequence(F.lit(0), F.col("level"))))
    return up.select("domain", (F.col("level") - F.col("up")).alias("level"), shr("path", (F.col("up") * dim).cast("int")).alias("path")).distinct()


def thread_trees(cells: DataFrame, dim: int, p: Params, n: int, bounds: list[int] | None = None, roots: int = 1) -> DataFrame:
    """Local trees: (domain, level, path, refined, masked) and the fields of ``cells``.

    A cell is refined in a domain if it is globally, and lies above level_min or within the halo
    of something the domain owns.  Every tree starts at the root and is closed, so its arrays hold
    all children of each refined cell.  With several roots, root i has the domains from i * n on.
    """
    bounds = split(cells, dim, n, p, roots) if bounds is None else bounds
    spark = cells.sparkSession
    refined = cells.where("refined").select("level", "path")
    deep = refined.where(F.col("level") >= p.level_min)
    owned = owned_paths(cells, dim, bounds, p, roots)
    if p.halo:
        # nearness goes both ways, and refined cells are few: they ask their surroundings for owners
        asked = neighbours(deep.withColumn("_at", F.col("path")), dim, p.halo, False, p.level_max, "_at", roots=roots)
        local = asked.join(owned, ["level", "path"]).select("domain", "level", F.col("_at").alias("path")).distinct()
    else:
        local = owned.join(deep, ["level", "path"], "left_semi").select("domain", "level", "path")
    domains = spark.range(n * roots).select(F.col("id").cast("int").alias("domain"))
    root_of = shr("path", (F.col("level") * dim).cast("int")).cast("int") if roots > 1 else F.lit(0)
    top = refined.where(F.col("level") < p.level_min).select("level", "path", F.explode(F.sequence(root_of * n, root_of * n + (n - 1))).alias("domain"))
    # stored: it stands on both sides of what follows, an eighth (in 3-D) of the cells it makes
    local = cut(local.unionByName(top.select("domain", "level", "path")))
    root = domains.select("domain", F.lit(0).alias("level"), F.expr(f"domain div {n}").alias("path"))
    every = root.union(children(local, dim, "domain"))
    marked = every.join(local.withColumn("_r", F.lit(True)), ["domain", "level", "path"], "left")
    fields = [c for c in cells.columns if c not in ("level", "path", "refined")]
    with_fields = marked.join(cells.select("level", "path", *fields), ["level", "path"])
    owner = owner_of(curve_start(dim, p.level_max, p.curve, roots), bounds)
    return with_fields.select("domain", "level", "path", F.coalesce("_r", F.lit(False)).alias("refined"), (owner != F.col("domain")).alias("masked"), *fields)


def merge(local: DataFrame, mapping: list[tuple[int, int]]) -> DataFrame:
    """Trees of domains joined into the domain that ``mapping`` gives: owner's values win."""
    to = F.create_map(*(F.lit(x) for pair in mapping for x in pair))
    fields = [c for c in local.columns if c not in ("domain", "level", "path", "refined", "masked")]
    # an owned value goes before a ghost's
    pick = [F.max_by(c, (~F.col("masked")).cast("int")).alias(c) for c in fields]
    return (
        local.withColumn("domain", F.element_at(to, F.col("domain"))).groupBy("domain", "level", "path")
        .agg(F.bool_or("refined").alias("refined"), F.bool_and("masked").alias("masked"), *pick)
    )


def stored(local: DataFrame, n: int) -> DataFrame:
    """Local trees partitioned by domain, once for all that follows, and stored."""
    return cut(local.repartition(n, "domain"))

