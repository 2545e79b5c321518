"""Tree pruning: refined cells without an owned descendant become leaves, their subtrees go.

Three forms give the same trees.  The closed form follows from the bottom-up rule: the working
mask of a cell is set exactly if nothing below it is owned, so a refined cell survives as refined
exactly if some strict descendant is owned, and a cell survives exactly if its parent does.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .storage import cut
from ..functions.shifts import shl, shr

KEY = ["domain", "level", "path"]


def live_refined(local: DataFrame, dim: int) -> DataFrame:
    """(domain, level, path) of the strict ancestors of owned cells."""
    owned = local.where("not masked and level > 0").withColumn("up", F.explode(F.sequence(F.lit(1), F.col("level"))))
    return owned.select("domain", (F.col("level") - F.col("up")).alias("level"), shr("path", (F.col("up") * dim).cast("int")).alias("path")).distinct()


def prune(local: DataFrame, dim: int, root_level: int = 0) -> DataFrame:
    """Closed form: two joins on keys that start with the domain, no iteration, one pass over ``local``."""
    live = live_refined(local, dim)
    flagged = local.join(live.withColumn("_live", F.lit(True)), KEY, "left")
    above = live.select(F.col("domain").alias("_d"), (F.col("level") + 1).alias("_l"), F.col("path").alias("_p"))
    up = (F.col("domain") == F.col("_d")) & (F.col("level") == F.col("_l")) & (shr("path", dim) == F.col("_p"))
    kept = flagged.join(above, up, "left").where((F.col("level") == root_level) | ((F.col("level") > root_level) & F.col("_d").isNotNull()))
    return kept.withColumn("refined", F.col("refined") & F.coalesce("_live", F.lit(False))).select(*local.columns)


def prune_sweep(local: DataFrame, dim: int, root_level: int = 0) -> DataFrame:
    """Bottom-up form: a round for each level, from the deepest to the top.

    The working mask starts as the stored one, and a cell with an unmasked child loses it; a
    refined cell whose children are all masked turns into a leaf and drops what hangs on it.
    """
    deepest = local.agg(F.max("level")).first()[0]
    if deepest is None:
        return local
    state = local.select(*KEY, "refined", F.col("masked").alias("work"))
    for level in range(deepest - 1, root_level - 1, -1):
        below = state.where(F.col("level") == level + 1).groupBy("domain", shr("path", dim).alias("path")).agg(F.bool_and("work").alias("all_masked"))
        below = below.withColumn("level", F.lit(level))
        state = state.join(below, KEY, "left").select(
            *KEY,
            (F.col("refined") & ~F.coalesce("all_masked", F.lit(False))).alias("refined"),
            (F.col("work") & F.coalesce("all_masked", F.lit(True))).alias("work"),
        )
        if level % 3 == 0:
            state = cut(state)
    # from the top: a cell stays if its parent stays and is still refined
    stays = state.where(F.col("level") == root_level)
    out = stays
    for level in range(root_level + 1, deepest + 1):
        parents = stays.where("refined").select("domain", F.lit(level).alias("level"), F.col("path").alias("_p"))
        here = state.where(F.col("level") == level)
        stays = here.join(parents, (here.domain == parents.domain) & (here.level == parents.level) & (shr(here.path, dim) == parents._p), "left_semi")
        if level % 3 == 0:
            stays = cut(stays)
        out = out.unionByName(stays)
    final = out.select(*KEY, F.col("refined").alias("_r"))
    return local.join(final, KEY).withColumn("refined", F.col("_r")).select(*local.columns)


def prune_interval(local: DataFrame, dim: int, level_max: int, root_level: int = 0) -> DataFrame:
    """Interval form: in depth-first order a cell has an owned strict descendant exactly if the
    next owned cell begins before the cell's own interval of finest keys ends.

    The order is walked from its end, so that the next owned cell is a running value and not a
    search for each cell.  Siblings share a parent, which lives exactly if one of them is owned or lives.
    """
    shift = ((F.lit(level_max) - F.col("level")) * dim).cast("int")
    first = shl("path", shift)
    end = shl(F.col("path") + 1, shift)
    behind = Window.partitionBy("domain").orderBy(F.desc("_first"), F.desc("level")).rowsBetween(Window.unboundedPreceding, -1)
    siblings = Window.partitionBy("domain", "level", "_above")
    marked = local.withColumns({"_first": first, "_end": end, "_above": shr("path", dim)})
    marked = marked.withColumn("_next", F.min(F.when(~F.col("masked"), F.col("_first"))).over(behind))
    marked = marked.withColumn("_live", F.coalesce(F.col("_next") < F.col("_end"), F.lit(False)))
    marked = marked.withColumn("_kept", F.bool_or(~F.col("masked") | F.col("_live")).over(siblings))
    kept = marked.where((F.col("level") == root_level) | ((F.col("level") > root_level) & F.col("_kept")))
    return kept.withColumn("refined", F.col("refined") & F.col("_live")).select(*local.columns)


def working_mask(local: DataFrame, dim: int) -> DataFrame:
    """``local`` with ``work``: masked, unless something below is owned."""
    live = live_refined(local, dim).withColumn("_live", F.lit(True))
    return local.join(live, KEY, "left").withColumn("work", F.col("masked") & ~F.coalesce("_live", F.lit(False))).drop("_live")


def prune_arrays(packed: DataFrame) -> DataFrame:
    """Per-domain form over raw arrays (see ``layout.to_arrays``): numpy, one pass a level."""
    from ..functions import codecs

    names = packed.columns

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            rows = batch.to_pylist()
            for r in rows:
                fields = {k: v for k, v in r.items() if k.startswith("f_")}
                refined, masked, kept, levels = codecs.prune_arrays(r["refined"], r["masked"], r["level_cells"], r["dim"])
                r.update(refined=refined.tobytes(), masked=masked.tobytes(), level_cells=levels, n_cells=int(kept.sum()))
                for k, v in fields.items():
                    r[k] = codecs.pick(v, kept, len(kept))
            yield pa.RecordBatch.from_pylist(rows, schema=batch.schema).select(names)

    return packed.mapInArrow(run, packed.schema)


def prune_times(packed: DataFrame, repeat: int = 5) -> DataFrame:
    """(domain, n_cells, coarse, place, ns): time of the numpy form, least of ``repeat`` runs, beside the number of
    coarse cells of each domain and their mean place in its arrays."""
    from pyspark.sql import types as T

    from ..functions import codecs

    schema = T.StructType([T.StructField("domain", T.IntegerType()), T.StructField("n_cells", T.LongType()), T.StructField("coarse", T.LongType()), T.StructField("place", T.DoubleType()), T.StructField("ns", T.LongType())])

    def run(batches):
        import time

        import numpy as np
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        for batch in batches:
            out = []
            for r in batch.select(["domain", "dim", "level_cells", "refined", "masked"]).to_pylist():
                best = None
                for _ in range(repeat):
                    began = time.perf_counter_ns()
                    codecs.prune_arrays(r["refined"], r["masked"], r["level_cells"], r["dim"])
                    ns = time.perf_counter_ns() - began
                    best = ns if best is None else min(best, ns)
                at = np.flatnonzero(np.frombuffer(r["refined"], np.uint8))
                out.append({"domain": r["domain"], "n_cells": len(r["refined"]), "coarse": len(at), "place": float(at.mean()) if len(at) else 0.0, "ns": best})
            yield pa.RecordBatch.from_pylist(out, schema=to_arrow_schema(schema))

    return packed.mapInArrow(run, schema)
