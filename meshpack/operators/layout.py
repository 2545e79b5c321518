"""The tree layout: breadth-first arrays of a domain's tree, and back.

Children follow the order of their refined parents, so the array order is (level, path) and a
cell's place is its rank in that order; no pointer is stored.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from ..functions.shifts import shr

BREADTH = ["level", "path"]


def with_place(local: DataFrame) -> DataFrame:
    """``local`` with ``place``: the index from 0 in the domain's arrays."""
    return local.withColumn("place", F.row_number().over(Window.partitionBy("domain").orderBy(*BREADTH)) - 1)


def packed_schema(fields: dict[str, str]) -> T.StructType:
    return T.StructType(
        [
            T.StructField("domain", T.IntegerType()), T.StructField("dim", T.IntegerType()), T.StructField("root_level", T.IntegerType()),
            T.StructField("roots", T.ArrayType(T.LongType())), T.StructField("level_cells", T.ArrayType(T.LongType())), T.StructField("n_cells", T.LongType()),
            T.StructField("refined", T.BinaryType()), T.StructField("masked", T.BinaryType()),
            *(T.StructField(f"f_{f}", T.BinaryType()) for f in fields),
        ]
    )


def to_arrays(local: DataFrame, dim: int, fields: dict[str, str] | None = None) -> DataFrame:
    """One row a domain: a byte for each boolean, and the raw little-endian bytes of each field.

    ``fields`` maps names to ``float64`` or ``float32``.
    """
    fields = fields or {}
    schema = packed_schema(fields)

    def pack(table: pa.Table) -> pa.Table:
        import numpy as np

        from ..functions import codecs

        level = table.column("level").to_numpy()
        path = table.column("path").to_numpy()
        order = np.lexsort((path, level))
        level, path = level[order], path[order]
        first = int(level[0])
        row = {
            "domain": [table.column("domain")[0].as_py()], "dim": [dim], "root_level": [first], "roots": [path[level == first].tolist()],
            "level_cells": [np.bincount(level - first).tolist()], "n_cells": [len(level)],
            "refined": [codecs.as_bytes(table.column("refined"), order)], "masked": [codecs.as_bytes(table.column("masked"), order)],
        }
        for f, kind in fields.items():
            row[f"f_{f}"] = [table.column(f).to_numpy()[order].astype(np.dtype(kind).newbyteorder("<")).tobytes()]
        from pyspark.sql.pandas.types import to_arrow_schema

        return pa.Table.from_pydict(row, schema=to_arrow_schema(schema))

    used = local.select("domain", "level", "path", "refined", "masked", *fields)
    return used.groupBy("domain").applyInArrow(pack, schema)


def to_cells(packed: DataFrame, fields: dict[str, str] | None = None) -> DataFrame:
    """Rows again: paths follow from counting refined cells level by level."""
    fields = fields or {}
    kinds = {"float64": T.DoubleType(), "float32": T.FloatType()}
    schema = T.StructType(
        [
            T.StructField("domain", T.IntegerType()), T.StructField("level", T.IntegerType()), T.StructField("path", T.LongType()),
            T.StructField("refined", T.BooleanType()), T.StructField("masked", T.BooleanType()), *(T.StructField(f, kinds[k]) for f, k in fields.items()),
        ]
    )

    def run(batches):
        import numpy as np

        from ..functions import codecs

        for batch in batches:
            for r in batch.to_pylist():
                refined, masked = np.frombuffer(r["refined"], np.uint8), np.frombuffer(r["masked"], np.uint8)
                level, path = codecs.paths_of(refined, r["level_cells"], r["roots"], r["dim"], r["root_level"])
                arrays = [pa.array(np.full(len(level), r["domain"], np.int32)), pa.array(level), pa.array(path), pa.array(refined.astype(bool)), pa.array(masked.astype(bool))]
                arrays += [pa.array(np.frombuffer(r[f"f_{f}"], np.dtype(k).newbyteorder("<")).astype(k)) for f, k in fields.items()]
                yield pa.RecordBatch.from_arrays(arrays, names=[f.name for f in schema])

    return packed.mapInArrow(run, schema)


def validate(local: DataFrame, dim: int) -> DataFrame:
    """Levels whose number of cells is not 2^dim times the refined cells above; none in a sound tree."""
    per = local.groupBy("domain", "level").agg(F.count("*").alias("cells"), F.count_if("refined").alias("refined"))
    above = per.select("domain", (F.col("level") + 1).alias("level"), F.col("refined").alias("parents"))
    both = per.join(above, ["domain", "level"], "full")
    first = Window.partitionBy("domain")
    return (
        both.withColumn("_first", F.min(F.when(F.col("cells").isNotNull(), F.col("level"))).over(first))
        .where((F.col("level") > F.col("_first")) & (F.coalesce("cells", F.lit(0)) != F.coalesce("parents", F.lit(0)) * (1 << dim)))
        .select("domain", "level", F.coalesce("cells", F.lit(0)).alias("cells"), (F.coalesce("parents", F.lit(0)) * (1 << dim)).alias("expected"))
    )


def level_counts(local: DataFrame) -> DataFrame:
    return local.groupBy("domain", "level").agg(F.count("*").alias("cells"), F.count_if("refined").alias("refined"), F.count_if("masked").alias("masked"))


def describe(local: DataFrame, **meta: str) -> DataFrame:
    """Counts that ease reading, and key-value pairs as given."""
    pairs = F.create_map(*(F.lit(x) for kv in sorted(meta.items()) for x in kv)) if meta else F.create_map().cast("map<string,string>")
    return local.groupBy("domain").agg(
        F.count("*").alias("n_cells"), F.count_if("refined").alias("n_grids"), (F.max("level") - F.min("level") + 1).cast("int").alias("n_levels"),
    ).withColumn("meta", pairs)


def upsample(leaves: DataFrame, dim: int, sums: dict[str, str]) -> DataFrame:
    """Values of all coarse cells from leaves: ``sums`` maps a result to an integer sum's expression.

    Leaves are dealt out to their ancestors and summed before the shuffle; means are quotients of sums.
    """
    up = leaves.withColumn("up", F.explode(F.sequence(F.lit(0), F.col("level"))))
    at = up.withColumns({"l": F.col("level") - F.col("up"), "k": shr("path", (F.col("up") * dim).cast("int"))})
    return at.groupBy(F.col("l").alias("level"), F.col("k").alias("path")).agg(*(F.sum(F.expr(e)).alias(c) for c, e in sums.items()))


def to_forest(local: DataFrame, dim: int, l0: int) -> DataFrame:
    """Cells from level ``l0`` on; roots that are masked leaves are dropped with their (empty) trees."""
    below = local.where(F.col("level") >= l0)
    return below.where(~((F.col("level") == l0) & F.col("masked") & ~F.col("refined")))


def roots(forest: DataFrame, dim: int, l0: int) -> DataFrame:
    """Root indices of each domain: Morton keys, and the coordinates that they save."""
    from ..functions.curves import morton_decode

    top = forest.where(F.col("level") == l0)
    return top.select("domain", F.col("path").alias("morton"), *(x.alias(f"i{a}") for a, x in enumerate(morton_decode(F.col("path"), dim))))


def from_forest(forest: DataFrame, dim: int, l0: int, curve: str = "morton") -> DataFrame:
    """The structure of the whole trees from a forest of pruned ones: (domain, level, path, refined, masked).

    A kept root owns something at or below itself, so the refined cells above are its ancestors and
    no others; children of these that the forest has not are roots that it dropped, masked leaves.
    A cell above belongs to the domain that its first root on the curve belongs to.
    """
    from .domains import curve_start
    from .mesh import children

    kept = forest.where(F.col("level") == l0).select("domain", "level", "path", "masked")
    up = kept.select("domain", "path", F.explode(F.sequence(F.lit(1), F.lit(l0))).alias("up")) if l0 else None
    if up is None:
        return forest.select("domain", "level", "path", "refined", "masked")
    above = up.select("domain", (F.lit(l0) - F.col("up")).alias("level"), shr("path", (F.col("up") * dim).cast("int")).alias("path")).distinct()
    first = lambda df: df.withColumn("_k", curve_start(dim, l0, curve))
    root = forest.select("domain").distinct().select("domain", F.lit(0).alias("level"), F.lit(0).cast("long").alias("path"))
    cells = first(root.unionByName(children(above, dim, "domain")))
    known = first(kept).select("domain", "_k", "masked")
    owner = cells.join(known, ["domain", "_k"], "left").select("domain", "level", "path", F.coalesce("masked", F.lit(True)).alias("masked"))
    top = owner.join(above.withColumn("refined", F.lit(True)), ["domain", "level", "path"], "left").withColumn("refined", F.coalesce("refined", F.lit(False)))
    own = forest.select("domain", "level", "path", "refined", "masked")
    missing = top.where(F.col("level") == l0).join(own, ["domain", "level", "path"], "left_anti")
    return own.unionByName(top.where(F.col("level") < l0)).unionByName(missing)


def select_fields(packed: DataFrame, fields: list[str]) -> DataFrame:
    """Packed rows with some of their fields: the arrays of the tree stay whole."""
    return packed.select(*(c for c in packed.columns if not c.startswith("f_") or c[2:] in fields))
