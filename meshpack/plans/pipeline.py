"""The whole chain: layout, pruning, run coding of both arrays, and float coding of the fields."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import codecs
from ..operators import layout, prune

STREAM = T.StructType([T.StructField("dtype", T.StringType()), T.StructField("k", T.IntegerType()), T.StructField("level_bits", T.ArrayType(T.LongType())), T.StructField("data", T.BinaryType())])


def compressed_schema(fields) -> T.StructType:
    head = [T.StructField("domain", T.IntegerType()), T.StructField("dim", T.IntegerType()), T.StructField("root_level", T.IntegerType()), T.StructField("roots", T.ArrayType(T.LongType())), T.StructField("level_cells", T.ArrayType(T.LongType())), T.StructField("n_cells", T.LongType()), T.StructField("grid", T.BinaryType()), T.StructField("mask", T.BinaryType())]
    return T.StructType([*head, *(T.StructField(f"f_{f}", STREAM) for f in fields)])


def compress(local: DataFrame, dim: int, fields: dict[str, str], k: int = 4, pruned: bool = False) -> DataFrame:
    """One row a domain.  Arrays are packed, pruned and coded in one pass over each domain, after the
    one shuffle by domain; rows that are pruned already skip that step."""
    packed = layout.to_arrays(local, dim, fields)
    schema = compressed_schema(fields)

    def run(batches):
        import numpy as np
        from pyspark.sql.pandas.types import to_arrow_schema

        for batch in batches:
            out = []
            for r in batch.to_pylist():
                refined, masked, levels = np.frombuffer(r["refined"], np.uint8), np.frombuffer(r["masked"], np.uint8), r["level_cells"]
                kept = np.ones(len(refined), bool)
                if not pruned:
                    refined, masked, kept, levels = codecs.prune_arrays(r["refined"], r["masked"], levels, dim)
                row = {c: r[c] for c in ("domain", "dim", "root_level", "roots")} | {"level_cells": levels, "n_cells": len(refined)}
                row |= {"grid": codecs.run52_encode(refined, levels), "mask": codecs.run52_encode(masked, levels)}
                for f, dtype in fields.items():
                    values = np.frombuffer(codecs.pick(r[f"f_{f}"], kept, len(kept)), np.dtype(dtype))
                    data, at = codecs.pxor_encode(values, refined, levels, dim, k)
                    row[f"f_{f}"] = {"dtype": dtype, "k": k, "level_bits": at, "data": data}
                out.append(row)
            yield pa.RecordBatch.from_pylist(out, schema=to_arrow_schema(schema))

    return packed.mapInArrow(run, schema)


def decompress(packed: DataFrame, fields: dict[str, str], max_level: int | None = None) -> DataFrame:
    """Cells again, or those down to a level: streams are read no further than asked for."""
    kinds = {"float64": T.DoubleType(), "float32": T.FloatType()}
    head = [T.StructField("domain", T.IntegerType()), T.StructField("level", T.IntegerType()), T.StructField("path", T.LongType()), T.StructField("refined", T.BooleanType()), T.StructField("masked", T.BooleanType())]
    schema = T.StructType([*head, *(T.StructField(f, kinds[d]) for f, d in fields.items())])

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                yield cells_of(r, fields, max_level)

    return packed.select("domain", "dim", "root_level", "roots", "level_cells", "grid", "mask", *(f"f_{f}" for f in fields)).mapInArrow(run, schema)


def cells_of(r: dict, fields: dict[str, str], max_level: int | None) -> pa.RecordBatch:
    """Cells of one packed row, as Arrow."""
    import numpy as np

    deep = None if max_level is None else max_level - r["root_level"]
    levels = r["level_cells"] if deep is None else r["level_cells"][: deep + 1]
    refined = codecs.run52_decode(r["grid"], None, deep)
    masked = codecs.run52_decode(r["mask"], None, deep)
    level, path = codecs.paths_of(refined, levels, r["roots"], r["dim"], r["root_level"])
    arrays = [pa.array(np.full(len(level), r["domain"], np.int32)), pa.array(level), pa.array(path), pa.array(refined.astype(bool)), pa.array(masked.astype(bool))]
    for f, dtype in fields.items():
        s = r[f"f_{f}"]
        arrays.append(pa.array(codecs.pxor_decode(s["data"], refined, levels, r["dim"], dtype, s["k"], max_level=deep)))
    return pa.RecordBatch.from_arrays(arrays, names=["domain", "level", "path", "refined", "masked", *fields])


def prune_first(local: DataFrame, dim: int, level_max: int) -> DataFrame:
    """Rows pruned by the form that suits the depth: closed up to 12 levels, intervals beyond."""
    return prune.prune(local, dim) if level_max <= 12 else prune.prune_interval(local, dim, level_max)


def volumes(packed: DataFrame, fields) -> DataFrame:
    """Bytes of each part over all domains."""
    return packed.agg(F.sum("n_cells").alias("n_cells"), F.sum(F.octet_length("grid")).alias("grid"), F.sum(F.octet_length("mask")).alias("mask"), *(F.sum(F.octet_length(f"f_{f}.data")).alias(f) for f in fields))
