"""What the coders are compared with: legacy lists, byte and bit arrays, libraries, down-casts."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import codecs
from ..functions.curves import morton_decode
from ..functions.shifts import shl, shr
from .analysis import at_level

#: (label, codec, level) of the libraries that boolean and float arrays are compared with.
BOOL_CODECS = [("run52", None, None), ("varint", None, None), ("zlib1", "zlib", 1), ("zlib9", "zlib", 9), ("lz4", "lz4", None), ("snappy", "snappy", None), ("zstd", "zstd", 3)]
FLOAT_CODECS = [("pxor4", None, None), ("zlib1", "zlib", 1), ("zlib6", "zlib", 6), ("zlib9", "zlib", 9), ("lz4", "lz4", None), ("snappy", "snappy", None), ("zstd", "zstd", 3), ("block", "block", None), ("lzma", "lzma", 6)]


def legacy_grid_bytes(dim: int, grids: Column) -> Column:
    """Byte model of the legacy lists: for each grid 32-bit links to 2d neighbours, a parent and
    2^d children with their refinement and ownership flags, the next and previous grid, and d doubles."""
    d = 1 << dim
    return grids * (4 * (2 * dim + 1 + 2 + 3 * d) + 8 * dim)


def codec_report(packed: DataFrame, array: str, labels, dtype: str | None = None, repeat: int = 1) -> DataFrame:
    """(array, codec, domain, raw_bytes, enc_bytes, ns, back_ns, exact) of an array under each codec; the best time of ``repeat`` runs."""
    schema = T.StructType(
        [T.StructField("array", T.StringType()), T.StructField("codec", T.StringType()), T.StructField("domain", T.IntegerType())]
        + [T.StructField(n, T.LongType()) for n in ("raw_bytes", "enc_bytes", "ns", "back_ns")]
        + [T.StructField("exact", T.BooleanType())]
    )

    def coder(label, name, level, row):
        import numpy as np

        if label == "run52":
            return codecs.run52_encode, lambda b, n: codecs.run52_decode(b)
        if label == "varint":
            return codecs.varint_encode, lambda b, n: codecs.varint_decode(b).tobytes()
        if label.startswith("pxor"):
            refined = np.frombuffer(row["refined"], np.uint8)
            args = (refined, row["level_cells"], row["dim"])
            return (lambda b: codecs.pxor_encode(np.frombuffer(b, dtype), *args, k=int(label[4:]))[0]), (lambda b, n: codecs.pxor_decode(b, *args, dtype, k=int(label[4:])).tobytes())
        return codecs.library(name, level)

    def run(batches):
        import time

        from pyspark.sql.pandas.types import to_arrow_schema

        for batch in batches:
            out = []
            for row in batch.to_pylist():
                raw = row[array]
                for label, name, level in labels:
                    enc, dec = coder(label, name, level, row)
                    times = []
                    for _ in range(repeat):
                        a = time.perf_counter_ns()
                        code = enc(raw)
                        b = time.perf_counter_ns()
                        back = dec(code, len(raw)) if dec else None
                        times.append((b - a, time.perf_counter_ns() - b))
                    ns, back_ns = map(min, zip(*times))
                    out.append({"array": array, "codec": label, "domain": row["domain"], "raw_bytes": len(raw), "enc_bytes": len(code), "ns": ns, "back_ns": back_ns if dec else None, "exact": None if back is None else bytes(back) == raw})
            yield pa.RecordBatch.from_pylist(out, schema=to_arrow_schema(schema))

    return packed.mapInArrow(run, schema)


def summed(report: DataFrame) -> DataFrame:
    """Ratio of sums over all domains, and single-thread speeds in MB/s."""
    return report.groupBy("array", "codec").agg(
        F.sum("raw_bytes").alias("raw_bytes"), F.sum("enc_bytes").alias("enc_bytes"),
        (F.sum("raw_bytes") / F.sum("enc_bytes")).alias("ratio"),
        (F.sum("raw_bytes") * 1000.0 / F.sum("ns")).alias("mb_s"), (F.sum("raw_bytes") * 1000.0 / F.sum("back_ns")).alias("back_mb_s"),
        F.max("ns").alias("longest_ns"), F.bool_and("exact").alias("exact"),
    )


def corners(leaves: DataFrame, dim: int, level_max: int) -> DataFrame:
    """The 2^d corner points of each leaf, in units of the finest cells."""
    x = morton_decode(F.col("path"), dim)
    side = shl(F.lit(1).cast("long"), (F.lit(level_max) - F.col("level")).cast("int"))
    at = leaves.withColumn("_c", F.explode(F.array(*map(F.lit, range(1 << dim)))))
    return at.select("level", "path", *((( x[a] + shr("_c", a).bitwiseAND(F.lit(1))) * side).alias(f"x{a}") for a in range(dim)))


def unstructured_volume(leaves: DataFrame, dim: int, level_max: int) -> DataFrame:
    """Points, cells and bytes of leaves as an unstructured grid: distinct corners and links to them."""
    points = corners(leaves, dim, level_max).select(*(f"x{a}" for a in range(dim))).distinct()
    n = points.agg(F.count("*").alias("n_points"))
    c = leaves.agg(F.count("*").alias("n_cells"))
    both = n.withColumn("_k", F.lit(1)).join(c.withColumn("_k", F.lit(1)), "_k")
    return both.select("n_points", "n_cells", (F.col("n_points") * 8 * dim + F.col("n_cells") * (8 * (1 << dim) + 8 + 1)).alias("bytes"))


def resample(cells: DataFrame, dim: int, level: int, fields: list[str], most_cells: int = 1 << 27) -> DataFrame:
    """A uniform grid at ``level``: each cell has the values of the leaf around it, or
    its own coarse ones where the mesh is refined further.  ``cells`` are those of the tree, refined ones included."""
    if 1 << (dim * level) > most_cells:
        raise ValueError("a uniform grid of this level is too large")
    up = at_level(cells, level)
    shift = ((F.lit(level) - F.col("level")) * dim).cast("int")
    inner = F.explode(F.sequence(shl("path", shift), shl(F.col("path") + 1, shift) - 1))
    return up.select(inner.alias("path"), *fields).select("path", *(x.alias(f"i{a}") for a, x in enumerate(morton_decode(F.col("path"), dim))), *fields)


def parquet_volume(df: DataFrame, codec: str, place: str) -> int:
    """Bytes of ``df`` as Parquet under a container codec, written below the shared folder ``place``."""
    df.write.mode("overwrite").option("compression", codec).parquet(place)
    jvm = df.sparkSession.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(place)
    fs = path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration())
    return int(fs.getContentSummary(path).getLength())
