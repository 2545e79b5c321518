"""The base-52 run coder, relational and as a kernel, with one contract.

A stream is the first bit, then for each run of equal bits its length: digits in base 52, most
significant first, ahead of their number if there are more than one.  With level marks, runs end
at levels and a byte tells whether the bit changes there.
"""

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import codecs

BASE, SHIFT, MOST = codecs.BASE, codecs.SHIFT, codecs.MOST_DIGITS


def runs(rows: DataFrame, by: list[str], order: list[str], bit: str, level: str | None = None) -> DataFrame:
    """(by, run_no, bit, len[, level]) of the maximal runs of ``bit``, cut at levels if one is named."""
    w = Window.partitionBy(*by).orderBy(*order)
    new = F.lag(bit).over(w).isNull() | (F.lag(bit).over(w) != F.col(bit))
    if level:
        new = new | (F.lag(level).over(w) != F.col(level))
    numbered = rows.withColumn("_new", new.cast("int")).withColumn("run_no", F.sum("_new").over(w.rowsBetween(Window.unboundedPreceding, 0)) - 1)
    keep = [F.first(level).alias("level")] if level else []
    return numbered.groupBy(*by, "run_no").agg(F.first(bit).alias("bit"), F.count("*").alias("len"), *keep)


def digit_count(length: Column) -> Column:
    return sum(((length >= BASE**j).cast("int") for j in range(1, MOST)), F.lit(1))


def run_bytes(length: Column) -> Column:
    n = digit_count(length)
    return F.when(n > 1, n + 1).otherwise(1).cast("long")


def run_hex(length: Column) -> Column:
    """A run's bytes in hexadecimal."""
    n = digit_count(length)
    digit = lambda j: F.lpad(F.hex((F.floor(length / F.pow(F.lit(float(BASE)), j.cast("double"))).cast("long") % BASE + SHIFT)), 2, "0")
    head = F.when(n > 1, F.lpad(F.hex(n.cast("long")), 2, "0")).otherwise("")
    checked = F.when(length > codecs.MAX_RUN, F.raise_error(F.lit("a run is longer than its code can tell")).cast("string"))
    return F.coalesce(checked, F.concat(head, F.array_join(F.transform(F.sequence(n - 1, F.lit(0), F.lit(-1)), digit), "")))


def encode(rows: DataFrame, by: list[str], order: list[str], bit: str, level: str | None = None) -> DataFrame:
    """(by, code) in DataFrame functions only."""
    found = runs(rows, by, order, bit, level)
    w = Window.partitionBy(*by).orderBy("run_no")
    text = run_hex(F.col("len"))
    if level:
        before, at = F.lag("bit").over(w), F.lag("level").over(w)
        mark = F.when(at != F.col("level"), F.when(before != F.col("bit"), "09").otherwise("0A")).otherwise("")
        text = F.concat(mark, text)
    head = F.when(F.col("bit").cast("int") == 1, "01").otherwise("00")
    hexed = found.select(*by, "run_no", F.concat(F.when(F.col("run_no") == 0, head).otherwise(""), text).alias("h"))
    joined = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("run_no", "h"))), lambda x: x["h"]), "")
    return hexed.groupBy(*by).agg(F.unhex(joined).alias("code"))


def encoded_bytes(found: DataFrame, by: list[str], marked: bool = False) -> DataFrame:
    """Length of each stream from its runs alone: one byte, each run's, and a byte for each mark."""
    marks = F.max("level") - F.min("level") if marked else F.lit(0)
    return found.groupBy(*by).agg((1 + F.sum(run_bytes(F.col("len"))) + marks).cast("long").alias("code_bytes"), F.sum("len").alias("n_bits"))


def tight_bytes(found: DataFrame, by: list[str]) -> DataFrame:
    """(by, code_bytes, six_bit_bytes, exact_bytes): the stream, the same in words of six bits, as its bytes stay
    below 64, and the first bit with the binary digits of all run lengths, which no stream of theirs can go below."""
    code, exact = 1 + F.sum(run_bytes(F.col("len"))), 1 + F.sum(F.length(F.bin("len")))
    per = found.groupBy(*by).agg(code.alias("code_bytes"), exact.alias("exact"))
    return per.select(*by, "code_bytes", F.expr("(6 * code_bytes + 7) div 8").alias("six_bit_bytes"), F.expr("(exact + 7) div 8").alias("exact_bytes"))


def runs_of_code(codes: DataFrame, by: list[str], code: str = "code") -> DataFrame:
    """(by, run_no, bit, len, level) of encoded streams; no bit is inflated."""
    kept = codes.select(*by, code)
    schema = T.StructType([*(kept.schema[c] for c in by), T.StructField("run_no", T.LongType()), T.StructField("bit", T.BooleanType()), T.StructField("len", T.LongType()), T.StructField("level", T.IntegerType())])
    n = len(by)

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                found = list(codecs.run52_runs(batch.column(n)[i].as_py() or b""))
                one = [batch.column(k).take(pa.array([i] * len(found), pa.int32())) for k in range(n)]
                yield pa.RecordBatch.from_arrays(
                    [*one, pa.array(range(len(found)), pa.int64()), pa.array([bool(b) for b, _, _ in found]), pa.array([m for _, m, _ in found], pa.int64()), pa.array([v for _, _, v in found], pa.int32())],
                    names=[f.name for f in schema],
                )

    return kept.mapInArrow(run, schema)


def bits_at(found: DataFrame, offsets: DataFrame, by: list[str]) -> DataFrame:
    """(by, offset, bit) by a range join of offsets with the running sums of run lengths.

    Both sides carry a bucket of offsets; a run stands in each bucket it touches.
    """
    size = 4096
    w = Window.partitionBy(*by).orderBy("run_no").rowsBetween(Window.unboundedPreceding, 0)
    placed = found.withColumn("stop", F.sum("len").over(w)).withColumn("start", F.col("stop") - F.col("len"))
    held = placed.withColumn("_b", F.explode(F.sequence(F.floor(F.col("start") / size), F.floor((F.col("stop") - 1) / size))))
    asked = offsets.withColumn("_b", F.floor(F.col("offset") / size))
    return held.join(asked, [*by, "_b"]).where("offset >= start and offset < stop").select(*by, "offset", "bit")


@F.arrow_udf(T.BinaryType())
def encode_udf(bits: pa.Array) -> pa.Array:
    """Stream of an array of booleans given as bytes."""
    return pa.array([None if b is None else codecs.run52_encode(b) for b in bits.to_pylist()], pa.binary())


@F.arrow_udf(T.BinaryType())
def decode_udf(code: pa.Array) -> pa.Array:
    return pa.array([None if b is None else codecs.run52_decode(b).tobytes() for b in code.to_pylist()], pa.binary())


@F.arrow_udf(T.IntegerType())
def bit_at_udf(code: pa.Array, offset: pa.Array) -> pa.Array:
    return pa.array([None if b is None or o is None else int(codecs.run52_bit_at(b, o)) for b, o in zip(code.to_pylist(), offset.to_pylist())], pa.int32())


@F.pandas_udf(T.BinaryType())
def encode_agg(place: pd.Series, bit: pd.Series) -> bytes:
    """Stream of a group's bits, in the order of their places."""
    return codecs.run52_encode(bit.to_numpy()[place.to_numpy().argsort()].astype("uint8"))
