"""Cost and accuracy measures: each one aggregation over cells, packs or packed rows."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ceiling_ratio(width: int, dim: int, k: int = 4) -> float:
    """Most that the float coder can reach: a full header's worth of zeros in every pack."""
    d = 1 << dim
    return width * d / ((width - min((1 << k) - 1, width)) * d + k)


def exponent_line(width: int, dim: int, k: int = 4) -> float:
    """Ratio if exactly sign and exponent are removed everywhere."""
    d, top = 1 << dim, 12 if width == 64 else 9
    return width * d / ((width - top) * d + k)


def pruning_report(before: DataFrame, after: DataFrame) -> DataFrame:
    """Removed fraction: least and most over domains, and of the summed counts."""
    a = before.groupBy("domain").agg(F.count("*").alias("a"))
    b = after.groupBy("domain").agg(F.count("*").alias("b"))
    both = a.join(b, "domain", "left").select("domain", "a", F.coalesce("b", F.lit(0)).alias("b"))
    gone = (F.col("a") - F.col("b")).cast("double") / F.col("a").cast("double")
    return both.agg(
        F.count("*").alias("domains"), F.sum("a").alias("cells_before"), F.sum("b").alias("cells_after"),
        F.min(gone).alias("min_frac"), F.max(gone).alias("max_frac"),
        ((F.sum("a") - F.sum("b")).cast("double") / F.sum("a").cast("double")).alias("global_frac"),
    )


def redundancy(local: DataFrame) -> DataFrame:
    """Local cells against distinct global ones."""
    per = local.groupBy("level", "path").agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("local_cells"), F.count("*").alias("global_cells"), (F.sum("n").cast("double") / F.count("*").cast("double")).alias("redundancy"))


def ratio(raw: Column, coded: Column) -> Column:
    return raw.cast("double") / coded.cast("double")


def pmf(leads: DataFrame) -> DataFrame:
    """(lead, n, share) of leading zeros; one row for each count from 0 to the width."""
    counts = leads.groupBy("lead").agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("t")).first()["t"] or 0
    return counts.select("lead", "n", (F.col("n").cast("double") / float(total or 1)).alias("share"))


def entropy(counts: DataFrame) -> DataFrame:
    """Bits of entropy of counts ``n``, to nine places."""
    total = counts.agg(F.sum("n").alias("t")).first()["t"] or 1
    p = F.col("n").cast("double") / float(total)
    return counts.agg(F.round(-F.sum(p * F.log2(p)), 9).alias("entropy"))


def frequency_factor(reduction: float) -> int:
    return math.floor(1 / (1 - reduction))


def byte_histogram(df: DataFrame, column: str) -> DataFrame:
    """(byte, n) over all bytes of a text column, without UDFs: pairs of hexadecimal digits,
    summed before the shuffle, so that a task deals out at most 256 rows."""
    pairs = F.regexp_extract_all(F.hex(F.encode(F.col(column), "utf-8")), F.lit("(..)"), F.lit(1))
    each = df.where(F.octet_length(column) > 0).select(F.explode(pairs).alias("byte"))
    return each.groupBy("byte").agg(F.count("*").alias("n"))


def file_count_model(processes: int, per_process: int = 4, target_files: int = 1) -> dict[str, int]:
    """Files a dump makes: several for each process against a few large ones."""
    return {"legacy_files": processes * per_process, "packed_files": target_files}


def roundtrip_mismatches(a: DataFrame, b: DataFrame) -> int:
    return a.exceptAll(b).count() + b.exceptAll(a).count()
