"""The parent-XOR float coder: predictions, residuals, pack statistics and exact sizes as
expressions; bytes by a kernel for each domain."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import bits, codecs
from .layout import to_arrays
from ..functions.shifts import shr

WIDTH = {"float64": 64, "float32": 32}


class MissingCoarseValues(ValueError):
    """The parent's value predicts its children's, so coarse cells need values (see layout.upsample)."""


def view(v: Column, dtype: str) -> Column:
    return bits.f64_bits(v) if dtype == "float64" else bits.f32_bits(v)


def predict(local: DataFrame, dim: int, field: str, how: str = "parent", by: tuple[str, ...] = ("domain",)) -> DataFrame:
    """Non-root cells with ``value`` and ``pred``: the parent's value, or its share by children.

    An equi-join on keys that start with the domain; both sides keep the domain's partitioning.
    """
    if field not in local.columns:
        raise MissingCoarseValues(field)
    child = local.select(*by, "level", "path", F.col(field).alias("value"), shr("path", dim).alias("parent"))
    share = F.col(field) / float(1 << dim) if how == "parent_share" else F.col(field)
    up = local.where("refined").select(*by, (F.col("level") + 1).alias("level"), F.col("path").alias("parent"), share.alias("pred"))
    return child.join(up, [*by, "level", "parent"])


def previous(local: DataFrame, field: str) -> DataFrame:
    """Each cell with the value before it in array order as its prediction."""
    w = Window.partitionBy("domain").orderBy("level", "path")
    return local.select("domain", "level", "path", F.col(field).alias("value"), F.lag(field).over(w).alias("pred"))


def residuals(pairs: DataFrame, dtype: str = "float64") -> DataFrame:
    return pairs.withColumn("s", view(F.col("value"), dtype).bitwiseXOR(view(F.col("pred"), dtype)))


def pack_stats(res: DataFrame, by: tuple[str, ...] = ("domain",), dtype: str = "float64") -> DataFrame:
    """(by, level, parent, or_bits, lead): the OR of each pack and its leading zeros, uncapped."""
    packs = res.groupBy(*by, "level", "parent").agg(F.bit_or("s").alias("or_bits"))
    return packs.withColumn("lead", bits.leading_zeros(F.col("or_bits"), WIDTH[dtype]))


def pack_bits(lead: Column, dim: int, k: int, width: int) -> Column:
    return (k + (1 << dim) * (width - F.least(lead, F.lit(min((1 << k) - 1, width))))).cast("long")


def pack_leads(local: DataFrame, dim: int, fields: dict[str, str], how: str = "parent", by: tuple[str, ...] = ("domain",)) -> DataFrame:
    """(by, level, parent, and for each name a lead): leading zeros of every pack for several fields at once.

    ``fields`` maps a name to ``column:dtype``.  An OR of exclusive-ors with one value follows from the
    children's OR and AND: where the value has a zero bit it is the OR's, elsewhere the inverse of the
    AND's.  So children are summed up to a row a pack, map-side first, before the join with parents,
    and one shuffle and one join serve all fields.
    """
    spec = {n: x.split(":") for n, x in fields.items()}
    for f, _ in spec.values():
        if f not in local.columns:
            raise MissingCoarseValues(f)
    keys = [*by, "level", "parent"]
    child = local.select(*by, "level", shr("path", dim).alias("parent"), *(view(F.col(f), t).alias(n) for n, (f, t) in spec.items()))
    packs = child.groupBy(*keys).agg(*(x for n in spec for x in (F.bit_or(n).alias(f"{n}_or"), F.bit_and(n).alias(f"{n}_and"))))
    value = lambda f: F.col(f) / float(1 << dim) if how == "parent_share" else F.col(f)
    up = local.where("refined").select(*by, (F.col("level") + 1).alias("level"), F.col("path").alias("parent"), *(view(value(f), t).alias(f"{n}_up") for n, (f, t) in spec.items()))
    differ = lambda n: F.col(f"{n}_or").bitwiseAND(F.bitwise_not(f"{n}_up")).bitwiseOR(F.bitwise_not(f"{n}_and").bitwiseAND(F.col(f"{n}_up")))
    return packs.join(up, keys).select(*keys, *(bits.leading_zeros(differ(n), WIDTH[t]).alias(n) for n, (_, t) in spec.items()))


def sizes_of(local: DataFrame, dim: int, fields: dict[str, str], k: int = 4, how: str = "parent", root_level: int = 0) -> DataFrame:
    """(domain, name, n_cells, enc_bits, enc_bytes) of the streams of several fields, by one join; see ``pack_leads``."""
    width = {n: WIDTH[x.split(":")[1]] for n, x in fields.items()}
    leads = pack_leads(local, dim, fields, how)
    per = leads.groupBy("domain").agg(*(F.sum(pack_bits(F.col(n), dim, k, w)).alias(n) for n, w in width.items()))
    cells = local.groupBy("domain").agg(F.count("*").alias("n_cells"), F.count_if(F.col("level") == root_level).alias("roots"))
    total = lambda n: F.coalesce(n, F.lit(0)) + width[n] * F.col("roots")
    each = cells.join(per, "domain", "left").select("domain", "n_cells", F.explode(F.array(*(F.struct(F.lit(n).alias("name"), total(n).cast("long").alias("enc_bits")) for n in fields))).alias("x"))
    return each.select("domain", "x.name", "n_cells", "x.enc_bits", F.ceil(F.col("x.enc_bits") / 8).cast("long").alias("enc_bytes"))


def shift_bits(v: Column, by: int, dtype: str = "float64") -> Column:
    """The bits of ``v`` moved on by a constant, modulo 2 to the width: the reversible form of a shift, ``-by`` undoes it.

    Sums wrap at the width, so this needs no float arithmetic and loses nothing, whatever the values.
    """
    width = WIDTH[dtype]
    if width == 64:  # wrapped in halves: whole sums of 64 bits may not overflow
        low, high = by & 0xFFFFFFFF, by >> 32 & 0xFFFFFFFF
        a = v.bitwiseAND(F.lit(0xFFFFFFFF)) + F.lit(low)
        b = F.shiftrightunsigned(v, 32) + F.lit(high) + shr(a, 32)
        return F.shiftleft(b.bitwiseAND(F.lit(0xFFFFFFFF)), 32).bitwiseOR(a.bitwiseAND(F.lit(0xFFFFFFFF)))
    return (v + F.lit(by & 0xFFFFFFFF)).bitwiseAND(F.lit(0xFFFFFFFF))


def require_coarse(local: DataFrame, fields) -> DataFrame:
    """``local`` with an error in place of a null coarse value, which nothing below it could be predicted from."""
    checked = lambda f: F.when(F.col("refined") & F.col(f).isNull(), F.raise_error(F.lit(f"no coarse value of {f}")).cast("double")).otherwise(F.col(f))
    for f in fields:
        if f not in local.columns:
            raise MissingCoarseValues(f)
    return local.withColumns({f: checked(f).cast(local.schema[f].dataType) for f in fields})


def sizes(local: DataFrame, dim: int, field: str, k: int = 4, dtype: str = "float64", how: str = "parent", root_level: int = 0) -> DataFrame:
    """(domain, n_cells, enc_bits, enc_bytes) of the stream of each domain, without writing it."""
    return sizes_of(local, dim, {field: f"{field}:{dtype}"}, k, how, root_level).drop("name")


def cell_leads(res: DataFrame, dtype: str = "float64") -> DataFrame:
    return res.withColumn("lead", bits.leading_zeros(F.col("s"), WIDTH[dtype]))


def encode(local: DataFrame, dim: int, fields: dict[str, str], k: int = 4, how: str = "parent") -> DataFrame:
    """One row a domain and field: stream, its plain size, and the bit where each level begins."""
    return encode_arrays(to_arrays(require_coarse(local, fields), dim, fields), fields, k, how)


def encode_arrays(packed: DataFrame, fields: dict[str, str], k: int = 4, how: str = "parent") -> DataFrame:
    schema = T.StructType(
        [
            T.StructField("domain", T.IntegerType()), T.StructField("field", T.StringType()), T.StructField("dtype", T.StringType()), T.StructField("k", T.IntegerType()),
            T.StructField("raw_bytes", T.LongType()), T.StructField("enc_bits", T.LongType()), T.StructField("level_bits", T.ArrayType(T.LongType())),
            T.StructField("data", T.BinaryType()), T.StructField("ns", T.LongType()),
        ]
    )

    def run(batches):
        import time

        import numpy as np
        from pyspark.sql.pandas.types import to_arrow_schema

        for batch in batches:
            for r in batch.to_pylist():
                out = []
                for f, dtype in fields.items():
                    values = np.frombuffer(r[f"f_{f}"], np.dtype(dtype))
                    refined = np.frombuffer(r["refined"], np.uint8)
                    began = time.perf_counter_ns()
                    data, at = codecs.pxor_encode(values, refined, r["level_cells"], r["dim"], k, how)
                    ns = time.perf_counter_ns() - began
                    out.append({"domain": r["domain"], "field": f, "dtype": dtype, "k": k, "raw_bytes": values.nbytes, "enc_bits": None, "level_bits": at, "data": data, "ns": ns})
                yield pa.RecordBatch.from_pylist(out, schema=to_arrow_schema(schema))

    return packed.mapInArrow(run, schema).withColumn("enc_bits", F.octet_length("data").cast("long") * 8)


def decode(streams: DataFrame, grids: DataFrame, how: str = "parent", max_level: int | None = None) -> DataFrame:
    """(domain, field, values, ns): fields again, as doubles, guided by the grids' arrays."""
    joined = streams.join(grids.select("domain", "dim", "level_cells", "refined"), "domain")
    schema = T.StructType([T.StructField("domain", T.IntegerType()), T.StructField("field", T.StringType()), T.StructField("dtype", T.StringType()), T.StructField("values", T.BinaryType()), T.StructField("ns", T.LongType())])

    def run(batches):
        import time

        import numpy as np
        from pyspark.sql.pandas.types import to_arrow_schema

        for batch in batches:
            out = []
            for r in batch.to_pylist():
                began = time.perf_counter_ns()
                values = codecs.pxor_decode(r["data"], np.frombuffer(r["refined"], np.uint8), r["level_cells"], r["dim"], r["dtype"], r["k"], how, max_level)
                out.append({"domain": r["domain"], "field": r["field"], "dtype": r["dtype"], "values": values.tobytes(), "ns": time.perf_counter_ns() - began})
            yield pa.RecordBatch.from_pylist(out, schema=to_arrow_schema(schema))

    return joined.select("domain", "field", "dtype", "k", "data", "dim", "level_cells", "refined").mapInArrow(run, schema)


@F.arrow_udf(T.ArrayType(T.LongType()))
def as_bits(values: pa.Array) -> pa.Array:
    """Raw double values as whole numbers of the same bits."""
    import numpy as np

    return pa.array([None if b is None else np.frombuffer(b, "<i8") for b in values.to_pylist()], pa.list_(pa.int64()))
