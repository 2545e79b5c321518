"""Given tables and the catalogue of meshes that are built from them.

Axes, weights and fields are integer expressions, so that Spark and any SQL engine agree to
the last bit: a field is a quotient of two integers.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


@dataclass(frozen=True)
class Axis:
    """Integer coordinate ``spark`` (or ``sql`` for DuckDB) in the box [lo, hi)."""

    spark: str
    sql: str
    lo: int
    hi: int | None  # None: one more than the largest value


@dataclass(frozen=True)
class MeshSpec:
    """How a point table becomes a mesh: axes, integer weights, and fields made of their sums."""

    name: str
    table: str
    axes: tuple[Axis, ...]
    signed: tuple[str, str]
    positive: tuple[str, str]
    v: tuple[int, int]  # offset and scale: (sum - offset * n) / (scale * n)
    p_scale: int
    domains: int = 16
    labels: tuple[str, ...] = field(default=("rho", "v", "p", "smooth"))

    @property
    def dim(self) -> int:
        return len(self.axes)


def _same(e: str, lo: int, hi: int | None) -> Axis:
    return Axis(e, e, lo, hi)


def _cents(c: str) -> tuple[str, str]:
    return (f"cast(round({c} * 100) as bigint)",) * 2


_DAY = ("datediff(cast({c} as date), date'1995-01-01')", "date_diff('day', date '1995-01-01', {c}::DATE)")
_EVENT_TIME = Axis("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', ts)", "epoch_us(ts)", 1704067200000000, 1706659200000000)
_micro = lambda k: (f"cast(round(cast(element_at(embedding, {k}) as double) * 1000000) as bigint)", f"cast(round(embedding[{k}]::DOUBLE * 1000000) as bigint)")

MESHES = {
    m.name: m
    for m in (
        MeshSpec("events", "events", (_EVENT_TIME, _same("user_id", 0, None), _same(_cents("value")[0], 0, 50_000)), _cents("value"), _cents("value"), (5000, 100), 100),
        MeshSpec(
            "line", "lineitem",
            (_same("cast(l_quantity as bigint)", 1, 51), _same(_cents("l_extendedprice")[0], 0, 10_500_000), Axis(_DAY[0].format(c="l_shipdate"), _DAY[1].format(c="l_shipdate"), 0, 2560)),
            _cents("l_discount"), _cents("l_extendedprice"), (5, 100), 100,
        ),
        MeshSpec("emb", "embeddings", tuple(Axis(*_micro(k), -500_000, 500_000) for k in (1, 2, 3)), _micro(4), tuple(f"abs({e})" for e in _micro(5)), (0, 1_000_000), 1_000_000, domains=4),
        MeshSpec("orders", "orders", (Axis(_DAY[0].format(c="o_orderdate"), _DAY[1].format(c="o_orderdate"), 0, 2560), _same(_cents("o_totalprice")[0], 0, 50_000_000)), _cents("o_totalprice"), _cents("o_totalprice"), (25_000_000, 100), 100),
        MeshSpec("cust", "customer", (_same("cast(c_nationkey as bigint)", 0, 25), _same("cast(round(c_acctbal * 100) as bigint) + 100000", 0, 1_100_000)), _cents("c_acctbal"), ("cast(round(c_acctbal * 100) as bigint) + 100000",) * 2, (0, 100), 100),
        MeshSpec("supp", "supplier", (_same("cast(s_nationkey as bigint)", 0, 25), _same("cast(round(s_acctbal * 100) as bigint) + 100000", 0, 1_100_000)), _cents("s_acctbal"), ("cast(round(s_acctbal * 100) as bigint) + 100000",) * 2, (0, 100), 100, domains=4),
        MeshSpec("part", "part", (_same("cast(p_size as bigint)", 0, 51), _same(_cents("p_retailprice")[0], 0, 250_000)), _cents("p_retailprice"), _cents("p_retailprice"), (100_000, 100), 100),
        MeshSpec("docs", "documents", (_same("n_chars", 0, 131_072),), ("n_chars", "n_chars"), ("n_chars", "n_chars"), (2000, 1), 1),
    )
}


def points(spark: SparkSession, sf_dir: str, mesh: str, max_level: int) -> DataFrame:
    """q0, q1, ... within the grid of the finest level, and the weights sv and sp."""
    spec = MESHES[mesh]
    rows = table(spark, sf_dir, spec.table)
    return grid_points(rows, spec, max_level)


def grid_points(rows: DataFrame, spec: MeshSpec, max_level: int, keep: tuple[str, ...] = ()) -> DataFrame:
    cols = []
    for a, axis in enumerate(spec.axes):
        hi = axis.hi
        if hi is None:
            hi = int(rows.agg(F.max(F.expr(axis.spark))).first()[0] or 0) + 1  # one number
        x = F.expr(axis.spark).cast("long")
        q = F.expr("1").cast("long") * F.least(F.lit((1 << max_level) - 1), F.greatest(F.lit(0), F.expr(f"(({axis.spark}) - {axis.lo}L) * {1 << max_level}L div {hi - axis.lo}L")))
        cols.append(F.when(x.isNotNull(), q).alias(f"q{a}"))
    used = rows.select(*keep, *cols, F.expr(spec.signed[0]).cast("long").alias("sv"), F.expr(spec.positive[0]).cast("long").alias("sp"))
    return used.where(" and ".join(f"q{a} is not null" for a in range(spec.dim)))
