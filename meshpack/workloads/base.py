"""The registry that workloads enter themselves in, and steps that many of them share."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession

from ..operators import domains, mesh, prune
from ..operators.mesh import Params
from ..operators.storage import cut
from ..sources.tables import MESHES

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}

#: The three snapshots' stand-ins: turbulent zoom, small zoom, homogeneous.
SNAPSHOTS = ("events", "emb", "line")


def query(name: str, sql: str | None = None):
    def enter(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return enter


def spec_of(name: str):
    return MESHES[name]


def domains_of(name: str, p: Params = Params()) -> int:
    return p.domains or MESHES[name].domains


def cells_of(spark: SparkSession, sf_dir: str, name: str, p: Params = Params()) -> DataFrame:
    """Global cells, stored: the split reads them more than once."""
    return cut(mesh.build_mesh(spark, sf_dir, name, p))


def local_of(spark: SparkSession, sf_dir: str, name: str, p: Params = Params(), cells: DataFrame | None = None) -> DataFrame:
    """Threaded trees, partitioned by domain and stored.  Larger tables make more domains than the
    catalogue names, so that none grows beyond what a task can pack."""
    cells = cells_of(spark, sf_dir, name, p) if cells is None else cells
    n = domains.domains_for(cells.count(), domains_of(name, p))
    return domains.stored(domains.thread_trees(cells, MESHES[name].dim, p, n), n)


def pruned_of(spark: SparkSession, sf_dir: str, name: str, p: Params = Params()) -> DataFrame:
    return cut(prune.prune(local_of(spark, sf_dir, name, p), MESHES[name].dim))


def with_params(p: Params = Params(), **change) -> Params:
    return replace(p, **change)


def rows(spark: SparkSession, data: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)
