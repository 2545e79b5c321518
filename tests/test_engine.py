"""Operators on Spark: against DuckDB on the smallest tables, and properties that hold by design."""

import math
import random
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from meshpack import registry
from meshpack.functions import bits, curves
from meshpack.operators import analysis, baselines, domains, layout, measures, mesh, prune, pxor, run52
from meshpack.operators.mesh import Params
from meshpack.operators.storage import cut
from meshpack.plans import pipeline
from meshpack.streaming import snapshots
from meshpack.workloads.base import cells_of, local_of

SF = os.environ.get("TEST_SF_DIR", "/root/testdata/sf0.001")
NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
HELD = [
    "op_grid_points", "op_morton3", "op_hilbert2", "op_mesh_leaves", "op_mesh_balance", "op_domain_split_hilbert", "op_thread_trees", "op_prune_closed", "op_prune_sweep",
    "op_prune_interval", "op_prune_arrays", "w_prune_events", "w_prune_cust", "op_run52_encode_grid", "op_bit_at", "w_run52_labels", "w_run52_example", "w_tree_example", "op_pxor_bits_2d",
    "op_pxor_shift", "w_nlz_summary", "w_published_recap", "w_ceiling", "op_particle_bind_asof", "op_compress_roundtrip", "op_packed_source", "op_udtf_decode", "op_merge_domains",
    "op_rollup_report", "op_tumbling", "op_session", "w_stream_snapshots", "op_join_range", "op_udf_run52",
]


@pytest.fixture(scope="session")
def duck():
    c = duckdb.connect()
    for n in NAMES:
        c.sql(f"create view {n} as select * from '{SF}/{n}.parquet'")
    return c


def shown(df):
    df = df[sorted(df.columns)]
    return sorted(tuple("null" if x is None or x != x else str(x) for x in row) for row in df.itertuples(index=False))


@pytest.mark.parametrize("name", HELD)
def test_against_sql(spark, duck, name):
    got = registry.queries()[name](spark, SF).toPandas()
    assert shown(got) == shown(duck.sql(registry.oracle_sql()[name]).df())


def test_every_query_has_sql_or_is_listed():
    rows_only = {"w_bool_codecs", "w_float_codecs", "w_speeds", "w_speeds_run52", "w_speeds_pxor", "w_speeds_header", "w_prune_times", "w_stream_encode", "w_parquet_volume"}
    assert set(registry.queries()) - set(registry.oracle_sql()) == rows_only


def test_float_views(spark):
    values = [0.0, -0.0, 1.0, -1.0, 5e-324, 2.2250738585072014e-308, 2.225073858507201e-308, 1.7976931348623157e308, float("inf"), -float("inf"), float("nan"), 0.1, -3.5e-310, math.pi]
    values += np.random.default_rng(0).normal(size=200).tolist() + (10.0 ** np.random.default_rng(1).uniform(-300, 300, 200)).tolist()
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, v double")
    for r in df.select("v", bits.f64_bits(F.col("v")).alias("a"), bits.f64_view("v").alias("b"), bits.f32_bits(F.col("v")).alias("c"), bits.f64_from_bits(bits.f64_view("v")).alias("d")).collect():
        assert r.a == r.b, r
        with np.errstate(over="ignore", under="ignore"):
            assert math.isnan(r.v) or r.c == int(np.float32(r.v).view(np.uint32)), r
        assert r.d == r.v or math.isnan(r.v)


@pytest.mark.parametrize("dim, bits_", [(2, 4), (3, 3)])
def test_hilbert_is_a_path(spark, dim, bits_):
    side = 1 << bits_
    df = spark.range(side**dim).select(*(F.expr(f"(id div {side**a}) % {side}").alias(f"q{a}") for a in range(dim)))
    cols = [F.col(f"q{a}") for a in range(dim)]
    rows = df.select(*cols, curves.hilbert_key(cols, bits_).alias("h"), curves.morton_encode(cols).alias("m")).orderBy("h").collect()
    assert [r.h for r in rows] == list(range(side**dim))
    assert all(sum(abs(a[i] - b[i]) for i in range(dim)) == 1 for a, b in zip(rows, rows[1:]))
    assert sorted(r.m for r in rows) == list(range(side**dim))


def test_key_too_wide(spark):
    with pytest.raises(ValueError):
        curves.morton_encode([F.lit(1)] * 3, 22)


def five(df):
    return sorted(tuple(r) for r in df.select("domain", "level", "path", "refined", "masked").collect())


def test_pruned_tree_does_not_depend_on_the_halo(spark):
    cells = cells_of(spark, SF, "events")
    made = [five(prune.prune(local_of(spark, SF, "events", Params(halo=h), cells), 3)) for h in (0, 1, 2)]
    assert made[0] == made[1] == made[2]


def test_pruning_keeps_what_is_owned_and_nothing_twice(spark):
    cells = cells_of(spark, SF, "events")
    local = local_of(spark, SF, "events", Params(), cells)
    after = cut(prune.prune(local, 3))
    assert layout.validate(local, 3).isEmpty() and layout.validate(after, 3).isEmpty()
    leaves = analysis.leaves(after).select("level", "path")
    assert leaves.count() == leaves.distinct().count() == cells.where("not refined").count()
    assert local.where("not masked").select("domain", "level", "path", "rho").exceptAll(after.select("domain", "level", "path", "rho")).isEmpty()
    assert five(prune.prune(after, 3)) == five(after)


def test_one_domain_has_nothing_to_prune(spark):
    local = local_of(spark, SF, "cust", Params(domains=1))
    r = measures.pruning_report(local, prune.prune(local, 2)).first()
    assert r.cells_before == r.cells_after and r.global_frac == 0


def test_coarse_split_and_forest_leave_no_redundancy(spark):
    after = cut(prune.prune(local_of(spark, SF, "line", Params(align="coarse", domains=8)), 3))
    assert measures.redundancy(layout.to_forest(after, 3, 2)).first().redundancy == 1
    back = layout.from_forest(layout.to_forest(after, 3, 2), 3, 2)  # from the forest alone
    assert five(back) == five(after)


def test_merging_all_domains_gives_the_global_tree(spark):
    cells = cells_of(spark, SF, "events")
    after = cut(prune.prune(local_of(spark, SF, "events", Params(), cells), 3))
    one = domains.merge(after.select("domain", "level", "path", "refined", "masked", "rho"), [(i, 0) for i in range(16)])
    assert sorted(map(tuple, one.select("level", "path", "refined", "rho").collect())) == sorted(map(tuple, cells.select("level", "path", "refined", "rho").collect()))


def test_many_domains_search_an_array(spark):
    keys = list(range(0, 3000, 7))
    df = spark.range(3010).select(F.col("id").alias("key"))
    for bounds in (keys[:20], keys):
        got = {r.key: r.o for r in df.select("key", domains.owner_of(F.col("key"), bounds).alias("o")).collect()}
        assert all(o == sum(b <= k for b in bounds) for k, o in got.items())


def test_empty_and_tiny_meshes(spark):
    schema = "q0 long, q1 long, sv long, sp long"
    for data in ([], [(3, 3, 1, 1)], [(3, 3, 1, 1)] * 50):
        pts = spark.createDataFrame(data, schema)
        for p in (Params(level_max=3, level_min=2), Params(level_max=3, level_min=0, threshold=0), Params(level_max=2, level_min=2)):
            cells = cut(mesh.build_mesh(spark, SF, "cust", p, pts))
            assert cells.agg(F.sum(F.when(~F.col("refined"), F.col("n")))).first()[0] == len(data)
            local = domains.thread_trees(cells, 2, p, 3)
            assert layout.validate(local, 2).isEmpty()
            assert five(prune.prune(local, 2)) == five(prune.prune_sweep(local, 2)) == five(prune.prune_interval(local, 2, p.level_max))


def test_stream_encodes_every_closed_day(spark, tmp_path):
    """Days in the middle of the month, at the batch form's depth and box; the last one is still open."""
    rows = spark.read.parquet(f"{SF}/events.parquet").where("ts >= timestamp_ntz'2024-01-10 00:00:00' and ts < timestamp_ntz'2024-01-13 00:00:00'")
    rows.write.parquet(f"{tmp_path}/events.parquet")
    got = registry.queries()["w_stream_encode"](spark, str(tmp_path)).where("field = 'rho'")
    days = {str(r.snapshot)[:10]: r.cells for r in got.groupBy("snapshot").agg((F.sum("raw_bytes") / 8).cast("long").alias("cells")).collect()}
    assert set(days) == {"2024-01-10", "2024-01-11"}
    users = rows.agg(F.max("user_id")).first()[0] + 1
    counts = cut(snapshots.cell_counts(rows.withColumn("at", F.to_timestamp(F.col("ts").cast("string"))), users=users))
    n = {str(r.d): r.n for r in counts.groupBy(F.to_date("w.start").alias("d")).agg(F.sum("n").alias("n")).collect()}
    assert n == {str(r.d): r.n for r in rows.groupBy(F.to_date("ts").alias("d")).agg(F.count("*").alias("n")).collect()}
    for day in days:
        some = counts.where(F.to_date("w.start") == F.lit(day).cast("date")).drop("w")
        trees = snapshots.snapshot_trees(some, 4)
        assert days[day] == trees.count() and trees.where("not refined and not masked").agg(F.sum("n")).first()[0] == n[day]


def test_uniform_grids_are_dense(spark):
    """At a level that the mesh refines further, refined cells give their own values."""
    cells = cells_of(spark, SF, "cust", Params(threshold=1))
    level = 2
    assert not cells.where(F.col("refined") & (F.col("level") == level)).isEmpty()
    got = {r.path: r.p for r in baselines.resample(cells, 2, level, ["p"]).collect()}
    own = {(r.level, r.path): (r.refined, r.p) for r in cells.collect()}
    assert set(got) == set(range(1 << (2 * level)))
    for path, value in got.items():
        up = next(k for k in range(level, -1, -1) if (k, path >> (2 * (level - k))) in own)
        assert value == own[up, path >> (2 * (level - up))][1]


def test_missing_coarse_values(spark):
    with pytest.raises(pxor.MissingCoarseValues):
        pxor.predict(local_of(spark, SF, "cust", Params()), 2, "nothing")


def test_long_runs_raise(spark):
    with pytest.raises(Exception, match="longer than"):
        spark.range(1).select(run52.run_hex(F.lit(52**7).cast("long")).alias("h")).collect()


def test_volumes_and_fields_survive_the_chain(spark):
    local = local_of(spark, SF, "cust", Params(domains=4))
    fields = {"v": "float64", "p": "float32"}
    packed = cut(pipeline.compress(local, 2, fields))
    back = pipeline.decompress(packed, fields)
    direct = prune.prune(local, 2).select("domain", "level", "path", "refined", "masked", "v", F.col("p").cast("float").alias("p"))
    assert measures.roundtrip_mismatches(back, direct) == 0
    assert pipeline.volumes(packed, fields).first().n_cells == direct.count()


def test_particles_bind_alike(spark):
    cells = cells_of(spark, SF, "orders")
    at = spark.range(500).select((F.col("id") * 131 % 65536).alias("key"), F.col("id").alias("who"))
    a = analysis.bind(at, cells, 2, 8).select("who", "level", "path").collect()
    b = analysis.bind_asof(at, cells, 2, 8).select("who", "level", "path").collect()
    assert sorted(a) == sorted(b) and len(a) == 500


def test_prune_needs_no_python_and_scans_prune_levels(spark, tmp_path):
    local = local_of(spark, SF, "events", Params())
    plan = prune.prune(local, 3)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan
    local.write.partitionBy("level").parquet(str(tmp_path / "cells"))
    text = analysis.at_level(spark.read.parquet(str(tmp_path / "cells")), 3)._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in text and "level" in text.split("PartitionFilters: [")[1].split("]")[0]


def test_registry_loads_without_a_session():
    import subprocess
    import sys

    code = "import __spark_entry__ as e; assert len(e.queries()) > 100 and len(e.oracle_sql()) > 100"
    subprocess.run([sys.executable, "-c", code], check=True, cwd=os.path.dirname(os.path.dirname(__file__)))


def test_boundaries_of_very_many_domains(spark):
    """12 800 domains: the first keys by rank, from a table of many partitions, and owners by search."""
    n, total = 12_800, 60_000
    keys = sorted(random.Random(3).sample(range(1 << 40), total))
    leaves = spark.createDataFrame([(k,) for k in random.Random(4).sample(keys, total)], "key long").repartition(9)
    bounds = domains.leaf_boundaries(leaves, n)
    rank = {}
    for r, k in enumerate(keys):
        rank.setdefault(r * n // total, k)
    assert bounds == [rank[d] for d in range(1, n)]
    owned = leaves.select("key", domains.owner_of(F.col("key"), bounds).alias("d"))
    place = {k: r * n // total for r, k in enumerate(keys)}
    assert all(place[r.key] == r.d for r in owned.collect())


@pytest.mark.parametrize("n, total", [(1, 5), (4, 0), (7, 3), (16, 16), (5, 100)])
def test_boundaries_of_few_leaves(spark, n, total):
    leaves = spark.createDataFrame([(3 * r,) for r in range(total)], "key long")
    bounds = domains.leaf_boundaries(leaves, n)
    assert len(bounds) == n - 1
    owned = leaves.select("key", domains.owner_of(F.col("key"), bounds).alias("d"))
    assert all(r.d == (r.key // 3) * n // total for r in owned.collect())


def test_domains_grow_with_cells():
    assert domains.domains_for(100, 16) == 16 and domains.domains_for(160_000_001, 16) == 17 and domains.domains_for(0) == 1


@pytest.mark.parametrize("curve, l0", [("hilbert", 2), ("morton", 1), ("hilbert", 0)])
def test_trees_come_back_from_the_forest_alone(spark, curve, l0):
    after = cut(prune.prune(local_of(spark, SF, "emb", Params(curve=curve)), 3))
    assert five(layout.from_forest(layout.to_forest(after, 3, l0), 3, l0, curve)) == five(after)


def test_null_coarse_values_raise(spark):
    local = cut(local_of(spark, SF, "emb", Params()))
    broken = local.withColumn("rho", F.when(~F.col("refined"), F.col("rho")))
    with pytest.raises(Exception, match="no coarse value of rho"):
        pxor.encode(broken, 3, {"rho": "float64"}).collect()
    with pytest.raises(pxor.MissingCoarseValues):
        pxor.encode(local.drop("rho"), 3, {"rho": "float64"})


def test_shifted_bits_come_back(spark):
    rows = spark.createDataFrame([(x,) for x in (0, 1, -1, 2**63 - 1, -(2**63), 0x0123456789ABCDEF)], "b long")
    for by in (1, 2**32, 2**63 - 1, -5, 0x123456789ABCDEF1):
        got = rows.select("b", pxor.shift_bits(F.col("b"), by).alias("m")).withColumn("back", pxor.shift_bits(F.col("m"), -by)).collect()
        assert all((r.m - r.b - by) % 2**64 == 0 and r.back == r.b for r in got)
    small = spark.createDataFrame([(x,) for x in (0, 1, 2**32 - 1)], "b long")
    got = small.select("b", pxor.shift_bits(F.col("b"), 77, "float32").alias("m")).withColumn("back", pxor.shift_bits(F.col("m"), -77, "float32")).collect()
    assert all(0 <= r.m < 2**32 and r.back == r.b for r in got)
