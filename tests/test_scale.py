"""How work grows, seen in plans and numbers of jobs, and queries moved onto given tables."""

from pyspark.sql import functions as F

from meshpack import registry
from meshpack.functions import curves
from meshpack.functions.shifts import shl
from meshpack.operators import measures, prune, run52
from meshpack.operators.mesh import Params
from meshpack.operators.storage import cut
from meshpack.streaming import snapshots
from meshpack.workloads import meshes
from meshpack.workloads.base import local_of


def test_interval_form_walks_each_domain_once(spark):
    """A frame that ends with its partition is summed anew for each row; a full tree of 2^17 leaves ended no more."""
    depth = 17
    cells = spark.range(1, 1 << (depth + 1)).select(F.floor(F.log2(F.col("id") + F.lit(0.5))).cast("int").alias("level"), "id")
    cells = cells.select("level", (F.col("id") - F.expr("shiftleft(1L, level)")).alias("path"))
    local = cells.select(F.lit(0).alias("domain"), "level", "path", (F.col("level") < depth).alias("refined"), (F.expr(f"shiftleft(path, {depth} - level)") != 0).alias("masked"))
    made = prune.prune_interval(local, 1, depth)
    assert "RowFrame, 1, unboundedfollowing" not in made._jdf.queryExecution().optimizedPlan().toString()
    got = {(r.level, r.path): r.refined for r in made.collect()}
    want = {(0, 0): True} | {(level, k): k == 0 and level < depth for level in range(1, depth + 1) for k in (0, 1)}
    assert got == want


def test_windows_of_a_batch_are_a_forest(spark):
    """Trees of several windows made in one pass are those of each window alone."""
    rows = spark.read.parquet("/root/testdata/sf0.001/events.parquet").where("ts < timestamp_ntz'2024-01-04 00:00:00'")
    for p in (Params(level_max=5, threshold=1), Params(level_max=4, threshold=1, curve="hilbert", align="coarse"), Params(level_max=4, level_min=0, threshold=12, curve="hilbert")):
        counts = cut(snapshots.cell_counts(rows.withColumn("at", F.to_timestamp(F.col("ts").cast("string"))), p=p, users=1000))
        days = sorted(r[0] for r in counts.select(F.unix_micros("w.start")).distinct().collect())
        assert len(days) == 3
        root = F.array_position(F.array(*map(F.lit, days)), F.unix_micros("w.start")) - 1
        forest = snapshots.snapshot_trees(counts.select(shl(root, 3 * p.level_max).bitwiseOR(F.col("path")).alias("path"), "n", "sv", "sp"), 3, p, 3)
        inner = F.col("path").bitwiseAND(shl(F.lit(1).cast("long"), F.col("level") * 3) - 1)
        got = sorted(map(tuple, forest.withColumn("path", inner).collect()))
        want = []
        for i, day in enumerate(days):
            alone = snapshots.snapshot_trees(counts.where(F.unix_micros("w.start") == day).select("path", "n", "sv", "sp"), 3, p)
            want += [(r[0] + 3 * i, *r[1:]) for r in alone.collect()]
        assert got == sorted(want)


SF = "/root/testdata/sf0.001"


def test_root_limits_of_a_table(spark):
    q = registry.queries()["op_root_limits"](spark, SF)
    got = {(r.dim, r.width): (r.most_level, r["keys"]) for r in q.collect()}
    assert [p.rsplit("/", 1)[1] for p in q.inputFiles()] == ["lineitem.parquet"]
    keys = [r[0] for r in spark.read.parquet(f"{SF}/lineitem.parquet").select("l_orderkey").collect()]
    assert all(level == curves.max_root_level(dim, width) for (dim, width), (level, _) in got.items())
    assert {(3, 32), (2, 64)} < set(got) and sum(n for (dim, _), (_, n) in got.items() if dim == 2) == 3 * len(keys)
    assert got[2, 9][1] == sum(128 <= k < 256 for k in keys)


def test_ceilings_of_a_table(spark):
    q = registry.queries()["w_ceiling"](spark, SF)
    assert {p.rsplit("/", 1)[1] for p in q.inputFiles()} == {"orders.parquet"}
    for r in q.collect():  # some packs are full
        assert r.ceiling == measures.ceiling_ratio(r.width, r.dim, r.k) and r.exponent_line == measures.exponent_line(r.width, r.dim, r.k)
        assert 0 < r.ratio <= r.ceiling


def test_recap_of_plane_meshes(spark):
    got = {r.snapshot: r for r in registry.queries()["w_published_recap"](spark, SF).collect()}
    assert set(got) == {"orders", "cust"}
    local = local_of(spark, SF, "cust", Params())
    assert got["cust"].removed == 100 * (1 - float(prune.prune(local, 2).count()) / float(local.count()))


def test_run_codes_of_a_table(spark):
    q = registry.queries()["w_run52_example"](spark, SF)
    assert {p.rsplit("/", 1)[1] for p in q.inputFiles()} == {"orders.parquet"}
    price = {r.o_orderkey: round(r.o_totalprice * 100) for r in spark.read.parquet(f"{SF}/orders.parquet").collect()}
    back = lambda h: (lambda b: sum((x - 11) * 52**j for j, x in enumerate(reversed(b[1:] if len(b) > 1 else b))))(bytes.fromhex(h))
    assert {r.o_orderkey: back(r.cents_code) for r in q.collect()} == price and all(back(r.key_code) == r.o_orderkey for r in q.collect())
    for n, h in ((1, "0C"), (51, "3E"), (52, "020C0B"), (2703, "023E3E"), (2704, "030C0B0B"), (2904, "030C0E37"), (52**7 - 1, "07" + "3E" * 7)):
        assert spark.range(1).select(run52.run_hex(F.lit(n).cast("long"))).first()[0] == h


def test_drawn_trees(spark):
    """The worked example, and the arrays of a table's mesh."""
    example = meshes.tree_example(spark)
    for local, want in ((example, meshes.TREE), (prune.prune(example, 2), meshes.AFTER)):
        r = meshes.drawn("", local).first()
        assert (r.refined, r.masked, r.cells) == (want["refined"], want["masked"], len(want["refined"]))
    got = registry.queries()["w_tree_example"](spark, SF).collect()
    assert sorted((r.stage, r.domain) for r in got) == [(s, d) for s in ("after", "before") for d in range(4)]
    assert all(len(r.refined) == len(r.masked) == r.cells == 1 + 4 * r.refined.count("1") for r in got)
