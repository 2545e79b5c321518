"""Grids, curves, meshes, domains, layout and pruning: operators and the pruning workloads."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import curves
from ..operators import domains, layout, measures, mesh, prune
from ..operators.mesh import Params
from ..operators.storage import cut
from ..sources.tables import MESHES, points, table
from . import sql
from .base import SNAPSHOTS, cells_of, domains_of, local_of, pruned_of, query, rows, with_params

P = Params()
L = P.level_max


# ---- grid and curves ---------------------------------------------------------------------------

query("op_grid_points", sql.with_(sql.points("orders", L), "SELECT q0, q1, sv, sp FROM pts"))(lambda s, d: points(s, d, "orders", L))


def _morton(name):
    dim = MESHES[name].dim
    cols = [f"q{a}" for a in range(dim)]
    text = sql.with_(sql.points(name, L), f"SELECT {', '.join(cols)}, key FROM keyed")
    return text, lambda s, d: points(s, d, name, L).select(*cols, curves.morton_encode([F.col(c) for c in cols], L).alias("key"))


for _dim, _name in ((2, "orders"), (3, "line")):
    _text, _f = _morton(_name)
    query(f"op_morton{_dim}", _text)(_f)


@query("op_morton_decode", sql.with_(sql.points("events", L), "SELECT key, q0, q1, q2 FROM keyed"))
def _(spark, sf_dir):
    key = points(spark, sf_dir, "events", L).select(curves.morton_encode([F.col(f"q{a}") for a in range(3)], L).alias("key"))
    return key.select("key", *(x.alias(f"q{a}") for a, x in enumerate(curves.morton_decode(F.col("key"), 3))))


for _dim, _name in ((2, "orders"), (3, "events")):
    _cols = [f"q{a}" for a in range(_dim)]
    _text = sql.with_(sql.points(_name, L) + sql.hilbert("keyed", "key", _dim, L), f"SELECT {', '.join(_cols)}, h::BIGINT AS hilbert FROM hk{L}")
    query(f"op_hilbert{_dim}", _text)(lambda s, d, n=_name, c=_cols: points(s, d, n, L).select(*c, curves.hilbert_key([F.col(x) for x in c], L).alias("hilbert")))


_WIDTHS = "SELECT dim::INTEGER AS dim, unnest([32, 64, 1 + length(bin(l_orderkey))])::INTEGER AS width FROM lineitem, (VALUES (2), (3)) AS t(dim) WHERE l_orderkey >= 0"


@query("op_root_limits", f"SELECT dim, width, (width // dim - CASE WHEN width = 64 AND width % dim = 0 THEN 1 ELSE 0 END)::INTEGER AS most_level, count(*) AS keys FROM ({_WIDTHS}) GROUP BY 1, 2")
def _(spark, sf_dir):
    """Deepest root level of words of 32 and 64 bits, and of words just wide enough for a key of the table."""
    keys = table(spark, sf_dir, "lineitem").where("l_orderkey >= 0")
    own = F.length(F.bin("l_orderkey")) + 1
    each = keys.select(F.explode(F.array(F.lit(32), F.lit(64), own)).alias("width")).withColumn("dim", F.explode(F.array(F.lit(2), F.lit(3))))
    return each.groupBy("dim", "width").agg(F.count("*").alias("keys")).select("dim", "width", curves.root_level("dim", "width").alias("most_level"), "keys")


# ---- mesh --------------------------------------------------------------------------------------


@query("op_mesh_counts", sql.with_(sql.mesh("events", P), "SELECT level, path, n, sv, sp FROM cnt"))
def _(spark, sf_dir):
    return mesh.counts_by_level(points(spark, sf_dir, "events", L), 3, L)


@query("op_mesh_levels", sql.with_(sql.mesh("line", P), "SELECT level, count(*) AS cells, count(*) FILTER (refined) AS refined FROM cells GROUP BY 1"))
def _(spark, sf_dir):
    return mesh.build_mesh(spark, sf_dir, "line", P).groupBy("level").agg(F.count("*").alias("cells"), F.count_if("refined").alias("refined"))


@query("op_mesh_leaves", sql.with_(sql.mesh("events", P), "SELECT level, path, n, rho, v, p, smooth FROM cells WHERE NOT refined"))
def _(spark, sf_dir):
    return mesh.build_mesh(spark, sf_dir, "events", P).where("not refined").drop("refined")


for _how in ("face", "full"):
    _p = with_params(P, balance=_how, level_max=6)
    query("op_mesh_balance" if _how == "face" else "op_mesh_balance_full", sql.with_(sql.mesh("events", _p), "SELECT level, count(*) AS cells, count(*) FILTER (refined) AS refined, sum(n)::BIGINT AS n FROM cells GROUP BY 1"))(
        lambda s, d, p=_p: mesh.build_mesh(s, d, "events", p).groupBy("level").agg(F.count("*").alias("cells"), F.count_if("refined").alias("refined"), F.sum("n").alias("n"))
    )

query("w_mesh_docs", sql.with_(sql.mesh("docs", P), "SELECT level, path, refined, n FROM cells"))(lambda s, d: mesh.build_mesh(s, d, "docs", P).select("level", "path", "refined", "n"))
for _name in ("supp", "part"):
    query(f"op_mesh_{_name}", sql.with_(sql.mesh(_name, P), "SELECT level, path, refined, n, rho, v, p, smooth FROM cells"))(lambda s, d, n=_name: mesh.build_mesh(s, d, n, P))


# ---- domains -----------------------------------------------------------------------------------


def _owned(name, p):
    dim, n = MESHES[name].dim, domains_of(name, p)

    def run(spark, sf_dir):
        cells = cells_of(spark, sf_dir, name, p)
        bounds = domains.split(cells, dim, n, p)
        return cells.where("not refined").select("level", "path", domains.owner_of(domains.curve_start(dim, p.level_max, p.curve), bounds).alias("owner"))

    return run


for _label, _p in (("leaf", P), ("coarse", with_params(P, align="coarse")), ("hilbert", with_params(P, curve="hilbert"))):
    query(f"op_domain_split_{_label}", sql.with_(sql.threads("events", 16, _p), "SELECT level, path, owner FROM lown"))(_owned("events", _p))

_LOCAL = "SELECT domain, level, path, refined, masked FROM local"
query("op_thread_trees", sql.with_(sql.threads("events", 16, P), _LOCAL))(lambda s, d: local_of(s, d, "events", P).select("domain", "level", "path", "refined", "masked"))
query("op_thread_trees_2d", sql.with_(sql.threads("orders", 16, P), _LOCAL))(lambda s, d: local_of(s, d, "orders", P).select("domain", "level", "path", "refined", "masked"))


@query("op_ownership", sql.with_(sql.threads("events", 16, P), "SELECT level, path, owner FROM own"))
def _(spark, sf_dir):
    cells = cells_of(spark, sf_dir, "events", P)
    bounds = domains.split(cells, 3, 16, P)
    return cells.select("level", "path", domains.owner_of(domains.curve_start(3, L, "morton"), bounds).alias("owner"))


# ---- layout ------------------------------------------------------------------------------------


@query("op_layout_arrays", sql.with_(sql.threads("events", 16, P), "SELECT domain, count(*) AS n_cells, string_agg(refined::INTEGER::VARCHAR, '' ORDER BY level, path) AS refined, string_agg(masked::INTEGER::VARCHAR, '' ORDER BY level, path) AS masked FROM local GROUP BY 1"))
def _(spark, sf_dir):
    packed = layout.to_arrays(local_of(spark, sf_dir, "events", P), 3)
    # "00" and "01" of each byte, without their first digits
    digits = lambda c: F.regexp_replace(F.hex(c), "0([01])", "$1")
    return packed.select("domain", "n_cells", digits(F.col("refined")).alias("refined"), digits(F.col("masked")).alias("masked"))


_FIELDS = {"rho": "float64", "v": "float64", "p": "float32"}


@query("op_layout_roundtrip", sql.with_(sql.threads("events", 16, P), "SELECT domain, level, path, refined, masked, rho, v FROM local"))
def _(spark, sf_dir):
    back = layout.to_cells(layout.to_arrays(local_of(spark, sf_dir, "events", P), 3, _FIELDS), _FIELDS)
    return back.select("domain", "level", "path", "refined", "masked", "rho", "v")


@query("op_layout_validate", sql.with_(sql.threads("emb", 4, P), "SELECT domain, level, 0::BIGINT AS cells, 0::BIGINT AS expected FROM local WHERE false"))
def _(spark, sf_dir):
    return layout.validate(local_of(spark, sf_dir, "emb", P), 3)


@query("op_level_counts", sql.with_(sql.threads("emb", 4, P), "SELECT domain, level, count(*) AS cells, count(*) FILTER (refined) AS refined, count(*) FILTER (masked) AS masked FROM local GROUP BY 1, 2"))
def _(spark, sf_dir):
    return layout.level_counts(local_of(spark, sf_dir, "emb", P))


@query("op_metadata", sql.with_(sql.threads("emb", 4, P), "SELECT domain, count(*) AS n_cells, count(*) FILTER (refined) AS n_grids, (max(level) - min(level) + 1)::INTEGER AS n_levels, '{\"box\":\"1\",\"unit\":\"none\"}' AS meta FROM local GROUP BY 1"))
def _(spark, sf_dir):
    return layout.describe(local_of(spark, sf_dir, "emb", P), box="1", unit="none").withColumn("meta", F.to_json("meta"))


_UP = "SELECT (c.level - l)::INTEGER AS level, c.path >> (3 * l) AS path, {e} FROM (SELECT c.*, coalesce(t.sp, 0) AS sp FROM cells c LEFT JOIN cnt t ON t.level = c.level AND t.path = c.path) c, levels WHERE NOT refined AND l <= c.level GROUP BY 1, 2"


def _upsampled(spark, sf_dir):
    counts = cut(mesh.counts_by_level(points(spark, sf_dir, "line", L), 3, L))
    cells = mesh.tree_of(mesh.refined_cells(counts, 3, P), 3).where("not refined").join(counts, ["level", "path"], "left").na.fill(0)
    return layout.upsample(cells, 3, {"n": "n", "sp": "sp"})


query("op_upsample_sum", sql.with_(sql.mesh("line", P), _UP.format(e="sum(n)::BIGINT AS n, sum(sp)::BIGINT AS sp")))(_upsampled)
query("op_upsample_mean", sql.with_(sql.mesh("line", P), "SELECT level, path, sp::DOUBLE / n::DOUBLE AS mean FROM (" + _UP.format(e="sum(n)::BIGINT AS n, sum(sp)::BIGINT AS sp") + ") WHERE n > 0"))(
    lambda s, d: _upsampled(s, d).where("n > 0").select("level", "path", (F.col("sp").cast("double") / F.col("n").cast("double")).alias("mean"))
)


# ---- pruning -----------------------------------------------------------------------------------

_KEPT = "SELECT domain, level, path, refined, masked FROM pruned"
_five = lambda df: df.select("domain", "level", "path", "refined", "masked")
query("op_prune_closed", sql.with_(sql.pruned("events", 16, P), _KEPT))(lambda s, d: _five(prune.prune(local_of(s, d, "events", P), 3)))
query("op_prune_sweep", sql.with_(sql.pruned("events", 16, P), _KEPT))(lambda s, d: _five(prune.prune_sweep(local_of(s, d, "events", P), 3)))
query("op_prune_interval", sql.with_(sql.pruned("events", 16, P), _KEPT))(lambda s, d: _five(prune.prune_interval(local_of(s, d, "events", P), 3, L)))
query("op_prune_2d", sql.with_(sql.pruned("orders", 16, P), _KEPT))(lambda s, d: _five(prune.prune(local_of(s, d, "orders", P), 2)))
query("op_prune_arrays", sql.with_(sql.pruned("events", 16, P), _KEPT))(lambda s, d: _five(layout.to_cells(prune.prune_arrays(layout.to_arrays(local_of(s, d, "events", P), 3)))))
query("op_working_mask", sql.with_(sql.pruned("events", 16, P), "SELECT c.domain, c.level, c.path, c.masked AND v.path IS NULL AS work FROM local c LEFT JOIN live v ON v.domain = c.domain AND v.level = c.level AND v.path = c.path"))(
    lambda s, d: prune.working_mask(local_of(s, d, "events", P), 3).select("domain", "level", "path", "work")
)

_REPORT = """SELECT {lead}count(*) AS domains, sum(a)::BIGINT AS cells_before, sum(b)::BIGINT AS cells_after, min((a - b)::DOUBLE / a::DOUBLE) AS min_frac,
max((a - b)::DOUBLE / a::DOUBLE) AS max_frac, (sum(a) - sum(b))::BIGINT::DOUBLE / sum(a)::BIGINT::DOUBLE AS global_frac
FROM (SELECT domain, count(*) AS a FROM local GROUP BY 1) JOIN (SELECT domain, count(*) AS b FROM pruned GROUP BY 1) USING (domain)"""


def prune_report(spark, sf_dir, name, p, cells=None):
    local = local_of(spark, sf_dir, name, p, cells)
    return measures.pruning_report(local, prune.prune(local, MESHES[name].dim))


for _name in ("events", "emb", "line", "orders", "cust"):
    _n = domains_of(_name)
    query(f"w_prune_{_name}", sql.with_(sql.pruned(_name, _n, P), _REPORT.format(lead=f"'{_name}' AS mesh, ")))(lambda s, d, n=_name: prune_report(s, d, n, P).select(F.lit(n).alias("mesh"), "*"))

#: Number of domains, curve, halo, balance and depth; each changes one thing.
SWEEP = [(4, "morton", 1, None, 8), (16, "morton", 1, None, 8), (64, "morton", 1, None, 8), (16, "hilbert", 1, None, 8), (16, "morton", 0, None, 8), (16, "morton", 2, None, 8), (16, "morton", 1, "face", 8), (16, "morton", 1, None, 6)]


def _sweep_params(c):
    n, curve, halo, balance, level = c
    return with_params(P, domains=n, curve=curve, halo=halo, balance=balance, level_max=level)


def _lead(c):
    n, curve, halo, balance, level = c
    return f"'{n}/{curve}/{halo}/{balance or 'none'}/{level}' AS setting, "


def _each(c, name):
    return f"({sql.with_(sql.pruned(name, c[0], _sweep_params(c)), _REPORT.format(lead=_lead(c)))})"


for _name in ("events", "line"):

    def _sweep(spark, sf_dir, name=_name):
        out, built = None, {}
        for c in SWEEP:
            p = _sweep_params(c)
            # how a mesh is dealt out changes nothing of its cells: settings of one depth and balance share them
            if (p.balance, p.level_max) not in built:
                built[p.balance, p.level_max] = cells_of(spark, sf_dir, name, p)
            one = prune_report(spark, sf_dir, name, p, built[p.balance, p.level_max]).select(F.expr(_lead(c).rstrip(", ")), "*")
            out = one if out is None else out.unionByName(one)
        return out

    query(f"w_prune_sweep_{_name}" if _name != "events" else "w_prune_sweep", " UNION ALL ".join(f"SELECT * FROM {_each(c, _name)}" for c in SWEEP))(_sweep)


@query(
    "w_prune_alignment",
    " UNION ALL ".join(
        f"SELECT * FROM ({sql.with_(sql.pruned('line', 16, with_params(P, align=a)), f'''SELECT '{a}' AS align, stage, count(*) AS local_cells, count(DISTINCT (level, path)) AS global_cells, count(*)::DOUBLE / count(DISTINCT (level, path))::DOUBLE AS redundancy FROM (SELECT 'before' AS stage, level, path FROM local UNION ALL SELECT 'after', level, path FROM pruned UNION ALL SELECT 'forest', level, path FROM pruned WHERE level >= 2 AND NOT (level = 2 AND masked AND NOT refined)) GROUP BY stage''')})"
        for a in ("leaf", "coarse")
    ),
)
def _(spark, sf_dir):
    out = None
    for a in ("leaf", "coarse"):
        local = local_of(spark, sf_dir, "line", with_params(P, align=a))
        after = cut(prune.prune(local, 3))
        for stage, df in (("before", local), ("after", after), ("forest", layout.to_forest(after, 3, 2))):
            one = measures.redundancy(df).select(F.lit(a).alias("align"), F.lit(stage).alias("stage"), "*")
            out = one if out is None else out.unionByName(one)
    return out


# ---- forest, merging ---------------------------------------------------------------------------

_FOREST = "SELECT domain, level, path, refined, masked FROM pruned WHERE level >= 2 AND NOT (level = 2 AND masked AND NOT refined)"
query("op_forest", sql.with_(sql.pruned("line", 16, P), _FOREST))(lambda s, d: _five(layout.to_forest(pruned_of(s, d, "line", P), 3, 2)))
query("w_forest_restore", sql.with_(sql.pruned("line", 16, P), "SELECT domain, level, path, refined, masked FROM pruned"))(
    lambda s, d: layout.from_forest(layout.to_forest(pruned_of(s, d, "line", P), 3, 2), 3, 2)
)


@query("w_prune_times")
def _(spark, sf_dir):
    """Seconds of pruning by domain, and how they go with the number of coarse cells and their mean place."""
    out = []
    for m in SNAPSHOTS:
        times = prune.prune_times(cut(layout.to_arrays(local_of(spark, sf_dir, m, P), MESHES[m].dim)))
        ns = F.col("ns").cast("double")
        out.append(times.agg(
            F.lit(m).alias("mesh"), F.count("*").alias("domains"), (F.min("ns") / 1000).alias("least_us"), (F.max("ns") / 1000).alias("most_us"), (F.sum("n_cells") * 1000.0 / F.sum("ns")).alias("million_cells_s"),
            F.corr(ns, F.col("coarse").cast("double")).alias("corr_coarse"), F.corr(ns, "place").alias("corr_place"),
        ))
    return out[0].unionByName(out[1]).unionByName(out[2])


query("w_forest", sql.with_(sql.pruned("line", 16, P), f"SELECT domain, count(*) FILTER (level = 2) AS roots, count(*) AS cells, 4 * count(*) FILTER (level = 2) AS morton_bytes, 12 * count(*) FILTER (level = 2) AS ijk_bytes FROM ({_FOREST}) GROUP BY 1"))(
    lambda s, d: layout.to_forest(pruned_of(s, d, "line", P), 3, 2).groupBy("domain").agg(
        F.count_if(F.col("level") == 2).alias("roots"), F.count("*").alias("cells"), (4 * F.count_if(F.col("level") == 2)).alias("morton_bytes"), (12 * F.count_if(F.col("level") == 2)).alias("ijk_bytes")
    )
)
query("op_forest_roots", sql.with_(sql.pruned("line", 16, P), f"SELECT domain, path AS morton, {', '.join(f'{x} AS i{a}' for a, x in enumerate(sql.deinterleave('path', 3, 2)))} FROM ({_FOREST}) WHERE level = 2"))(
    lambda s, d: layout.roots(layout.to_forest(pruned_of(s, d, "line", P), 3, 2), 3, 2)
)

_TO_ONE = [(i, 0) for i in range(16)]
query("w_merge", sql.with_(sql.mesh("line", P), "SELECT 0::INTEGER AS domain, level, path, refined, false AS masked, rho FROM cells"))(
    lambda s, d: domains.merge(pruned_of(s, d, "line", P).select("domain", "level", "path", "refined", "masked", "rho"), _TO_ONE)
)
query("op_merge_domains", sql.with_(sql.pruned("events", 16, P), "SELECT (domain // 4)::INTEGER AS domain, level, path, bool_or(refined) AS refined, bool_and(masked) AS masked FROM pruned GROUP BY 1, 2, 3"))(
    lambda s, d: domains.merge(_five(pruned_of(s, d, "events", P)), [(i, i // 4) for i in range(16)])
)

# ---- worked example: a 2-D tree of 17 cells, 13 after pruning -----------------------------------

TREE = {"refined": "1" + "1101" + "0" * 12, "masked": "0" + "0011" + "000000111111"}
AFTER = {"refined": "1" + "1100" + "0" * 8, "masked": "0" + "0011" + "00000011"}


def tree_example(spark):
    """Cells of the example as one domain."""
    level = [0] + [1] * 4 + [2] * 12
    path = [0, 0, 1, 2, 3, *range(4), *range(4, 8), *range(12, 16)]
    data = [(0, lv, k, r == "1", m == "1", float(i)) for i, (lv, k, r, m) in enumerate(zip(level, path, TREE["refined"], TREE["masked"]))]
    return rows(spark, data, "domain int, level int, path long, refined boolean, masked boolean, d double")


_SMALL = with_params(P, level_max=4, level_min=1, domains=4)
_DRAWN = "SELECT '{stage}' AS stage, domain, count(*) AS cells, string_agg(refined::INTEGER::VARCHAR, '' ORDER BY level, path) AS refined, string_agg(masked::INTEGER::VARCHAR, '' ORDER BY level, path) AS masked FROM {source} GROUP BY domain"


def drawn(stage: str, local):
    """The two boolean arrays of each domain as text."""
    each = F.array_sort(F.collect_list(F.struct("level", "path", F.col("refined").cast("int").alias("r"), F.col("masked").cast("int").alias("m"))))
    joined = lambda c: F.array_join(F.transform("a", lambda x: x[c].cast("string")), "")
    return local.groupBy("domain").agg(F.count("*").alias("cells"), each.alias("a")).select(F.lit(stage).alias("stage"), "domain", "cells", joined("r").alias("refined"), joined("m").alias("masked"))


@query("w_tree_example", sql.with_(sql.pruned("orders", 4, _SMALL), _DRAWN.format(stage="before", source="local") + " UNION ALL " + _DRAWN.format(stage="after", source="pruned")))
def _(spark, sf_dir):
    """Arrays of a table's mesh, small enough to be read, before and after pruning."""
    local = local_of(spark, sf_dir, "orders", _SMALL)
    return drawn("before", local).unionByName(drawn("after", prune.prune(local, 2)))


@query("w_coarse_overhead", " UNION ALL ".join(f"SELECT * FROM ({sql.with_(sql.mesh(m, P), f'''SELECT '{m}' AS mesh, count(*) AS cells, count(*) FILTER (refined) AS coarse, count(*) FILTER (refined)::DOUBLE / count(*)::DOUBLE AS share FROM cells''')})" for m in (*SNAPSHOTS, "orders", "cust")))
def _(spark, sf_dir):
    out = None
    for m in (*SNAPSHOTS, "orders", "cust"):
        one = mesh.build_mesh(spark, sf_dir, m, P).agg(F.count("*").alias("cells"), F.count_if("refined").alias("coarse")).select(F.lit(m).alias("mesh"), "cells", "coarse", (F.col("coarse").cast("double") / F.col("cells").cast("double")).alias("share"))
        out = one if out is None else out.unionByName(one)
    return out
