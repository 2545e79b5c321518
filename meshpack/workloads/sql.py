"""DuckDB text of the same meshes, built from the same catalogue but written in its own way:
per-bit interleaving, global ranks and plain joins, for results to be held against."""

from __future__ import annotations

from ..functions.curves import hilbert_tables
from ..operators.mesh import Params
from ..sources.tables import MESHES


def interleave(cols: list[str], bits: int) -> str:
    d = len(cols)
    if d == 1:
        return f"({cols[0]})::BIGINT"
    return "(" + " | ".join(f"(((({c})::BIGINT >> {j}) & 1) << {j * d + a})" for j in range(bits) for a, c in enumerate(cols)) + ")"


def deinterleave(path: str, d: int, bits: int) -> list[str]:
    if d == 1:
        return [f"({path})::BIGINT"]
    return ["(" + " | ".join(f"(((({path})::BIGINT >> {j * d + a}) & 1) << {j})" for j in range(bits)) + ")" for a in range(d)]


def with_(parts: list[tuple[str, str]], final: str) -> str:
    return "WITH " + ",\n".join(f"{n} AS ({q})" for n, q in parts) + "\n" + final


def points(mesh: str, level: int) -> list[tuple[str, str]]:
    spec = MESHES[mesh]
    q = []
    for a, axis in enumerate(spec.axes):
        hi = f"(select 1 + coalesce(max({axis.sql}), 0) from {spec.table})" if axis.hi is None else str(axis.hi)
        q.append(f"least({(1 << level) - 1}, greatest(0, (({axis.sql}) - {axis.lo})::BIGINT * {1 << level} // ({hi} - {axis.lo})::BIGINT))::BIGINT AS q{a}")
    pts = f"SELECT {', '.join(q)}, {spec.signed[1]} AS sv, {spec.positive[1]} AS sp FROM {spec.table}"
    keyed = f"SELECT *, {interleave([f'q{a}' for a in range(spec.dim)], level)} AS key FROM pts"
    return [("pts", pts), ("keyed", keyed)]


def mesh(name: str, p: Params = Params()) -> list[tuple[str, str]]:
    """... cells(level, path, refined, n, rho, v, p, smooth)."""
    spec = MESHES[name]
    d, L = spec.dim, p.level_max
    top = [(lv, k) for lv in range(p.level_min) for k in range(1 << (lv * d))]
    tops = " UNION ALL ".join(f"SELECT {lv}::INTEGER AS level, unnest(range({1 << (lv * d)}))::BIGINT AS path" for lv in range(p.level_min))
    refd = f"SELECT level, path FROM cnt WHERE level >= {p.level_min} AND level < {L} AND n > {p.threshold}" + (f" UNION ALL {tops}" if top else "")
    parts = points(name, L) + [
        ("levels", f"SELECT unnest(range({L + 1}))::INTEGER AS l"),
        ("cnt", f"SELECT l AS level, key >> ({d} * ({L} - l)) AS path, count(*) AS n, sum(sv)::BIGINT AS sv, sum(sp)::BIGINT AS sp FROM keyed, levels GROUP BY 1, 2"),
        ("refd0" if p.balance else "refd", refd),
    ]
    if p.balance:
        parts += balance(d, L, p.balance == "face")
    off, scale = spec.v
    x = deinterleave("t.path", d, L)
    r2 = " + ".join(f"(2 * {c} + 1 - (1::BIGINT << t.level)) * (2 * {c} + 1 - (1::BIGINT << t.level))" for c in x)
    parts += [
        ("tree", f"SELECT 0::INTEGER AS level, 0::BIGINT AS path UNION ALL SELECT (level + 1)::INTEGER, (path << {d}) | c FROM refd, (SELECT unnest(range({1 << d}))::BIGINT AS c)"),
        ("above", f"SELECT t.level, t.path, l AS al, t.path >> ({d} * (t.level - l)) AS ap FROM tree t, levels WHERE l <= t.level"),
        ("near_points", "SELECT a.level, a.path, arg_max(struct_pack(n := c.n, sv := c.sv, sp := c.sp), al) AS w FROM above a JOIN cnt c ON c.level = al AND c.path = ap GROUP BY 1, 2"),
        (
            "cells",
            f"""SELECT t.level, t.path, r.path IS NOT NULL AS refined, coalesce(c.n, 0)::BIGINT AS n,
            coalesce(c.n, 0)::DOUBLE * (1::BIGINT << (t.level * {d}))::DOUBLE AS rho,
            coalesce((w.sv - {off} * w.n)::DOUBLE / ({scale} * w.n)::DOUBLE, 0.0) AS v,
            coalesce(w.sp::DOUBLE / ({spec.p_scale} * w.n)::DOUBLE, 0.0) AS p,
            ((1::BIGINT << t.level) * (1::BIGINT << t.level))::DOUBLE / ((1::BIGINT << t.level) * (1::BIGINT << t.level) + {r2})::DOUBLE AS smooth
            FROM tree t LEFT JOIN refd r ON r.level = t.level AND r.path = t.path LEFT JOIN cnt c ON c.level = t.level AND c.path = t.path
            LEFT JOIN near_points m ON m.level = t.level AND m.path = t.path""",
        ),
    ]
    return parts


def balance(d: int, L: int, face: bool) -> list[tuple[str, str]]:
    parts, last = [], "refd0"
    for level in range(L - 1, 0, -1):
        asked = around(f"(SELECT level, path FROM {last} WHERE level = {level})", d, L, 1, face, [])
        name = f"refd{L - level}_"
        parts.append((name, f"SELECT level, path FROM {last} UNION SELECT (level - 1)::INTEGER, path >> {d} FROM ({asked})"))
        last = name
    return [*parts, ("refd", f"SELECT level, path FROM {last}")]


def around(source: str, d: int, L: int, reach: int, face: bool, keep: list[str]) -> str:
    """Same-level cells within reach of the cells of ``source``, inside the box."""
    from itertools import product

    offs = [o for o in product(range(-reach, reach + 1), repeat=d) if not face or sum(map(abs, o)) <= reach]
    values = ", ".join("(" + ", ".join(map(str, o)) + ")" for o in offs)
    names = ", ".join(f"o{a}" for a in range(d))
    x = deinterleave("path", d, L)
    kept = "".join(f"{k}, " for k in keep)
    moved = f"SELECT {kept}level, {', '.join(f'{x[a]} + o{a} AS y{a}' for a in range(d))} FROM {source} s, (VALUES {values}) AS o({names})"
    ok = " AND ".join(f"y{a} >= 0 AND y{a} < (1::BIGINT << level)" for a in range(d))
    return f"SELECT {kept}level, {interleave([f'y{a}' for a in range(d)], L)} AS path FROM ({moved}) WHERE {ok}"


def hilbert(source: str, path: str, d: int, L: int, out: str = "h") -> list[tuple[str, str]]:
    """Steps that add the Hilbert key of a finest-level Morton path: hk0 .. hkL."""
    digit, after = hilbert_tables(d)
    parts = [("hk0", f"SELECT *, 0::BIGINT AS {out}, 0 AS hs FROM {source}")]
    for i in range(1, L + 1):
        at = f"hs * {1 << d} + (({path} >> {d * (L - i)}) & {(1 << d) - 1}) + 1"
        parts.append((f"hk{i}", f"SELECT * EXCLUDE ({out}, hs), ({out} << {d}) | ({digit})[{at}] AS {out}, ({after})[{at}] AS hs FROM hk{i - 1}"))
    return parts


def threads(name: str, n: int, p: Params = Params()) -> list[tuple[str, str]]:
    """... local(domain, level, path, refined, masked, n, rho, v, p, smooth) and what leads to it."""
    d, L = MESHES[name].dim, p.level_max
    parts = mesh(name, p)
    shift = f"({d} * ({L} - level))"
    if p.curve == "hilbert":
        parts += [("lv", f"SELECT level, path, path << {shift} AS fine FROM cells WHERE NOT refined")] + hilbert("lv", "fine", d, L)
        parts.append(("lk", f"SELECT level, path, (h >> {shift}) << {shift} AS key FROM hk{L}"))
    else:
        parts.append(("lk", f"SELECT level, path, path << {shift} AS key FROM cells WHERE NOT refined"))
    if p.align == "coarse":
        up = d * (L - p.level_min)
        parts.append(("tops", f"SELECT key >> {up} AS k, count(*) AS c FROM lk GROUP BY 1"))
        parts.append(("tops2", f"SELECT k, ((sum(c) OVER (ORDER BY k) - c) * {n} // (SELECT count(*) FROM lk))::INTEGER AS owner FROM tops"))
        parts.append(("lown", f"SELECT level, path, key, owner FROM lk JOIN tops2 ON k = key >> {up}"))
    else:
        parts.append(("lown", f"SELECT level, path, key, ((row_number() OVER (ORDER BY key) - 1) * {n} // (SELECT count(*) FROM lk))::INTEGER AS owner FROM lk"))
    parts += [
        ("up", f"SELECT (level - l)::INTEGER AS level, path >> ({d} * l) AS path, owner, key FROM lown, levels WHERE l <= lown.level"),
        ("own", "SELECT level, path, arg_min(owner, key) AS owner FROM up GROUP BY 1, 2"),
        ("held", "SELECT DISTINCT owner AS domain, level, path FROM up"),
        ("near", f"SELECT DISTINCT domain, level, path FROM ({around('held', d, L, p.halo, False, ['domain'])})" if p.halo else "SELECT domain, level, path FROM held"),
        ("doms", f"SELECT unnest(range({n}))::INTEGER AS domain"),
        ("lref", f"SELECT domain, r.level, r.path FROM refd r JOIN near ON near.level = r.level AND near.path = r.path WHERE r.level >= {p.level_min} UNION ALL SELECT domain, level, path FROM refd, doms WHERE level < {p.level_min}"),
        ("lcell", f"SELECT domain, 0::INTEGER AS level, 0::BIGINT AS path FROM doms UNION ALL SELECT domain, (level + 1)::INTEGER, (path << {d}) | c FROM lref, (SELECT unnest(range({1 << d}))::BIGINT AS c)"),
        (
            "local",
            """SELECT k.domain, k.level, k.path, r.path IS NOT NULL AS refined, o.owner <> k.domain AS masked, g.n, g.rho, g.v, g.p, g.smooth
            FROM lcell k JOIN cells g ON g.level = k.level AND g.path = k.path JOIN own o ON o.level = k.level AND o.path = k.path
            LEFT JOIN lref r ON r.domain = k.domain AND r.level = k.level AND r.path = k.path""",
        ),
    ]
    return parts


def pruned(name: str, n: int, p: Params = Params()) -> list[tuple[str, str]]:
    """... pruned(domain, level, path, refined, masked, fields)."""
    d = MESHES[name].dim
    return threads(name, n, p) + [
        ("live", f"SELECT DISTINCT domain, (level - l)::INTEGER AS level, path >> ({d} * l) AS path FROM local, levels WHERE NOT masked AND l >= 1 AND l <= local.level"),
        (
            "pruned",
            f"""SELECT c.* REPLACE (c.refined AND v.path IS NOT NULL AS refined) FROM local c
            LEFT JOIN live v ON v.domain = c.domain AND v.level = c.level AND v.path = c.path
            WHERE c.level = 0 OR EXISTS (SELECT 1 FROM live u WHERE u.domain = c.domain AND u.level = c.level - 1 AND u.path = (c.path >> {d}))""",
        ),
    ]


def run_table(source: str, bit: str, by: str = "domain", order: str = "level, path", level: str | None = None, name: str = "runs") -> list[tuple[str, str]]:
    """... runs(by, run_no, bit, len[, level])."""
    cut = f" OR {level} <> lag({level}) OVER w" if level else ""
    lv = f", any_value({level}) AS level" if level else ""
    return [
        (f"{name}_a", f"SELECT *, CASE WHEN lag({bit}) OVER w IS NULL OR lag({bit}) OVER w <> {bit}{cut} THEN 1 ELSE 0 END AS fresh FROM {source} WINDOW w AS (PARTITION BY {by} ORDER BY {order})"),
        (f"{name}_b", f"SELECT *, sum(fresh) OVER (PARTITION BY {by} ORDER BY {order} ROWS UNBOUNDED PRECEDING)::BIGINT - 1 AS run_no FROM {name}_a"),
        (name, f"SELECT {by}, run_no, any_value({bit}) AS bit, count(*) AS len{lv} FROM {name}_b GROUP BY {by}, run_no"),
    ]


def digits(length: str = "len") -> str:
    return "(1 + " + " + ".join(f"({length} >= {52**j})::INTEGER" for j in range(1, 7)) + ")"


def run_bytes(length: str = "len") -> str:
    return f"(CASE WHEN {digits(length)} > 1 THEN {digits(length)} + 1 ELSE 1 END)"


def bits(v: str, dtype: str = "float64") -> str:
    return f"({v})::DOUBLE::BIT::BIGINT" if dtype == "float64" else f"((({v})::FLOAT::BIT::INTEGER)::BIGINT & 4294967295)"


def lead(x: str, width: int = 64) -> str:
    return f"(CASE WHEN {x} = 0 THEN {width} ELSE {width} - length(bin({x})) END)"


def packs(source: str, d: int, field: str, dtype: str = "float64", pred: str = "u.{f}", value: str = "c.{f}") -> list[tuple[str, str]]:
    """... res(domain, level, path, parent, value, pred, s) and packs(domain, level, parent, or_bits, lead)."""
    value, pred = value.format(f=field), pred.format(f=field)
    return [
        ("res", f"SELECT c.domain, c.level, c.path, c.path >> {d} AS parent, {value} AS value, {pred} AS pred, xor({bits(value, dtype)}, {bits(pred, dtype)}) AS s FROM {source} c JOIN {source} u ON u.domain = c.domain AND u.level = c.level - 1 AND u.path = (c.path >> {d}) AND u.refined"),
        ("packs_", "SELECT domain, level, parent, bit_or(s) AS or_bits FROM res GROUP BY 1, 2, 3"),
        ("packs", f"SELECT *, {lead('or_bits', 64 if dtype == 'float64' else 32)} AS lead FROM packs_"),
    ]


def pack_bits(d: int, k: int, width: int = 64) -> str:
    return f"({k} + {1 << d} * ({width} - least(lead, {min((1 << k) - 1, width)})))"
