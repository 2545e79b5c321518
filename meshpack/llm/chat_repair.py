"""Chat formatting by minimum-cost role repair.

A legal conversation is an optional system turn, then user and assistant in turn, ending with
the assistant.  Each source turn may be kept, merged into the turn before, relabelled, or
preceded by empty turns; a dynamic programme over the automaton's states finds the cheapest
repair and the repaired sequence is rendered.

A turn acts on the vector of least costs as a small matrix in (min, +), so a conversation of
any length can be cut: turns are range-partitioned by (conv_id, turn), and only pieces of
conversations that cross a partition's edge are summed up as one matrix each.  From those the
costs-to-go at each edge follow, then the states at each edge, then every partition decides
its own turns.  The result does not depend on where the edges fall.

Defined cases: a null conv_id is a conversation of its own; turns order by turn, then role,
then a hash of the text, nulls first; null or unknown roles may take any role at the price of
a relabelling; null text is empty; template marks inside a text are broken by a space; a
conversation of system turns only gets an empty user and assistant turn; repeated rows are turns
like any other; ids may be of any type; columns of the names that are added give way.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, fresh

ROLES = ("system", "user", "assistant")
#: States are "after role r", and the start; turns allowed after each; where a text may end.
START, SYSTEM, USER, ASSISTANT = range(4)
NEXT = {START: (SYSTEM, USER), SYSTEM: (USER,), USER: (ASSISTANT,), ASSISTANT: (USER,)}
FINAL = ASSISTANT
#: Costs of the repairs.
KEEP, MERGE, RELABEL, INSERT = 0, 2, 5, 4
FAR = 1 << 40

OPEN, CLOSE = "<|{}|>\n", "<|end|>\n"


def inserted(a: int, b: int) -> tuple[int, ...] | None:
    """Shortest run of empty turns that leads from state ``a`` to ``b``."""
    ways, seen = [(a, ())], {a}
    while ways:
        at, path = ways.pop(0)
        if at == b:
            return path
        for n in NEXT[at]:
            if n not in seen:
                seen.add(n)
                ways.append((n, (*path, n)))
    return None


def moves_of(role: int | None) -> list[list[tuple[int, int, str, tuple[int, ...]]]]:
    """For each state the (cost, state after, action, empty turns before) of a turn, in order of preference."""
    out = []
    for s in range(4):
        found = []
        for r in (SYSTEM, USER, ASSISTANT):
            change = 0 if r == role else RELABEL
            if s == r:
                found.append((MERGE + change, r, "relabel_merge" if change else "merge", ()))
            for t in range(4):
                if r in NEXT[t] and (way := inserted(s, t)) is not None:
                    found.append((INSERT * len(way) + change, r, ("relabel" if change else "keep"), way))
        out.append(sorted(found, key=lambda m: (m[0], len(m[3]), m[2], m[1], m[3])))
    return out


MOVES = {r: moves_of(r) for r in (SYSTEM, USER, ASSISTANT, None)}
#: Cost and empty turns that end a text from each state; an empty text may stay empty.
ENDING = [(0, ()) if s == START else (INSERT * len(inserted(s, FINAL)), inserted(s, FINAL)) for s in range(4)]


def number(role: str | None) -> int | None:
    name = (role or "").strip().lower()
    return ROLES.index(name) + 1 if name in ROLES else None


def matrix_of(role: int | None) -> tuple[tuple[int, ...], ...]:
    return tuple(tuple(min((c for c, r, *_ in MOVES[role][s] if r == e), default=FAR) for e in range(4)) for s in range(4))


MATRIX = {r: matrix_of(r) for r in MOVES}


def before(matrix, to_go: list[int]) -> list[int]:
    """Costs-to-go ahead of a turn or piece, given those behind it."""
    return [min(FAR, min(m + g for m, g in zip(row, to_go))) for row in matrix]


def product(a, b):
    return tuple(tuple(min(FAR, min(a[i][k] + b[k][j] for k in range(4))) for j in range(4)) for i in range(4))


UNIT = tuple(tuple(0 if i == j else FAR for j in range(4)) for i in range(4))


def decide(roles: list[int | None], state: int, to_go: list[int]):
    """Moves of the turns from ``state``, with costs-to-go ``to_go`` behind the last one."""
    ahead = [to_go]
    for r in reversed(roles):
        ahead.append(before(MATRIX[r], ahead[-1]))
    ahead.reverse()
    out = []
    for i, r in enumerate(roles):
        move = next(m for m in MOVES[r][state] if m[0] + ahead[i + 1][m[1]] == ahead[i][state])
        out.append((state, move))
        state = move[1]
    return out, state, ahead[0]


def quoted(text: str | None) -> str:
    return (text or "").replace("<|", "< |")


def empty_turns(way) -> str:
    return "".join(OPEN.format(ROLES[r - 1]) + CLOSE for r in way)


def fragment(state: int, move, text: str | None) -> str:
    """What a turn adds to the rendered text; open turns are closed by what follows."""
    _, role, action, way = move
    if action.endswith("merge"):
        return "\n" + quoted(text)
    return ("\n" + CLOSE if state != START else "") + empty_turns(way) + OPEN.format(ROLES[role - 1]) + quoted(text)


def ending(state: int) -> str:
    return ("\n" + CLOSE if state != START else "") + empty_turns(ENDING[state][1])


def repair(turns: list[tuple[str | None, str | None]]) -> tuple[int, str]:
    """Cost and rendered text of one conversation in memory."""
    moves, state, ahead = decide([number(r) for r, _ in turns], START, [c for c, _ in ENDING])
    return ahead[START], "".join(fragment(s, m, t) for (s, m), (_, t) in zip(moves, turns)) + ending(state)


ADDED = [
    T.StructField("new_role", T.StringType()), T.StructField("action", T.StringType()),
    T.StructField("cost", T.LongType()), T.StructField("n_inserted", T.LongType()), T.StructField("fragment", T.StringType()),
]


def _groups(batches):
    """Runs of equal conv_id in a sorted partition, as lists of (conv_id, role, text) rows."""
    key, rows, first = None, [], True
    for batch in batches:
        names = batch.schema.names
        cols = [batch.column(names.index(c)).to_pylist() for c in ("conv_id", "role", "text")]
        for i, (conv, role, text) in enumerate(zip(*cols)):
            if not first and conv != key:
                yield key, rows
                rows = []
            key, first = conv, False
            rows.append((role, text, batch, i))
    if not first:
        yield key, rows


def repair_roles(conversations: DataFrame) -> DataFrame:
    """Each turn with its new role, action, cost, empty turns added, and rendered fragment.

    The fragments of a conversation, joined in (turn, place) order, are its rendered text;
    ``place`` counts turns within a partition's sorted order and so breaks ties of ``turn``.
    """
    names = {f.name for f in ADDED} | {"place"}
    kept = [c for c in conversations.columns if c not in names]
    (part,) = fresh(kept, "part")
    tie = F.xxhash64("text")
    own = conversations.select(*kept)
    placed = cut(
        own.repartitionByRange(F.col("conv_id"), F.col("turn"), F.col("role"), tie).sortWithinPartitions("conv_id", "turn", "role", tie)
        .withColumn(part, F.spark_partition_id()).withColumn("place", F.monotonically_increasing_id())
    )
    edges = placed.groupBy(F.col(part).alias("part")).agg(F.min_by("conv_id", "place").alias("first"), F.max_by("conv_id", "place").alias("last"), F.count("*").alias("n")).orderBy("part").collect()  # a row for each partition
    crossing = {}  # part -> conversations that go on before or after it
    for a, b in zip(edges, edges[1:]):
        if a["last"] == b["first"]:
            crossing.setdefault(a["part"], set()).add(a["last"])
            crossing.setdefault(b["part"], set()).add(b["first"])
    enter, leave = _edges(placed.select("conv_id", "role", F.col(part).alias("part")), crossing) if crossing else ({}, {})
    schema = T.StructType([*(placed.schema[c] for c in [*kept, "place"]), *ADDED])
    out_names = [*kept, "place", *(f.name for f in ADDED)]

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_type

        types = {f.name: to_arrow_type(f.dataType) for f in ADDED}
        held: list[tuple] = []

        def flush():
            by_batch: dict[int, list] = {}
            for row in held:
                by_batch.setdefault(id(row[0]), []).append(row)
            for rows in by_batch.values():
                batch = rows[0][0]
                part = batch.take(pa.array([r[1] for r in rows]))
                arrays = [part.column(batch.schema.names.index(c)) for c in [*kept, "place"]]
                arrays += [pa.array([r[2][k] for r in rows], types[f.name]) for k, f in enumerate(ADDED)]
                yield pa.RecordBatch.from_arrays(arrays, names=out_names)
            held.clear()

        for conv, rows in _groups(batches):
            at = rows[0][2].column(rows[0][2].schema.names.index(part))[0].as_py()
            state = enter.get((at, conv), START)
            ends = (at, conv) not in leave
            to_go = [c for c, _ in ENDING] if ends else leave[at, conv]
            moves, last, _ = decide([number(r[0]) for r in rows], state, to_go)
            for k, ((s, m), (_, text, batch, i)) in enumerate(zip(moves, rows)):
                close = ends and k == len(rows) - 1
                extra = ENDING[last] if close else (0, ())
                made = fragment(s, m, text) + (ending(last) if close else "")
                held.append((batch, i, (ROLES[m[1] - 1], m[2], m[0] + extra[0], len(m[3]) + len(extra[1]), made)))
            if len(held) >= 512:
                yield from flush()
        yield from flush()

    return placed.select(*kept, "place", part).mapInArrow(run, schema)


def _edges(placed: DataFrame, crossing: dict[int, set]):
    """States at which pieces of crossing conversations begin, and costs-to-go where they end.

    Two small passes: a matrix for each piece, then for each the states it leads to.  Both bring
    at most two rows a partition to the driver.
    """
    pieces = placed.where(F.col("part").isin(sorted(crossing))).select("conv_id", "role", F.lit("").alias("text"), "part")

    def summed(batches):
        for conv, rows in _groups(batches):
            at = rows[0][2].column(3)[0].as_py()
            if conv in crossing[at]:
                total = UNIT
                for role, *_ in rows:
                    total = product(total, MATRIX[number(role)])
                yield pa.RecordBatch.from_pydict({"part": pa.array([at], pa.int32()), "conv_id": pa.array([conv], rows[0][2].schema.field(0).type), "m": pa.array([[x for row in total for x in row]], pa.list_(pa.int64()))})

    kind = placed.schema["conv_id"].dataType
    first = T.StructType([T.StructField("part", T.IntegerType()), T.StructField("conv_id", kind), T.StructField("m", T.ArrayType(T.LongType()))])
    got = sorted(((r.part, r.conv_id, r.m) for r in pieces.mapInArrow(summed, first).collect()), key=lambda r: r[0])
    chains: dict[object, list] = {}
    for part, conv, m in got:
        chains.setdefault(conv, []).append((part, [m[4 * i : 4 * i + 4] for i in range(4)]))
    leave = {}
    for conv, chain in chains.items():
        to_go = [c for c, _ in ENDING]
        for k, (part, m) in reversed(list(enumerate(chain))):
            if k < len(chain) - 1:
                leave[part, conv] = to_go
            to_go = before(m, to_go)

    def led(batches):
        for conv, rows in _groups(batches):
            at = rows[0][2].column(3)[0].as_py()
            if conv in crossing[at]:
                to_go = leave.get((at, conv), [c for c, _ in ENDING])
                roles = [number(r[0]) for r in rows]
                to = [decide(roles, s, to_go)[1] for s in range(4)]
                yield pa.RecordBatch.from_pydict({"part": pa.array([at], pa.int32()), "conv_id": pa.array([conv], rows[0][2].schema.field(0).type), "m": pa.array([to], pa.list_(pa.int64()))})

    to = {(r.part, r.conv_id): r.m for r in pieces.mapInArrow(led, first).collect()}
    enter = {}
    for conv, chain in chains.items():
        state = START
        for part, _ in chain:
            enter[part, conv] = state
            state = to[part, conv][state]
    return enter, leave


def rendered(conversations: DataFrame) -> DataFrame:
    """conv_id, rendered text and cost; for conversations that fit one row."""
    return repair_roles(conversations).groupBy("conv_id").agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("place", "fragment"))), lambda x: x["fragment"]), "").alias("text"),
        F.sum("cost").alias("cost"),
    )
