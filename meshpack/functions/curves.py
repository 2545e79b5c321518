"""Space-filling curve keys as Catalyst expressions (no UDF), and their tables."""

from __future__ import annotations

from functools import lru_cache

from pyspark.sql import Column
from pyspark.sql import functions as F
from .shifts import shl, shr, ushr

#: Bits of an axis that one table lookup spreads, and of a key (times the dimension) that one gathers.
SPREAD_BITS = 8
GATHER_BITS = {2: 4, 3: 3}


@lru_cache
def _spread_table(dim: int) -> tuple[int, ...]:
    """Each byte with its bits ``dim`` places apart."""
    return tuple(sum((x >> j & 1) << (j * dim) for j in range(SPREAD_BITS)) for x in range(1 << SPREAD_BITS))


@lru_cache
def _gather_table(dim: int) -> tuple[int, ...]:
    """Every ``dim``-th bit of a few key bits, brought together."""
    n = GATHER_BITS[dim]
    return tuple(sum((x >> (j * dim) & 1) << j for j in range(n)) for x in range(1 << (n * dim)))


def _longs(values) -> Column:
    return F.lit(list(values)).cast("array<bigint>")


def _sum_or(parts: list[Column]) -> Column:
    out = parts[0]
    for p in parts[1:]:
        out = out.bitwiseOR(p)
    return out


def morton_encode(cols: list[Column], bits: int | None = None) -> Column:
    """Interleave: bit j of axis a goes to bit ``j * dim + a``.

    Bytes of each axis go through a table of 256 entries made by rule, so the expression grows with
    the number of bytes only and stays in generated code.
    """
    dim = len(cols)
    most = max_root_level(dim, 64)
    bits = most if bits is None else bits
    if bits > most:
        raise ValueError(f"{bits} bits on {dim} axes do not fit a 64-bit key")
    if dim == 1:
        return cols[0].cast("long")
    known, parts = _longs(_spread_table(dim)), []
    for a, x in enumerate(cols):
        for at in range(0, bits, SPREAD_BITS):
            low = (shr(x, at) if at else x).bitwiseAND(F.lit((1 << min(SPREAD_BITS, bits - at)) - 1)).cast("int")
            parts.append(shl(F.get(known, low), at * dim + a))
    return _sum_or(parts)


def morton_decode(key: Column, dim: int, bits: int | None = None) -> list[Column]:
    if dim == 1:
        return [key]
    n, known = GATHER_BITS[dim], _longs(_gather_table(dim))
    bits = max_root_level(dim, 64) if bits is None else bits

    def axis(a: int) -> Column:
        steps = range(0, bits, n)
        chunk = lambda at: ushr(key, at * dim + a).bitwiseAND(F.lit((1 << (n * dim)) - 1)).cast("int")
        return _sum_or([shl(F.get(known, chunk(at)), at) for at in steps])

    return [axis(a) for a in range(dim)]


def max_root_level(dim: int, width: int = 32) -> int:
    """Deepest level whose keys fit a signed-safe word of ``width`` bits."""
    return width // dim if dim > 1 and width % dim else width // dim - (1 if width == 64 else 0)


def root_level(dim: str, width: str) -> Column:
    """:func:`max_root_level` of columns, for two axes or more."""
    dim, width = F.col(dim), F.col(width)
    return (F.floor(width / dim) - ((width == 64) & (width % dim == 0)).cast("int")).cast("int")


def hilbert_tables(dim: int) -> tuple[list[int], list[int]]:
    """(digit, next state) by ``state * 2^dim + coordinate bits``, by rule.

    A state is an entry corner and a direction; corners follow the reflected binary code.
    """
    n, full = dim, (1 << dim) - 1
    turn = lambda x, k: ((x >> (k % n)) | (x << (n - k % n))) & full
    gray = lambda x: x ^ (x >> 1)
    back = {gray(x): x for x in range(full + 1)}
    ones = lambda x: next(k for k in range(64) if not x >> k & 1)
    corner = lambda w: gray(2 * ((w - 1) // 2)) if w else 0
    way = lambda w: 0 if not w else ones(w) % n if w & 1 else ones(w - 1) % n
    digit, after = [], []
    for e in range(full + 1):
        for d in range(n):
            for bits in range(full + 1):
                w = back[turn(bits ^ e, d + 1)]
                digit.append(w)
                e2, d2 = e ^ turn(corner(w), n - (d + 1) % n), (d + way(w) + 1) % n
                after.append(e2 * n + d2)
    return digit, after


_tables = lru_cache(hilbert_tables)


def hilbert_key(cols: list[Column], bits: int) -> Column:
    """Hilbert key of integer coordinates, by a walk over their bits with a state table."""
    dim = len(cols)
    if dim == 1:
        return cols[0].cast("long")
    return hilbert_of_morton(morton_encode(cols, bits), dim, F.lit(bits))


def hilbert_of_morton(path: Column, dim: int, level: Column) -> Column:
    """Hilbert key of a cell from its Morton path and level; a prefix of its descendants' keys."""
    if dim == 1:
        return path
    digit, after = _tables(dim)
    size = 1 << dim
    digits, states = F.array(*map(F.lit, digit)), F.array(*map(F.lit, after))

    def step(acc, i):
        bits = shr(path, ((level - i) * dim).cast("int")).bitwiseAND(F.lit(size - 1)).cast("int")
        at = acc["s"] * size + bits + 1
        return F.struct(
            shl(acc["h"], dim).bitwiseOR(F.element_at(digits, at).cast("long")).alias("h"),
            F.element_at(states, at).alias("s"),
        )

    start = F.struct(F.lit(0).cast("long").alias("h"), F.lit(0).alias("s"))
    walk = F.filter(F.sequence(F.lit(1), F.greatest(level, F.lit(1))), lambda i: i <= level)
    return F.aggregate(walk, start, step, lambda acc: acc["h"])
