"""Numpy kernels: run-length and parent-XOR coding, pruning of arrays, and library codecs."""

from __future__ import annotations

import lzma
import zlib

import numpy as np

#: Fixed values of the run coder: base and shift of digits, marks between levels for a changing
#: and a continuing bit, and the most digits a length may have.
BASE, SHIFT = 52, 11
FLIP, SAME = 9, 10
MOST_DIGITS = 7
MAX_RUN = BASE**MOST_DIGITS - 1


def as_bytes(column, order) -> bytes:
    return column.combine_chunks().to_numpy(zero_copy_only=False)[order].astype(np.uint8).tobytes()


def pick(raw: bytes, kept: np.ndarray, n: int) -> bytes:
    """Items of a raw field array where ``kept`` is set."""
    width = len(raw) // n if n else 1
    return np.frombuffer(raw, np.uint8).reshape(n, width)[kept].tobytes()


def paths_of(refined: np.ndarray, level_cells, roots, dim: int, root_level: int) -> tuple[np.ndarray, np.ndarray]:
    """Level and path of each cell of a breadth-first refinement array."""
    level, paths, at = [], [], 0
    here = np.asarray(roots, np.int64)
    for k, n in enumerate(level_cells):
        level.append(np.full(n, root_level + k, np.int32))
        paths.append(here)
        split = here[refined[at : at + n] != 0]
        here = ((split[:, None] << dim) | np.arange(1 << dim)).ravel()
        at += n
    return np.concatenate(level), np.concatenate(paths)


def prune_arrays(refined: bytes, masked: bytes, level_cells, dim: int):
    """Pruned refinement and mask arrays, which cells stay, and the new cells per level."""
    r, m = np.frombuffer(refined, np.uint8).copy(), np.frombuffer(masked, np.uint8)
    bounds = np.concatenate([[0], np.cumsum(level_cells)])
    width, below = 1 << dim, None
    live = np.zeros(len(r), bool)
    for k in range(len(level_cells) - 1, -1, -1):
        lo, hi = bounds[k], bounds[k + 1]
        grids = np.flatnonzero(r[lo:hi]) + lo
        if below is not None:
            live[grids] = below.reshape(len(grids), width).any(axis=1)
        below = (m[lo:hi] == 0) | live[lo:hi]
    kept, stay = np.zeros(len(r), bool), np.ones(int(level_cells[0]), bool)
    for k in range(len(level_cells)):
        lo, hi = bounds[k], bounds[k + 1]
        kept[lo:hi] = stay
        stay = np.repeat((stay & live[lo:hi])[r[lo:hi] != 0], width)
    r[~live] = 0
    levels = [int(kept[bounds[k] : bounds[k + 1]].sum()) for k in range(len(level_cells))]
    return r[kept], m[kept], kept, [n for n in levels if n]


# ---- runs in base 52 -------------------------------------------------------------------------


def run_lengths(bits: np.ndarray, cuts=()) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of runs of equal bits; ``cuts`` are places where a run ends anyway."""
    if not len(bits):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    change = bits[1:] != bits[:-1]
    inside = np.asarray(cuts, np.int64)
    change[inside[(inside > 0) & (inside < len(bits))] - 1] = True
    starts = np.concatenate([[0], np.flatnonzero(change) + 1])
    return starts, np.diff(np.append(starts, len(bits)))


def digits_of(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all lengths after one another, and how many each takes."""
    lengths = np.asarray(lengths, np.int64)
    most = int(lengths.max()) if len(lengths) else 0
    if most > MAX_RUN:
        raise ValueError("a run is longer than its code can tell")
    size = np.ones(len(lengths), np.int64)
    if most < BASE:
        return (lengths + SHIFT).astype(np.uint8), size
    long = np.flatnonzero(lengths >= BASE)
    value, powers = lengths[long], BASE ** np.arange(1, MOST_DIGITS, dtype=np.int64)
    n = 1 + (value[:, None] >= powers).sum(axis=1)
    size[long] = n + 1
    at = np.cumsum(size) - size
    out = np.zeros(int(size.sum()), np.uint8)
    out[at] = np.minimum(lengths, BASE - 1) + SHIFT
    first = at[long]
    out[first] = n
    for k in range(MOST_DIGITS):
        some = n > k
        out[first[some] + n[some] - k] = value[some] // BASE**k % BASE + SHIFT
    return out, size


def run52_encode(bits, level_cells=None) -> bytes:
    """First bit, then run lengths; with ``level_cells``, runs end at levels and a mark follows."""
    b = np.frombuffer(bits, np.uint8) if isinstance(bits, (bytes, memoryview)) else np.asarray(bits, np.uint8)
    if not len(b):
        return b""
    ends = np.cumsum(level_cells)[:-1] if level_cells is not None else np.zeros(0, np.int64)
    starts, lengths = run_lengths(b, ends)
    code, size = digits_of(lengths)
    if not len(ends):
        return bytes([b[0]]) + code.tobytes()
    before = np.searchsorted(starts, ends)  # the run that a mark stands ahead of
    at = (np.cumsum(size) - size)[before]
    marks = np.where(b[ends] != b[ends - 1], FLIP, SAME).astype(np.uint8)
    return bytes([b[0]]) + np.insert(code, at, marks).tobytes()


def run52_tokens(code: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bits, lengths and levels of all runs of a stream.  Byte values tell digits, counts and marks apart."""
    c = np.frombuffer(code, np.uint8)
    if len(c) < 2:
        return np.zeros(0, np.uint8), np.zeros(0, np.int64), np.zeros(0, np.int64)
    body = c[1:].astype(np.int64)
    counts = np.flatnonzero((body > 1) & (body <= MOST_DIGITS))
    n = body[counts]
    single = body >= SHIFT
    value = body - SHIFT
    if len(counts):
        digit = np.repeat(counts, n) + 1 + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        single[digit] = False
        value[counts] = 0
        for k in range(MOST_DIGITS):
            some = n > k
            value[counts[some]] = value[counts[some]] * BASE + body[counts[some] + 1 + k] - SHIFT
        single[counts] = True
    at = np.flatnonzero(single)
    marked = (body == FLIP) | (body == SAME)
    before = body[np.maximum(at - 1, 0)]
    flip = np.where(marked[np.maximum(at - 1, 0)], before == FLIP, True)
    flip[0] = False
    return (c[0] ^ (np.cumsum(flip) & 1)).astype(np.uint8), value[at], np.cumsum(marked)[at]


def run52_runs(code: bytes):
    """(bit, length, level) of each run of a stream, in order; levels count marks."""
    yield from zip(*(x.tolist() for x in run52_tokens(code)))


def upto_level(code: bytes, high: int) -> bytes:
    """The stream's bytes for levels 0 to ``high``: reading ends at the mark behind them."""
    marks = np.flatnonzero(np.isin(np.frombuffer(code, np.uint8)[1:], (FLIP, SAME)))
    return code if len(marks) <= high else code[: int(marks[high]) + 1]


def run52_decode(code: bytes, low: int | None = None, high: int | None = None) -> np.ndarray:
    """All bits, or those of levels ``low`` to ``high``; reading ends with the last one asked for."""
    bits, lengths, levels = run52_tokens(code if high is None else upto_level(code, high))
    if low:
        bits, lengths = bits[levels >= low], lengths[levels >= low]
    return np.repeat(bits, lengths)


def run52_bit_at(code: bytes, offset: int) -> int:
    """The bit at an offset of the plain array, from run lengths alone."""
    bits, lengths, _ = run52_tokens(code)
    ends = np.cumsum(lengths)
    at = int(np.searchsorted(ends, offset, "right"))
    if offset < 0 or at >= len(ends):
        raise IndexError("offset behind the end")
    return int(bits[at])


def varint_encode(bits) -> bytes:
    """Run lengths in groups of seven bits, for comparison."""
    b = np.asarray(np.frombuffer(bits, np.uint8) if isinstance(bits, bytes) else bits, np.uint8)
    if not len(b):
        return b""
    lengths = run_lengths(b)[1]
    size = 1 + (lengths[:, None] >= 128 ** np.arange(1, 9)).sum(axis=1)
    at = np.cumsum(size) - size
    out = np.zeros(int(size.sum()), np.uint8)
    for k in range(int(size.max())):
        some = size > k
        out[at[some] + k] = lengths[some] >> 7 * k & 127 | np.where(size[some] > k + 1, 128, 0)
    return bytes([b[0]]) + out.tobytes()


def varint_decode(code: bytes) -> np.ndarray:
    """The bits of such a stream."""
    c = np.frombuffer(code, np.uint8)
    if not len(c):
        return np.zeros(0, np.uint8)
    body = c[1:].astype(np.int64)
    last = np.flatnonzero(body < 128)
    first = np.concatenate([[0], last[:-1] + 1])
    place = np.arange(len(body)) - np.repeat(first, last - first + 1)
    lengths = np.add.reduceat((body & 127) << 7 * place, first)
    return np.repeat((c[0] ^ (np.arange(len(lengths)) & 1)).astype(np.uint8), lengths)


# ---- parent XOR ------------------------------------------------------------------------------


def _views(values: np.ndarray) -> np.ndarray:
    return values.view(np.uint64 if values.dtype.itemsize == 8 else np.uint32).astype(np.uint64)


def _clz(x: np.ndarray, width: int) -> np.ndarray:
    """Leading zeros, from the exponent as a double; the bit behind the first is cleared, so nothing rounds up."""
    return width - np.frexp((x & ~(x >> np.uint64(1))).astype(np.float64))[1].astype(np.int64)


class Bits:
    """Fields of given widths after one another, most significant bit first."""

    @staticmethod
    def write(values: np.ndarray, widths: np.ndarray) -> bytes:
        """Bytes of all fields; each is put, shifted, on the one or two 64-bit words that it touches."""
        widths = np.asarray(widths, np.int64)
        end = np.cumsum(widths)
        total = int(end[-1]) if len(end) else 0
        words = np.zeros(total // 64 + 2, np.uint64)
        some = widths > 0
        v, w, start = values[some].astype(np.uint64), widths[some], (end - widths)[some]
        word, off = start // 64, start % 64
        over = off + w - 64
        if len(v):
            # fields come in order of their words: all that begin in a word are one slice
            cross = np.flatnonzero(over > 0)
            high = v << np.maximum(-over, 0).astype(np.uint64)
            high[cross] = v[cross] >> over[cross].astype(np.uint64)
            heads = np.flatnonzero(np.diff(word, prepend=-1))
            words[word[heads]] = np.bitwise_or.reduceat(high, heads)
            words[word[cross] + 1] |= v[cross] << (64 - over[cross]).astype(np.uint64)  # one field a word boundary
        return words.astype(">u8").tobytes()[: (total + 7) // 8]

    @staticmethod
    def words(data: bytes) -> np.ndarray:
        return np.frombuffer(data + bytes(16 + -len(data) % 8), ">u8").astype(np.uint64)

    @staticmethod
    def read(words: np.ndarray, start: np.ndarray, widths: np.ndarray) -> np.ndarray:
        start, widths = np.asarray(start, np.int64), np.asarray(widths, np.int64)
        word, off = start // 64, (start % 64).astype(np.uint64)
        high = words[word] << off
        low = np.where(off > 0, words[word + 1] >> ((np.uint64(64) - off) & np.uint64(63)), np.uint64(0))
        both = high | low
        return np.where(widths > 0, both >> ((64 - widths) & 63).astype(np.uint64), np.uint64(0))


def _residues(values: np.ndarray, refined: np.ndarray, level_cells, dim: int, how: str) -> tuple[int, np.ndarray, np.ndarray]:
    """Number of cells ahead of the first pack, their bits, and the residues as packs of siblings.

    Packs come in the order of their refined parents, so predictions are those cells' values, one a pack.
    """
    roots, pack = int(level_cells[0]), 1 << dim
    own = values.view(np.uint64 if values.dtype.itemsize == 8 else np.uint32)
    if how == "previous":  # a chain over all cells in packs, the first cells raw
        return roots, own[:roots], (own[roots:] ^ own[roots - 1 : -1]).reshape(-1, pack)
    above = values[refined != 0]
    if how == "parent_share":
        above = above / values.dtype.type(pack)
    return roots, own[:roots], own[roots:].reshape(-1, pack) ^ above.view(own.dtype)[:, None]


def _leads(packs: np.ndarray, width: int, k: int) -> np.ndarray:
    """Header of each pack: the leading zeros of all its residues, as far as ``k`` bits can tell."""
    both = packs[:, 0].copy()
    for j in range(1, packs.shape[1]):
        both |= packs[:, j]
    return np.minimum(_clz(both.astype(np.uint64), width), min((1 << k) - 1, width))


def _alike(lead: np.ndarray, start: np.ndarray):
    """(lead, bit within a byte, numbers of the packs) for packs of equal header and phase: what is written or
    read for these differs in values only, so it takes the same few shifts for all."""
    kind = lead * 8 + (start & 7)
    order = np.argsort(kind.astype(np.int16), kind="stable")
    cuts = np.flatnonzero(np.diff(kind[order])) + 1
    for some in np.split(order, cuts) if len(order) else ():
        yield int(kind[some[0]]) >> 3, int(kind[some[0]]) & 7, some


def _spans(raw: np.ndarray, size: int) -> np.ndarray:
    """The ``size`` bytes from each place on, as single items that are moved at once."""
    return np.ndarray((len(raw) - size + 1,), f"V{size}", raw, strides=(1,))


def pxor_encode(values: np.ndarray, refined: np.ndarray, level_cells, dim: int, k: int = 4, how: str = "parent") -> tuple[bytes, list[int]]:
    """Stream and the bit at which each level begins.  Roots raw; then for each pack of siblings
    a header of ``k`` bits and the residues without their common leading zeros."""
    values = np.ascontiguousarray(values)
    width, pack = values.dtype.itemsize * 8, 1 << dim
    roots, raw, packs = _residues(values, refined, level_cells, dim, how)
    lead = _leads(packs, width, k) if len(packs) else np.zeros(0, np.int64)
    ends = np.concatenate([[0], np.cumsum(k + pack * (width - lead))]) + roots * width
    first = [0, *(int(ends[p]) for p in (np.cumsum(level_cells)[:-1] - roots) // pack)]
    head = raw.astype(raw.dtype.newbyteorder(">")).tobytes()
    if not len(packs):
        return head, first
    # each pack puts the bytes from the one it begins in to before the one the next begins in; what is
    # left of it is joined to that one
    byte = (ends >> 3) - (ends[0] >> 3)
    out, tail = np.zeros(int(byte[-1]) + 1, np.uint8), np.zeros(len(packs), np.uint8)
    for n, phase, some in _alike(lead, ends[:-1]):
        w, at = width - n, phase + k
        words = np.zeros(((at + pack * w + 63) // 64 + 1, len(some)), np.uint64)  # a row for all packs' words in turn
        words[0] = n << (64 - at)
        each = np.ascontiguousarray(packs[some].T, np.uint64)
        for j in range(pack if w else 0):
            word, over = at >> 6, (at & 63) + w - 64
            if over > 0:
                words[word] |= each[j] >> np.uint64(over)
                words[word + 1] = each[j] << np.uint64(64 - over)
            else:
                words[word] |= each[j] << np.uint64(-over)
            at += w
        got = np.ascontiguousarray(words.T, ">u8").view(np.uint8)
        size = at >> 3
        if size:
            _spans(out, size)[byte[some]] = np.ascontiguousarray(got[:, :size]).view(f"V{size}").ravel()
        tail[some] = got[:, size]
    np.bitwise_or.at(out, byte[1:], tail)
    return head + out[: int(ends[-1] + 7 >> 3) - int(ends[0] >> 3)].tobytes(), first


def pxor_decode(data: bytes, refined: np.ndarray, level_cells, dim: int, dtype="float64", k: int = 4, how: str = "parent", max_level: int | None = None, level_bits=None) -> np.ndarray:
    """Values of all cells, or of the levels down to ``max_level``: top-down, as levels need those above."""
    dtype = np.dtype(dtype)
    width, pack = dtype.itemsize * 8, 1 << dim
    unsigned = np.dtype(np.uint64 if width == 64 else np.uint32)
    levels = list(level_cells) if max_level is None else list(level_cells)[: max_level + 1]
    roots, cells = int(levels[0]), int(sum(levels))
    out = np.empty(cells, unsigned)
    out[:roots] = np.frombuffer(data, unsigned.newbyteorder(">"), roots)
    packs = (cells - roots) // pack
    starts, lead = _headers(data, roots * width, packs, k, pack, width)
    # a pack's bytes, and enough behind the last for the words that are read
    room = (width * pack + k + 7) // 64 * 8 + 16
    padded = np.frombuffer(data + bytes(room), np.uint8)
    windows = _spans(padded, room)
    res = out[roots:].reshape(-1, pack)
    for n, phase, some in _alike(lead, starts):
        w, at = width - n, phase + k
        if not w:
            res[some] = 0
            continue
        words = np.ascontiguousarray(windows[starts[some] >> 3].view(">u8").reshape(len(some), -1).T, np.uint64)
        each = np.empty((pack, len(some)), unsigned)
        for j in range(pack):
            word, off = at >> 6, at & 63
            v = words[word] << np.uint64(off)
            if off + w > 64:
                v |= words[word + 1] >> np.uint64(64 - off)
            each[j] = v >> np.uint64(64 - w)
            at += w
        res[some] = each.T
    if how == "previous":
        return _chained(out, roots).view(dtype)
    values = out.view(dtype)
    above, done = 0, roots
    for n, m in zip(levels, levels[1:]):
        guess = values[above : above + int(n)][refined[above : above + int(n)] != 0]
        if how == "parent_share":
            guess = guess / dtype.type(pack)
        out[done : done + int(m)].reshape(-1, pack)[:] ^= guess.view(unsigned)[:, None]
        above, done = done, done + int(m)
    return values


def _chained(out: np.ndarray, roots: int) -> np.ndarray:
    """Values of a chain of previous ones: each is the exclusive-or of all residues up to it."""
    out[roots - 1 :] = np.bitwise_xor.accumulate(out[roots - 1 :])
    return out


def _headers(data: bytes, at: int, packs: int, k: int, pack: int, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Start and header of each pack from bit ``at`` on.

    A header tells where the next one is, so they are walked in turn.  Where packs begin at half
    bytes, the walk is over a list of those, by a table of steps.
    """
    if k == 0 or not packs:
        return at + np.arange(packs) * pack * width, np.zeros(packs, np.int64)
    if k == 4 and pack >= 4:
        whole = np.frombuffer(data, np.uint8)
        half = np.empty((len(whole), 2), np.uint8)
        np.right_shift(whole, 4, out=half[:, 0])
        np.bitwise_and(whole, 15, out=half[:, 1])
        nibbles, place = half.tobytes(), at >> 2
        step = [1 + pack * (width - min(n, width)) // 4 for n in range(16)]
        found = []
        add = found.append
        for _ in range(packs):
            add(place)
            place += step[nibbles[place]]
        places = np.array(found, np.int64)
        return places * 4, half.ravel()[places].astype(np.int64)
    return _walk(data, at, packs, k, [k + pack * (width - min(n, width)) for n in range(1 << k)])


def _walk(data: bytes, at: int, packs: int, k: int, step: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Start and header of each pack, where a header of ``k`` bits, eight at most, tells the bits to the next."""
    whole = np.frombuffer(data + bytes(2), np.uint8).astype(np.uint16)
    pairs = memoryview(whole[:-1] << 8 | whole[1:])
    shifts, mask = [16 - k - off for off in range(8)], (1 << k) - 1
    starts, lead = [], []
    for _ in range(packs):
        n = pairs[at >> 3] >> shifts[at & 7] & mask
        starts.append(at)
        lead.append(n)
        at += step[n]
    return np.array(starts, np.int64), np.array(lead, np.int64)


def pxor_bits(values: np.ndarray, refined: np.ndarray, level_cells, dim: int, k: int = 4, how: str = "parent") -> int:
    values = np.ascontiguousarray(values)
    width, pack = values.dtype.itemsize * 8, 1 << dim
    roots, _, packs = _residues(values, refined, level_cells, dim, how)
    return roots * width + (int((k + pack * (width - _leads(packs, width, k))).sum()) if len(packs) else 0)


# ---- other codecs ----------------------------------------------------------------------------


def library(name: str, level: int | None = None):
    """(encode, decode) of a general-purpose codec; decode takes the plain size too."""
    import pyarrow as pa

    if name == "zlib":
        return (lambda b: zlib.compress(b, level)), (lambda b, n: zlib.decompress(b))
    if name == "lzma":
        return (lambda b: lzma.compress(b, preset=level or 6)), (lambda b, n: lzma.decompress(b))
    if name == "block":
        return block_encode, (lambda b, n: block_decode(b, n))
    codec = pa.Codec({"lz4": "lz4_raw"}.get(name, name), compression_level=level) if name == "zstd" else pa.Codec({"lz4": "lz4_raw"}.get(name, name))
    return (lambda b: codec.compress(b, asbytes=True)), (lambda b, n: codec.decompress(b, decompressed_size=n, asbytes=True))


def block_encode(raw: bytes) -> bytes:
    """Reversible transform of blocks of four doubles and their bit planes from the highest used one.

    A small stand-in for lossless block-transform float coders: the order-keeping integer view, two
    rounds of integer lifting (in modular arithmetic), zigzag, and a header with the common leading
    zeros of a block's coefficients.
    """
    x = np.frombuffer(raw + bytes(-len(raw) % 32), "<i8").reshape(-1, 4).copy()
    x = np.where(x < 0, x ^ np.int64(2**63 - 1), x)  # order of integers as of floats
    with np.errstate(over="ignore"):
        a, b, c, d = (x[:, i].copy() for i in range(4))
        b -= a
        d -= c
        c -= a
        d -= b
        coded = np.stack([a, b, c, d], axis=1)
        zig = ((coded << 1) ^ (coded >> 63)).view(np.uint64)
    lead = np.minimum(_clz(np.bitwise_or.reduce(zig[:, 1:], axis=1), 64), 63)
    fields = np.concatenate([lead[:, None].astype(np.uint64), zig], axis=1)
    widths = np.concatenate([np.full((len(zig), 1), 6), np.full((len(zig), 1), 64), np.repeat((64 - lead)[:, None], 3, axis=1)], axis=1)
    return Bits.write(fields.ravel(), widths.ravel())


def block_decode(data: bytes, n: int) -> bytes:
    words = Bits.words(data)
    blocks = -(-n // 32)
    out = np.zeros((blocks, 4), np.int64)
    # a pack of three behind each block's header and first value, walked like packs of siblings
    starts, lead = _walk(data, 0, blocks, 6, [70 + 3 * (64 - m) for m in range(64)])
    cols = [Bits.read(words, starts + 6, np.full(blocks, 64))]
    cols += [Bits.read(words, starts + 70 + k * (64 - lead), 64 - lead) for k in range(3)]
    zig = np.stack(cols, axis=1)
    back = (zig >> np.uint64(1)).view(np.int64) ^ -(zig & np.uint64(1)).view(np.int64)
    a, b, c, d = (back[:, i].copy() for i in range(4))
    with np.errstate(over="ignore"):
        d += b
        c += a
        d += c
        b += a
    out[:] = np.stack([a, b, c, d], axis=1)
    out = np.where(out < 0, out ^ np.int64(2**63 - 1), out)
    return out.astype("<i8").tobytes()[:n]
