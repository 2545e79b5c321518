"""SentencePiece segmentations by Gumbel top-k without replacement, and their decoding.

The lattice of a text has an arc for each vocabulary piece that fits at a place, weighted by
the piece's rank; characters outside the vocabulary have an arc of byte pieces.  No piece
holds a space mark after another character, so the lattice falls apart into units (marks
followed by characters), whose backward sums are found once for all equal units of a batch.

With these sums as exact heuristic, a top-down search perturbed by Gumbel noise visits
segmentations best first: a path is drawn forward, each set of siblings along it gets the
maximum of its perturbed values under the bound of its parent's, and the best set is where
the next distinct path branches off.  Noise has 53 bits and so can't lift a set by more than
``LIFT``; sets below the last value wanted less that are left alone without loss.  The value
after the last one taken is the threshold for inclusion scores.

All noise comes from a counter-based mix of the row's key, so results do not depend on
batches, order or retries.

Defined cases: null and empty texts have the one segmentation of an empty lattice; a text
with fewer than ``k`` segmentations returns all, with inclusion 1; a literal space mark in a
text decodes to a space; repeated rows of equal key and text return equal samples; null keys
count as key 0.
"""

from __future__ import annotations

import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import Lookup, map_texts, released, tokenizer_path

MODEL = "piece_bpe_32k.model"
K = 2
SEED = 11
#: Exponent of the rank in a piece's weight.
ALPHA = 1.0
MARK = "▁"
#: Most that noise of 53 bits adds to a location, rounded up.
LIFT = 37.0
#: A path's sets below this log probability are left alone: the rest of a text has nearly all the
#: mass then, so that the values wanted lie far above FLOOR + LIFT.
FLOOR = -45.0
#: Noise that is made for all texts of a batch at once.
AHEAD = 96
#: Characters taken at once, at about 200 bytes of memory each.
CHARS = 1_800_000

_UNITS = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+").findall
_VOCABULARIES: dict[str, Vocabulary] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of 64-bit words."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def uniform(bits: np.ndarray) -> np.ndarray:
    """Numbers inside (0, 1), with 53 bits."""
    return ((bits >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53


def noise(kind: int, n: int, base) -> np.ndarray:
    """The first ``n`` uniform numbers of a kind, from the mixed key of a text or a column of keys."""
    at = np.arange(n, dtype=np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
    return uniform(mix(mix(at + np.uint64((kind * 0x165667B19E3779F9 + 0x1234567) & (2**64 - 1))) + base))


class Vocabulary:
    """Pieces of a model as a trie over code points, their weights, and byte pieces."""

    def __init__(self, path: str, alpha: float = ALPHA):
        import sentencepiece

        self.library = sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.byte_ids = np.zeros(256, np.int32)
        self.weight = np.zeros(n)
        self.byte_of: dict[int, int] = {}
        self.control = {i for i in range(n) if sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)}
        nodes, follow, ends = 1, {}, {}
        for i, piece in enumerate(self.pieces):
            rank = min(-sp.get_score(i), n) if not sp.is_byte(i) else n
            self.weight[i] = -alpha * np.log1p(max(rank, 0.0))
            if sp.is_byte(i):
                self.byte_of[i] = int(piece[3:5], 16)
                self.byte_ids[self.byte_of[i]] = i
            elif i not in self.control:
                if MARK in piece.lstrip(MARK):
                    raise ValueError(f"piece {i} crosses a word's edge; units would not be independent")
                at = 0
                for c in map(ord, piece):
                    at_next = follow.get((at, c))
                    if at_next is None:
                        at_next = follow[at, c] = nodes
                        nodes += 1
                    at = at_next
                ends[at] = i
        keys = np.array([(a << 21 | c) + 1 for a, c in follow], np.uint64)
        self.follow = Lookup(keys, np.array(list(follow.values()), np.int32), -1)
        #: the first step, by a plain table for code points below its size
        self.first = np.full(0x3000, -1, np.int32)
        for (a, c), to in follow.items():
            if a == 0 and c < len(self.first):
                self.first[c] = to
        self.piece_at = np.full(nodes, -1, np.int32)
        self.piece_at[list(ends)] = list(ends.values())
        self.byte_weight = -alpha * np.log1p(n)

        self.surface = np.array([chr(self.byte_of[i]) if self.byte_of.get(i, 128) < 128 else "" if i in self.control else p for i, p in enumerate(self.pieces)], object)
        self.beyond = np.array([self.byte_of.get(i, 0) >= 128 for i in range(n)])

    def decode_array(self, ids: np.ndarray) -> str:
        """:meth:`decode` of an array of ids."""
        if self.beyond[ids].any():
            return self.decode(ids.tolist())
        text = "".join(self.surface[ids].tolist()).replace(MARK, " ")
        return text[1:] if text.startswith(" ") else text

    def decode(self, ids) -> str:
        """Text of piece ids: bytes joined, marks as spaces, without the leading one."""
        raw = b"".join(bytes([self.byte_of[i]]) if i in self.byte_of else b"" if i in self.control else self.pieces[i].encode() for i in ids)
        text = raw.decode("utf-8", "replace").replace(MARK, " ")
        return text[1:] if text.startswith(" ") else text


def vocabulary(path: str) -> Vocabulary:
    if path not in _VOCABULARIES:
        _VOCABULARIES[path] = Vocabulary(path)
    return _VOCABULARIES[path]


class Lattice:
    """Arcs of all distinct units of a batch.

    Places are numbered by how many characters of the unit are left, units by falling length: the
    ends of all units come first, then all places with one character left, and so on.  A step of one
    character is then a step between these blocks, and backward sums run over slices.
    """

    def __init__(self, v: Vocabulary, units: list[str]):
        sizes = np.fromiter(map(len, units), np.int64, len(units))
        flat = np.frombuffer("".join(units).encode("utf-32-le"), "<u4").astype(np.uint64)
        first = np.cumsum(sizes) - sizes
        rank = np.argsort(-sizes, kind="stable")
        longest = int(sizes.max()) if len(units) else 0
        # block r holds the units with at least r characters, in order of rank
        block = len(units) - np.searchsorted(np.sort(sizes), np.arange(longest + 1))
        off = np.concatenate([[0], np.cumsum(block)])
        self.n_end = int(off[1])
        self.left = np.repeat(np.arange(longest + 1), block)
        n = len(self.left)
        unit = np.arange(n) - off[self.left]
        self.start = np.zeros(len(units), np.int64)
        self.start[rank] = off[sizes[rank]] + np.arange(len(units))
        down = (off[np.maximum(self.left - 1, 0)] + unit).astype(np.int32)
        cp = np.zeros(n, np.uint64)
        inner = np.arange(self.n_end, n)
        cp[inner] = flat[(first + sizes)[rank][unit[inner]] - self.left[inner]]
        # arcs by length: the places that a walk down the trie reaches a piece from
        found, at, node, here, deep = [], inner.astype(np.int32), np.zeros(len(inner), np.uint64), inner.astype(np.int32), 0
        size = np.zeros(n, np.int64)
        while len(at):
            if deep:
                node = v.follow.get((node << np.uint64(21) | cp[here]) + np.uint64(1))
            else:
                node = v.first[np.minimum(cp[here], len(v.first) - 1).astype(np.int64)]
                far = np.flatnonzero(cp[here] >= len(v.first))
                node[far] = v.follow.get(cp[here[far]] + np.uint64(1))
            alive = np.flatnonzero(node >= 0)
            at, node, here = at[alive], node[alive], down[here[alive]]
            deep += 1
            ids = v.piece_at[node]
            full = np.flatnonzero(ids >= 0)
            found.append((at[full], here[full], ids[full]))
            size[at[full]] += 1
            on = np.flatnonzero(here >= self.n_end)
            at, node, here = at[on], node[on].astype(np.uint64), here[on]
        # characters without a piece of their own: one arc of byte pieces, numbered below zero
        short = np.zeros(n, bool)
        short[inner] = True
        if found:
            short[found[0][0]] = False
        lone = np.flatnonzero(short)
        kinds, which = np.unique(cp[lone], return_inverse=True)
        self.bytes = [v.byte_ids[list(chr(int(c)).encode("utf-8", "replace"))] for c in kinds]
        size[lone] += 1
        # longest piece first at each place
        self.arc0 = arc0 = np.concatenate([[0], np.cumsum(size)])
        self.dst, self.piece = np.zeros(int(arc0[-1]), np.int32), np.zeros(int(arc0[-1]), np.int32)
        free = arc0[:-1].copy()
        for at, to, ids in reversed(found):
            put = free[at]
            self.dst[put], self.piece[put] = to, ids
            free[at] += 1
        put = free[lone]
        self.dst[put], self.piece[put] = down[lone], -1 - which
        value = v.weight[np.maximum(self.piece, 0)]
        odd = np.flatnonzero(self.piece < 0)
        if len(odd):
            cost = np.array([len(b) for b in self.bytes]) * v.byte_weight
            value[odd] = cost[-1 - self.piece[odd]]
        # backward sums.  Units whose single characters together have no tiny weight are summed as
        # plain numbers, others as logarithms; which of the two never depends on the batch.
        self.lp = self.backward(value, off, size, False)
        single = np.zeros(len(units))
        np.add.at(single, unit[inner], value[arc0[inner + 1] - 1])
        if (single < -600.0).any():
            tiny = np.repeat((single < -600.0)[unit], size)
            self.lp[tiny] = self.backward(value, off, size, True)[tiny]
        # running sums of each place's probabilities, added up alike in any batch
        self.upto = np.exp(self.lp)
        on, k = np.flatnonzero(size > 1), 1
        while len(on):
            at = arc0[on] + k
            self.upto[at] += self.upto[at - 1]
            k += 1
            on = on[size[on] > k]
        self.upto[arc0[inner + 1] - 1] = 2.0
        # what arcs write: their piece, or the byte pieces of a character
        if len(kinds):
            self.n_byte = np.array([len(b) for b in self.bytes])
            self.byte_flat = np.concatenate(self.bytes)
            self.byte_from = np.cumsum([0, *map(len, self.bytes)])

    def backward(self, value: np.ndarray, off: np.ndarray, size: np.ndarray, logs: bool) -> np.ndarray:
        """Log probability of each arc among those of its place, by sums from the units' ends."""
        beta = np.zeros(len(size)) if logs else np.ones(len(size))
        own = value.copy() if logs else np.exp(value)
        with np.errstate(all="ignore"):
            for lo, hi in zip(off[1:-1].tolist(), off[2:].tolist()):
                a, b = int(self.arc0[lo]), int(self.arc0[hi])
                heads = self.arc0[lo:hi] - a
                total = own[a:b]
                if logs:
                    total += beta[self.dst[a:b]]
                    top = np.maximum.reduceat(total, heads)
                    beta[lo:hi] = top + np.log(np.add.reduceat(np.exp(total - np.repeat(top, size[lo:hi])), heads))
                else:
                    total *= beta[self.dst[a:b]]
                    beta[lo:hi] = np.add.reduceat(total, heads)
            base = np.repeat(beta, size)
            return np.minimum(own - base if logs else np.log(own / base), 0.0)

    def place_of(self, arc: int) -> int:
        return int(np.searchsorted(self.arc0, arc, "right")) - 1

    def ids(self, arcs: np.ndarray) -> np.ndarray:
        piece = self.piece[arcs]
        odd = np.flatnonzero(piece < 0)
        if not len(odd):
            return piece
        n = np.ones(len(piece), np.int64)
        n[odd] = self.n_byte[-1 - piece[odd]]
        at = np.cumsum(n) - n
        out = np.repeat(piece, n)
        m = n[odd]
        step = np.arange(int(m.sum())) - np.repeat(np.cumsum(m) - m, m)
        out[np.repeat(at[odd], m) + step] = self.byte_flat[np.repeat(self.byte_from[-1 - piece[odd]], m) + step]
        return out

    def draw(self, at: np.ndarray, u: np.ndarray) -> np.ndarray:
        """An arc from each place, by its probability."""
        arc = self.arc0[at]
        left = np.flatnonzero(u > self.upto[arc])
        while len(left):
            arc[left] += 1
            left = left[u[left] > self.upto[arc[left]]]
        return arc

    def forward(self, start: np.ndarray, seed: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """A random path from each start place to its unit's end: number of arcs, and arcs in order."""
        n = len(start)
        count, steps = np.zeros(n, np.int64), []
        on, at, t = np.arange(n), start, 0
        while len(on):
            arc = self.draw(at, uniform(mix(seed[on] + np.uint64((t * 0xD1342543DE82EF95 + 0x63) & (2**64 - 1)))))
            steps.append((on, arc))
            count[on] += 1
            at = self.dst[arc]
            more = np.flatnonzero(at >= self.n_end)
            on, at, t = on[more], at[more], t + 1
        offset = np.cumsum(count) - count
        arcs = np.zeros(int(count.sum()), np.int64)
        for t, (on, arc) in enumerate(steps):
            arcs[offset[on] + t] = arc
        return count, arcs


class Sampler:
    """Distinct sampled segmentations of texts."""

    def __init__(self, path: str, k: int = K, seed: int = SEED, chars: int = CHARS):
        self.chars = chars
        self.v, self.k, self.seed = vocabulary(path), k, seed

    def sample(self, keys: list[int | None], texts: list[str | None]):
        """For each text the list of (ids, log probability, perturbed value) and the threshold."""
        out, lo = [None] * len(texts), 0
        while lo < len(texts):
            hi, size = lo, 0
            while hi < len(texts) and (hi == lo or size + len(texts[hi] or "") <= self.chars):
                size += len(texts[hi] or "")
                hi += 1
            out[lo:hi] = self.batch(keys[lo:hi], texts[lo:hi])
            lo = hi
        return out

    def batch(self, keys, texts):
        number: defaultdict[str, int] = defaultdict()
        number.default_factory = number.__len__
        per_doc, flat = [], []
        for t in texts:
            units = _UNITS(MARK + t.replace(" ", MARK)) if t else []
            per_doc.append(len(units))
            flat.append(np.fromiter(map(number.__getitem__, units), np.int64, len(units)))
        lattice = Lattice(self.v, list(number))
        kinds = np.concatenate(flat) if flat else np.zeros(0, np.int64)
        n_units = np.array(per_doc, np.int64)
        unit0 = np.cumsum(n_units) - n_units
        base = mix(np.array([number_of(k) for k in keys], np.uint64) + np.uint64(self.seed * 0x9E3779B97F4A7C15 & (2**64 - 1)))
        within = np.arange(len(kinds)) - np.repeat(unit0, n_units)
        doc_of = np.repeat(np.arange(len(texts)), n_units)
        start = lattice.start[kinds]
        ready = {kind: noise(kind, n, base[:, None]) for kind, n in [(0, 1), *((1 + m, AHEAD) for m in range(self.k)), *((1000 + m, 2) for m in range(1, self.k)), *((2000 + m, 16) for m in range(1, self.k))]}
        docs = [_Search(lattice, base[d], {kind: rows[d] for kind, rows in ready.items()}) for d in range(len(texts))]
        for m in range(self.k):
            seeds = mix(base[doc_of] + within.astype(np.uint64) * np.uint64(0xA24BAED4963EE407) + np.uint64(m * 0x9FB21C651E98DF25 & (2**64 - 1)))
            count, arcs = lattice.forward(start, seeds)
            ends = np.cumsum(count)
            for d, s in enumerate(docs):
                if m and not s.more():
                    continue
                a, b = int(unit0[d]), int(unit0[d] + n_units[d])
                lo = int(ends[a - 1]) if a else 0
                hi = int(ends[b - 1]) if b else 0
                s.take(m, arcs[lo:hi], count[a:b], kinds[a:b])
        return [s.result() for s in docs]


class _Search:
    """Best-first search over one text's segmentations."""

    def __init__(self, lattice: Lattice, base: np.uint64, ready: dict[int, np.ndarray]):
        self.lattice, self.base, self.ready = lattice, base, ready
        self.paths: list[np.ndarray] = []
        self.values: list[float] = []
        self.sums: list[float] = []
        self.heads: list[tuple[np.ndarray, np.ndarray]] = []  # sums ahead of each arc, and sets' values
        self.taken: dict[tuple[int, int], list[int]] = {}
        self.next: tuple[float, int, int] | None = None

    def noise(self, kind: int, n: int) -> np.ndarray:
        row = self.ready.get(kind)
        return row[:n] if row is not None and n <= len(row) else noise(kind, n, self.base)

    def more(self) -> bool:
        return self.next is not None

    def take(self, m: int, arcs: np.ndarray, count: np.ndarray, kinds: np.ndarray) -> None:
        """Add path ``m``: the fresh draw, behind the branch that the search has picked."""
        if m == 0:
            value = float(-np.log(-np.log(self.noise(0, 1)[0])))
            branch = -1
        else:
            value, j, branch = self.next
            arcs = self.branched(m, j, branch, arcs, count, kinds)
        lp = self.lattice.lp[arcs]
        low = min(FLOOR, value - LIFT - 8)
        some = lp[:AHEAD]
        ahead = np.cumsum(some) - some
        if len(lp) > AHEAD and ahead[-1] >= low:
            ahead = np.cumsum(lp) - lp
        head = len(ahead)
        if head and ahead[-1] < low:
            head = int(np.searchsorted(-ahead, -low, "right"))
        with np.errstate(divide="ignore"):
            where = ahead[:head] + np.log(-np.expm1(lp[:head]))
        sets = self.bounded(where, value, self.noise(1 + m, head))
        sets[: branch + 1] = -np.inf  # those belong to the path that this one left
        self.paths.append(arcs)
        self.values.append(value)
        self.sums.append(float(lp.sum()))
        self.heads.append((ahead[:head], sets))
        self.advance()

    @staticmethod
    def bounded(where: np.ndarray, bound: float, u: np.ndarray) -> np.ndarray:
        """Gumbel values at locations ``where``, given that none is above ``bound``."""
        with np.errstate(over="ignore", invalid="ignore", divide="ignore"):
            got = where - np.log(np.exp(where - bound) - np.log(u))
        return np.where(np.isneginf(where), -np.inf, np.minimum(got, bound))

    def advance(self) -> None:
        best = None
        for j, (_, sets) in enumerate(self.heads):
            if len(sets):
                i = int(np.argmax(sets))
                if np.isfinite(sets[i]) and (best is None or sets[i] > best[0]):
                    best = (float(sets[i]), j, i)
        self.next = best

    def branched(self, m: int, j: int, i: int, arcs, count, kinds) -> np.ndarray:
        """Path j up to arc i, a sibling of that arc, then a fresh path."""
        g, old = self.lattice, self.paths[j]
        at = g.place_of(int(old[i]))
        used = self.taken.setdefault((j, i), [int(old[i])])
        lo, hi = int(g.arc0[at]), int(g.arc0[at + 1])
        rest = [a for a in range(lo, hi) if a not in used]
        p = np.exp(g.lp[rest])
        u = self.noise(1000 + m, 2)
        pick = rest[min(int(np.searchsorted(np.cumsum(p), u[0] * p.sum(), "right")), len(rest) - 1)]
        used.append(pick)
        # what is left of the set, bounded by the value just taken
        left = [a for a in rest if a != pick]
        ahead, sets = self.heads[j]
        sets[i] = -np.inf
        if left:
            where = np.array([ahead[i] + np.log(np.exp(g.lp[left]).sum())])
            sets[i] = self.bounded(where, self.next[0], u[1:])[0]
        # to the end of the unit, then the fresh draws of the units behind it
        tail, place, t = [pick], int(g.dst[pick]), 0
        more = self.noise(2000 + m, int(g.left[place]))
        while place >= g.n_end:
            a = int(g.draw(np.array([place]), more[t : t + 1])[0])
            tail.append(a)
            place, t = int(g.dst[a]), t + 1
        units = np.cumsum(g.dst[old[: i + 1]] < g.n_end)
        behind = int(units[i - 1]) + 1 if i else 1  # units up to and with the one branched in
        skip = int(count[:behind].sum())
        return np.concatenate([old[:i], np.array(tail, np.int64), arcs[skip:]])

    def result(self):
        g = self.lattice
        out = []
        for arcs, value, total in zip(self.paths, self.values, self.sums):
            ids = g.ids(arcs)
            out.append((ids.astype(np.int32), total, value))
        return out, (self.next[0] if self.next else -np.inf)


def number_of(key) -> int:
    """64 bits for a row's key: whole numbers as such, null as 0, all else by a hash of its text."""
    import xxhash

    return 0 if key is None else key & (2**64 - 1) if isinstance(key, int) else xxhash.xxh3_64_intdigest(str(key).encode())


def inclusion(total: float, threshold: float) -> float:
    """Log probability that a segmentation exceeds the threshold."""
    if threshold == -np.inf:
        return 0.0
    gap = total - threshold
    return gap if gap < -30 else float(np.log(-np.expm1(-np.exp(min(gap, 700.0)))))


SAMPLE = [
    T.StructField("sample", T.IntegerType()), T.StructField("n_pieces", T.LongType()), T.StructField("log_prob", T.DoubleType()),
    T.StructField("perturbed", T.DoubleType()), T.StructField("log_inclusion", T.DoubleType()), T.StructField("exact", T.BooleanType()),
    T.StructField("ids_sha256", T.StringType()),
]
IDS = T.StructField("ids", T.ArrayType(T.IntegerType()))


def segmentations(docs: DataFrame, k: int = K, model: str = MODEL, seed: int = SEED, key: str = "doc_id", with_ids: bool = True, keep=("doc_id",), chars: int = CHARS, nested: bool = False) -> DataFrame:
    """A row for each text and sample: counts, scores, a digest of the ids, and the ids.

    ``nested``: a row for each text, with its first sample, and the others as an array of structs ``more``.

    ``exact`` tells whether the ids decode to the text; the digest is over ids as little-endian 32-bit words.
    """
    each = [*SAMPLE, *([IDS] if with_ids else [])]
    added = [*each, *([T.StructField("more", T.ArrayType(T.StructType(each)))] if nested else [])]
    kept = [c for c in keep if c not in {f.name for f in added}]
    schema = T.StructType([*(docs.schema[c] for c in kept), *added])
    read = list(dict.fromkeys([*kept, key, "text"]))

    def run(batches):
        import hashlib

        sampler = Sampler(tokenizer_path(model), k, seed, chars)
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                texts = part.column(read.index("text")).to_pylist()
                got = sampler.sample(part.column(read.index(key)).to_pylist(), texts)
                rows, cols, further = [], {f.name: [] for f in each}, {f.name: [] for f in each}
                behind = [0]
                for i, (samples, threshold) in enumerate(got):
                    plain = (texts[i] or "").replace(MARK, " ")
                    if nested:
                        behind.append(behind[-1] + len(samples) - 1)
                    for s, (ids, total, value) in enumerate(samples, 1):
                        to = further if nested and s > 1 else cols
                        if to is cols:
                            rows.append(i)
                        to["sample"].append(s)
                        to["n_pieces"].append(len(ids))
                        to["log_prob"].append(total)
                        to["perturbed"].append(value)
                        to["log_inclusion"].append(inclusion(total, threshold))
                        to["exact"].append(sampler.v.decode_array(ids) == plain)
                        to["ids_sha256"].append(hashlib.sha256(ids.astype("<i4").tobytes()).hexdigest())
                        if with_ids:
                            to["ids"].append(ids)
                taken = part.take(pa.array(rows, pa.int64()))
                arrays = [taken.column(read.index(c)) for c in kept]
                arrays += columns(cols)
                if nested:
                    kind = schema_of["more"]
                    arrays.append(pa.ListArray.from_arrays(pa.array(behind, pa.int32()), pa.StructArray.from_arrays(columns(further), fields=list(kind.value_type)), type=kind))
                yield pa.RecordBatch.from_arrays(arrays, names=[*kept, *(f.name for f in added)])

    from pyspark.sql.pandas.types import to_arrow_type

    schema_of = {f.name: to_arrow_type(f.dataType) for f in added}

    def columns(values):
        out = []
        for f in each:
            got, kind = values[f.name], schema_of[f.name]
            if f.name != IDS.name:
                out.append(pa.array(got, kind))
                continue
            ends = np.cumsum([0, *map(len, got)]).astype(np.int32)
            out.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(got) if got else np.zeros(0, np.int32)), type=kind))
        return out

    return docs.select(*read).mapInArrow(released(run), schema)


def decoded(encoded: DataFrame, model: str = MODEL, ids: str = "ids", name: str = "text") -> DataFrame:
    """``encoded`` with the text of its piece ids; null ids decode to the empty text."""

    def make():
        v = vocabulary(tokenizer_path(model))
        return lambda rows: {name: [v.decode(r or []) for r in rows]}

    return map_texts(encoded, make, [T.StructField(name, T.StringType())], text=ids)
