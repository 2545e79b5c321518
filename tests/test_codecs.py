"""Kernels: worked examples, edges, and round trips on random trees."""

import numpy as np
import pytest

from meshpack.functions import codecs


def random_tree(seed, dim, depth=5, p=0.5):
    """Refinement array, cells per level, and a mask."""
    rng = np.random.default_rng(seed)
    levels, here = [np.array([1], np.uint8)], 1
    for level in range(1, depth + 1):
        n = int(levels[-1].sum()) << dim
        if not n:
            break
        levels.append((rng.random(n) < (p if level < depth else 0)).astype(np.uint8))
    refined = np.concatenate(levels)
    return refined, [len(x) for x in levels], (rng.random(len(refined)) < 0.7).astype(np.uint8)


@pytest.mark.parametrize("length, code", [(1, [12]), (51, [62]), (52, [2, 12, 11]), (2703, [2, 62, 62]), (2704, [3, 12, 11, 11]), (2904, [3, 12, 14, 55]), (52**7 - 1, [7] + [62] * 7)])
def test_digits(length, code):
    assert codecs.digits_of([length])[0].tolist() == code


def test_run_too_long():
    with pytest.raises(ValueError):
        codecs.digits_of([52**7])


def test_example_streams():
    before = np.array([int(c) for c in "1" + "1101" + "0" * 12])
    assert list(codecs.run52_encode(before)) == [1, 14, 12, 12, 23]
    assert list(codecs.run52_encode(before, [1, 4, 12])) == [1, 12, 10, 13, 12, 12, 9, 23]
    after = np.array([int(c) for c in "1" + "1100" + "0" * 8])
    assert list(codecs.run52_encode(after)) == [1, 14, 21]
    assert list(codecs.run52_encode(after, [1, 4, 8])) == [1, 12, 10, 13, 13, 10, 19]


@pytest.mark.parametrize("bits, levels", [([], None), ([0], [1]), ([1] * 200, [1, 8, 191]), ([0, 1] * 50, [1, 99]), ([1] * 60 + [0] * 44, [52, 52]), ([0] * 3000, None)])
def test_run_round_trip(bits, levels):
    b = np.array(bits, np.uint8)
    code = codecs.run52_encode(b, levels)
    assert codecs.run52_decode(code).tolist() == bits
    assert all(codecs.run52_bit_at(code, i) == x for i, x in enumerate(bits[:120]))
    if levels and len(bits):
        ends = np.cumsum(levels)
        for low in range(len(levels)):
            assert codecs.run52_decode(code, low, low).tolist() == bits[ends[low] - levels[low] : ends[low]]
    assert set(code) <= set(range(63))


@pytest.mark.parametrize("lengths", [[1], [127, 128, 129], [5, 16383, 16384, 1, 2097152, 3], [300] * 50])
def test_varint(lengths):
    bits = np.repeat(np.arange(len(lengths)) % 2 ^ 1, lengths).astype(np.uint8)
    plain = bytearray([1])
    for n in lengths:
        while n > 127:
            plain.append(n & 127 | 128)
            n >>= 7
        plain.append(n)
    assert codecs.varint_encode(bits) == bytes(plain) and (codecs.varint_decode(bytes(plain)) == bits).all()
    assert codecs.varint_encode([]) == b"" and not len(codecs.varint_decode(b""))


def test_bit_behind_the_end():
    with pytest.raises(IndexError):
        codecs.run52_bit_at(codecs.run52_encode([1, 0]), 2)


@pytest.mark.parametrize("children, lead, bits", [((1, 1.5, 1.25, 1.75), 12, 212), ((1, 1, 1, 1), 15, 200), ((1, 1, 1, 2), 1, 256), ((1, 1, 1, 2.0**-64), 5, 240), ((1, 1, 1, -1), 0, 260)])
def test_packs(children, lead, bits):
    values = np.array([1.0, *children])
    refined = np.array([1, 0, 0, 0, 0], np.uint8)
    data, at = codecs.pxor_encode(values, refined, [1, 4], 2)
    assert at == [0, 64] and len(data) == (64 + bits + 7) // 8
    assert codecs.Bits.read(codecs.Bits.words(data), np.array([64]), np.array([4]))[0] == lead
    assert codecs.pxor_bits(values, refined, [1, 4], 2) == 64 + bits


SPECIAL = [0.0, -0.0, np.inf, -np.inf, np.nan, 5e-324, 1.7976931348623157e308, np.nextafter(1, 2), 1e-45]


@pytest.mark.parametrize("dim", [1, 2, 3])
@pytest.mark.parametrize("dtype", ["float64", "float32"])
@pytest.mark.parametrize("k", [0, 3, 4, 5, 6])
@pytest.mark.parametrize("how", ["parent", "parent_share", "previous"])
def test_float_round_trip(dim, dtype, k, how):
    for seed in range(4):
        refined, levels, _ = random_tree(seed, dim)
        rng = np.random.default_rng(seed)
        with np.errstate(over="ignore"):
            values = np.where(rng.random(len(refined)) < 0.2, rng.choice(SPECIAL, len(refined)), rng.normal(size=len(refined))).astype(dtype)
        data, at = codecs.pxor_encode(values, refined, levels, dim, k, how)
        back = codecs.pxor_decode(data, refined, levels, dim, dtype, k, how)
        assert back.tobytes() == values.tobytes()
        assert len(data) == (codecs.pxor_bits(values, refined, levels, dim, k, how) + 7) // 8
        top = codecs.pxor_decode(data, refined, levels, dim, dtype, k, how, max_level=1)
        assert top.tobytes() == values[: sum(levels[:2])].tobytes()


@pytest.mark.parametrize("dim", [1, 2, 3])
@pytest.mark.parametrize("k", [1, 2, 3, 6])
def test_packs_shorter_than_a_byte(dim, k):
    """Equal values leave a header alone, and several packs in one byte."""
    refined, levels, _ = random_tree(3, dim)
    for dtype in ("float32", "float64"):
        values = np.full(len(refined), 2.5, dtype)
        values[len(values) // 2 :: 7] = 1.25
        data, _ = codecs.pxor_encode(values, refined, levels, dim, k)
        assert len(data) == (codecs.pxor_bits(values, refined, levels, dim, k) + 7) // 8
        assert codecs.pxor_decode(data, refined, levels, dim, dtype, k).tobytes() == values.tobytes()


def brute_prune(refined, masked, levels, dim):
    """Recursive definition on explicit nodes."""
    level, path = codecs.paths_of(refined, levels, [0], dim, 0)
    at = {(int(a), int(b)): i for i, (a, b) in enumerate(zip(level, path))}

    def owned(l, p):
        i = at[l, p]
        return masked[i] == 0 or (refined[i] and any(owned(l + 1, p << dim | c) for c in range(1 << dim)))

    keep = {}

    def walk(l, p):
        i = at[l, p]
        split = bool(refined[i]) and any(owned(l + 1, p << dim | c) for c in range(1 << dim))
        keep[i] = split
        if split:
            for c in range(1 << dim):
                walk(l + 1, p << dim | c)

    walk(0, 0)
    return keep


@pytest.mark.parametrize("dim", [1, 2, 3])
def test_prune_arrays(dim):
    for seed in range(20):
        refined, levels, masked = random_tree(seed, dim, 4, (0.2, 0.5, 0.8)[seed % 3])
        r, m, kept, new = codecs.prune_arrays(refined.tobytes(), masked.tobytes(), levels, dim)
        expect = brute_prune(refined, masked, levels, dim)
        assert set(np.flatnonzero(kept)) == set(expect)
        assert [bool(x) for x in r] == [expect[i] for i in sorted(expect)]
        again = codecs.prune_arrays(r.tobytes(), m.tobytes(), new, dim)
        assert again[2].all() and (again[0] == r).all()


@pytest.mark.parametrize("name, level", [("zlib", 1), ("zlib", 9), ("lz4", None), ("snappy", None), ("zstd", 3), ("lzma", 1), ("block", None)])
def test_libraries(name, level):
    rng = np.random.default_rng(1)
    for raw in (b"", np.cumsum(rng.normal(size=1001)).tobytes(), np.array(SPECIAL * 5).tobytes()):
        if not raw and name in ("lz4", "snappy"):
            continue
        enc, dec = codecs.library(name, level)
        assert bytes(dec(enc(raw), len(raw))) == raw
