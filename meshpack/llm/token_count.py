"""Token counts by the whole-token shortcut.

Offline, every vocabulary string is encoded alone by the library; those that come back as
one token are proved to be *whole*.  A text is cut where no token can cross (white space,
after the library's own normalisation rules), its pre-tokens are looked up among the whole
ones and count one each, and only the rest is merged by the library.  Counts of pieces
between spaces are remembered in a bounded table, which changes speed only.

Pieces with characters outside the scripts for which the two sets of character classes were
compared, and pieces with a special string, are encoded by the library in full.

Defined cases: null counts as empty; an empty text has no tokens and no bytes.
"""

from __future__ import annotations

import json
from unicodedata import normalize

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_texts, tokenizer_path, utf8

MODEL = "word_bpe_49k.json"
LIMIT = 2048
#: Pieces remembered by one task.
REMEMBERED = 400_000
#: White space as the library's expression engine has it (Unicode White_Space).
SPACES = "\t\n\x0b\x0c\r \x85\xa0\u1680" + "".join(map(chr, range(0x2000, 0x200B))) + "\u2028\u2029\u202f\u205f\u3000"
#: The pre-token classes named by the vocabulary file.
PRE_TOKENS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


class Counter:
    """Counts tokens as the library does, without begin, end or added special tokens."""

    def __init__(self, path: str):
        import regex
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.pre_tokens = regex.compile(PRE_TOKENS).findall
        self.whole = self.prove(spec["model"]["vocab"])
        self.plain = regex.compile(r"[\x21-\x7e\xa1-\u024f\u0370-\u03ff\u0400-\u04ff]*").fullmatch
        self.odd_space = regex.compile(f"[{SPACES[6:]}\x1c-\x1f]").search
        self.space = regex.compile(f"[{SPACES}]+").split
        self.known: dict[str, int] = {}
        self.merged: dict[str, int] = {}

    def prove(self, vocabulary: dict[str, int]) -> frozenset[str]:
        """Surface strings that the library encodes alone as exactly one token."""
        surfaces = [s for s in map(self.surface, vocabulary) if s]
        coded = self.library.encode_batch(surfaces, add_special_tokens=False)
        whole = {s for s, e in zip(surfaces, coded) if len(e.ids) == 1}
        # a string counts directly only as one pre-token by itself
        return frozenset(s for s in whole if self.pre_tokens(s) == [s] and s not in self.special)

    @staticmethod
    def surface(piece: str) -> str | None:
        """Text of a byte-level vocabulary entry that ends a word."""
        if not piece.endswith("</w>"):
            return None
        try:
            return bytes(BYTES[c] for c in piece[:-4]).decode("utf-8")
        except (KeyError, UnicodeDecodeError):
            return None

    def merge(self, piece: str) -> int:
        n = self.merged.get(piece)
        if n is None:
            if len(self.merged) >= REMEMBERED:
                self.merged.clear()
            n = self.merged[piece] = len(self.library.encode(piece, add_special_tokens=False).ids)
        return n

    def piece(self, piece: str) -> int:
        """Tokens of a piece without white space."""
        if not self.plain(piece) or any(s in piece for s in self.special):
            return len(self.library.encode(piece, add_special_tokens=False).ids)
        whole, n = self.whole, 0
        # the library lowers character by character: no final form of sigma
        for pre in self.pre_tokens(normalize("NFC", piece).replace("\u03a3", "\u03c3").lower()):
            n += 1 if pre in whole else self.merge(pre)
        return n

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        pieces = self.space(text) if self.odd_space(text) else text.split()
        known, n = self.known, 0
        for p in pieces:
            k = known.get(p)
            if k is None:
                k = self.piece(p) if p else 0
                if len(p) < 64:
                    if len(known) >= REMEMBERED:
                        known.clear()
                    known[p] = k
            n += k
        return n


def _byte_table() -> dict[str, int]:
    """Byte for each character of byte-level vocabularies: printable ones stand for themselves."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}


BYTES = _byte_table()
_COUNTERS: dict[str, Counter] = {}


def counter(path: str) -> Counter:
    if path not in _COUNTERS:
        _COUNTERS[path] = Counter(path)
    return _COUNTERS[path]


ADDED = [T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType())]


def token_counts(docs: DataFrame, model: str = MODEL, limit: int = LIMIT, keep=None) -> DataFrame:
    """``docs`` with n_bytes, n_tokens and over_limit."""

    def make():
        count = counter(tokenizer_path(model)).count
        return lambda texts: {"n_bytes": [len(utf8(t)) for t in texts], "n_tokens": [count(t) for t in texts]}

    kept = [c for c in (docs.columns if keep is None else keep) if c != "over_limit"]
    return map_texts(docs, make, ADDED, kept).withColumn("over_limit", F.col("n_tokens") > limit)
