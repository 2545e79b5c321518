"""Helpers shared by the text operators: tables, lineage cuts and Arrow kernels."""

from __future__ import annotations

import ctypes
import os
import tempfile
from collections.abc import Callable, Iterable, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import IntegralType, StructField, StructType

#: Rows that a kernel turns into Python objects at once; bounds a worker's memory.
ROWS_AT_ONCE = 256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder for checkpoints: the session's own, else a local one on local masters only."""
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if found:
        return found
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        named = tempfile.mkdtemp(prefix="meshpack-checkpoint-")
    sc.setCheckpointDir(named)
    return named


def cut(df: DataFrame) -> DataFrame:
    """Compute once, store in the shared checkpoint folder, forget the lineage."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def released(run):
    """``run`` over a task's batches; what it has freed goes back to the system when it ends.

    Workers live on from stage to stage, and without this each would keep the most it ever held.
    """

    def go(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
            if trim:
                trim(0)

    return go


def map_texts(
    df: DataFrame,
    make_kernel: Callable[[], Callable[[list[str | None]], dict[str, Sequence]]],
    added: Sequence[StructField],
    keep: Iterable[str] | None = None,
    text: str = "text",
) -> DataFrame:
    """``df`` with columns that a kernel computes from whole texts, in Arrow batches.

    ``make_kernel`` runs once in each task.  A column of ``df`` that has the name of an
    added one gives way to it.  ``keep`` names the columns that stay (all by default).
    """
    names = {f.name for f in added}
    kept = [c for c in (df.columns if keep is None else keep) if c not in names]
    schema = StructType([*(df.schema[c] for c in kept), *added])
    types = {f.name: to_arrow_type(f.dataType) for f in added}
    read = list(dict.fromkeys([*kept, text]))

    def run(batches):
        kernel = make_kernel()
        for batch in batches:
            for lo in range(0, batch.num_rows, ROWS_AT_ONCE):
                part = batch.slice(lo, ROWS_AT_ONCE)
                got = kernel(part.column(read.index(text)).to_pylist())
                arrays = [part.column(read.index(c)) for c in kept]
                arrays += [pa.array(got[n], type=t) for n, t in types.items()]
                yield pa.RecordBatch.from_arrays(arrays, names=[*kept, *types])

    return df.select(*read).mapInArrow(released(run), schema)


def fresh(taken: Iterable[str], *names: str) -> list[str]:
    """``names``, each led by as many underscores as keep it apart from all ``taken`` (in any case)."""
    used, out = {c.lower() for c in taken}, []
    for n in names:
        while n.lower() in used:
            n = f"_{n}"
        used.add(n.lower())
        out.append(n)
    return out


def id_key(df: DataFrame, name: str = "doc_id") -> tuple[Column, Column]:
    """An id that orders null last, and what stands for null: whole numbers as such, all else as text."""
    if isinstance(df.schema[name].dataType, IntegralType):
        top = F.lit(2**63 - 1)
        return F.coalesce(F.col(name).cast("long"), top), top
    top = F.lit("\U0010ffff")
    return F.coalesce(F.col(name).cast("string"), top), top


def utf8(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "replace")


def tokenizer_path(name: str) -> str:
    """Place of a public vocabulary file: $PUBLIC_TOKENIZERS, else the installed package's."""
    folder = os.environ.get("PUBLIC_TOKENIZERS")
    if folder:
        return os.path.join(folder, name)
    import public_tokenizers

    return public_tokenizers.path(name)


class Lookup:
    """Open-addressed table from non-zero 64-bit keys to numbers, filled and probed in numpy."""

    def __init__(self, keys: np.ndarray, values: np.ndarray, missing=0):
        self.missing = values.dtype.type(missing)
        bits = max(4, int(np.ceil(np.log2(max(1, 2 * len(keys))))))
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.full(1 << bits, missing, values.dtype)
        at, left = self.place(keys), np.arange(len(keys))
        while len(left):
            free = self.keys[at[left]] == 0
            some = left[free]
            _, first = np.unique(at[some], return_index=True)
            put = some[first]
            self.keys[at[put]], self.values[at[put]] = keys[put], values[put]
            left = left[self.keys[at[left]] != keys[left]]
            at[left] = (at[left] + 1) & self.mask

    def place(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def get(self, keys: np.ndarray) -> np.ndarray:
        at = self.place(keys)
        found = self.keys[at]
        out = np.where(found == keys, self.values[at], self.missing)
        left = np.flatnonzero((found != keys) & (found != 0))
        at = at[left]
        while len(left):
            at = (at + 1) & self.mask
            found = self.keys[at]
            hit = found == keys[left]
            out[left[hit]] = self.values[at[hit]]
            on = ~hit & (found != 0)
            left, at = left[on], at[on]
        return out
