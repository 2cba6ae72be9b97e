"""Whole-sequence kernels: one row per sequence in, one row out, no shuffle, no states at rest.

A state is recomputed from its token where it is used, so what is stored is tokens and centroids.
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from longweave.functions.kernels import TokenVectors

_vectors: dict[tuple[int, int], TokenVectors] = {}
_kept: list[bool] = []


def states_of(toks: list[str], d: int, seed: int) -> np.ndarray:
    return _vectors.setdefault((d, seed), TokenVectors(d, seed))(toks)


def per_sequence(packed: DataFrame, fn: Callable[[int, list[str]], dict | list[dict]], schema: str) -> DataFrame:
    """fn(seq_id, toks) of every row of packed (seq_id, toks); its dicts are rows of schema."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches):
        keep_memory()
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part, out = batch.slice(at, 64), []
                for seq, toks in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    got = fn(seq, toks or [])
                    out += got if isinstance(got, list) else [got]
                if out:
                    yield pa.RecordBatch.from_pylist(out, schema=arrow)

    return packed.select("seq_id", "toks").mapInArrow(run, schema)


#: Rows of states that kernels of several sequences take at a time.
AT_ONCE = 8192


def keep_memory() -> None:
    """Have this worker use freed memory again; matrices beyond 128 kB would else be new pages each time."""
    if not _kept:
        _kept.append(True)
        with contextlib.suppress(OSError, AttributeError):  # another C library
            for option in (-3, -1):  # from where on blocks are mapped alone; what may lie free at the end
                ctypes.CDLL("libc.so.6").mallopt(option, 1 << 26)


def together(batches, size: Callable[[dict], int]):
    """Rows of Arrow batches as dicts, in lists of AT_ONCE states or one row; size: the states of a row."""
    keep_memory()
    part, held = [], 0
    for batch in batches:
        for at in range(batch.num_rows):
            r = batch.slice(at, 1).to_pylist()[0]
            n = size(r)
            if part and held + n > AT_ONCE:
                yield part
                part, held = [], 0
            part.append(r)
            held += n
    if part:
        yield part


def digest(seq: int, h: np.ndarray, digits: int = 4) -> dict:
    """Row count and coordinate sums of a sequence's states."""
    s = h.sum(0) if len(h) else np.zeros(8)
    return {"seq_id": seq, "n": len(h)} | {f"s{j}": round(float(x), digits) + 0.0 for j, x in enumerate(s[:4])}


DIGEST = "seq_id long, n long, s0 double, s1 double, s2 double, s3 double"
