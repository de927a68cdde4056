"""What the text operators share: stored intermediate tables, word counts, and what a Python worker keeps."""

from __future__ import annotations

import contextlib
import ctypes
import functools
import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.shared import drop_folder, drop_stored, shared_folder, stored  # noqa: F401

#: A word is a run of characters outside this class (space and the five ASCII controls 09-0D).
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text):
    """Number of words of a string column; null counts as no words."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def parts_for(rows: int, per_part: int) -> int:
    return max(1, -(-rows // per_part))


def runs_of(batches: Iterator[pa.RecordBatch], key: str) -> Iterator[dict[str, np.ndarray]]:
    """The columns of each run of equal keys in a stream that is sorted by them."""
    held: dict[str, np.ndarray] = {}
    for batch in batches:
        now = {n: batch.column(n).to_numpy(zero_copy_only=False) for n in batch.schema.names}
        held = {n: np.concatenate([held[n], x]) if held else x for n, x in now.items()}
        cuts = np.flatnonzero(np.diff(held[key])) + 1
        for lo, hi in zip([0, *cuts[:-1].tolist()], cuts.tolist(), strict=False):
            yield {n: x[lo:hi] for n, x in held.items()}
        if len(cuts):
            held = {n: x[cuts[-1] :] for n, x in held.items()}
    if held and len(held[key]):
        yield held


def text_slices(column: pa.Array, chars: int = 4_000_000) -> Iterator[tuple[int, int]]:
    """lo, hi of runs of texts of about so many bytes together (a longer text is a run of its own)."""
    sizes = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(), dtype=np.int64)
    lo = 0
    while lo < len(column):
        hi = max(lo + 1, int(np.searchsorted(sizes, (sizes[lo - 1] if lo else 0) + chars, "right")))
        yield lo, hi
        lo = hi


_SLOT: list = [None, None]


def worker_slot(key, make):
    """What a Python worker keeps from task to task: one thing at a time, so that operators run one after another do not add up.

    Memory that the former one held is given back to the system.
    """
    if _SLOT[0] != key:
        _SLOT[:] = [None, None]
        release()
        _SLOT[:] = [key, make()]
    return _SLOT[1]


def release() -> None:
    """Give memory that this process no longer uses back to the system, as far as the platform can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def tidied(run):
    """A map function of a task that gives back, at the task's end, the memory it no longer uses."""

    @functools.wraps(run)
    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            release()

    return wrapped
