"""Helpers that several operators share."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows are handed to Python code in stretches of about this size.
BATCH_BYTES = 4 << 20
GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective); wraps around silently."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: About what a dict entry with its two small objects takes beyond their contents.
ENTRY_BYTES = 200


class Memo(dict):
    """A dict that asks ``fill`` for what it lacks and forgets everything once keys and values fill ``limit`` bytes.

    What is too long to be worth it (``longest`` characters) is never kept.
    """

    def __init__(self, fill, limit: int = 48 << 20, longest: int = 256):
        super().__init__()
        self.fill, self.limit, self.longest, self.used = fill, limit, longest, 0

    def __missing__(self, key):
        value = self.fill(key)
        if len(key) <= self.longest:
            if self.used > self.limit:
                self.clear()
            self.used += ENTRY_BYTES + len(key)
            self[key] = value
        return value

    def clear(self) -> None:
        super().clear()
        self.used = 0


def release() -> None:
    """Give freed memory back to the system: workers are reused by the stages that follow."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def crc_fold(doc_id: Column, folds: int) -> Column:
    """crc32 of the id's decimal text, modulo ``folds``; NULL ids have no fold."""
    return F.crc32(doc_id.cast("string").cast("binary")) % folds


def cut(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """Stretches of a batch of about ``BATCH_BYTES`` each, so that Python objects exist for few rows at a time."""
    n = batch.num_rows
    step = max(1, n * BATCH_BYTES // max(1, batch.nbytes))
    for at in range(0, n, step):
        yield batch.slice(at, step)


#: Characters of the texts that are encoded together.
GROUP = 1 << 18


def groups(rows: list[tuple]) -> Iterator[list[tuple]]:
    """Stretches of ``(id, text)`` rows with about ``GROUP`` characters of text; at least one row each."""
    held, used = [], 0
    for row in rows:
        held.append(row)
        used += len(row[1] or "")
        if used >= GROUP:
            yield held
            held, used = [], 0
    if held:
        yield held


def map_rows(df: DataFrame, columns: list[str], kernel, schema: str) -> DataFrame:
    """Run ``kernel(iterator of lists of row tuples) -> iterator of dicts of columns`` on each partition.

    Only ``columns`` reach Python; batches arrive and leave as Arrow, so memory follows the batch, not the partition.
    Batches are cut into rows ``BATCH_BYTES`` at a time.
    """
    from pyspark.sql.types import _parse_datatype_string

    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (list(zip(*(c.to_pylist() for c in part.columns))) for b in batches for part in cut(b))
        for out in kernel(rows):
            yield pa.RecordBatch.from_arrays([pa.array(out[f.name], f.type) for f in arrow], schema=arrow)
        release()

    return df.select(*columns).mapInArrow(run, schema)
