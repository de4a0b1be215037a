"""What the text operators share: word pattern, held-out split, Arrow slices of bounded size."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

#: A word is a maximal run of anything but the six ASCII blanks.
WORD = r"[^\x20\x09-\x0D]+"
#: Rows and bytes of text that a worker turns into Python objects at once; a longer row is a slice of its own.
SLICE_ROWS, SLICE_BYTES = 512, 2 << 20


def fold(doc_id: str | Column, n: int) -> Column:
    """crc32 of the id's decimal text, modulo ``n``."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.crc32(c.cast("string").cast("binary")) % n


def least_by_hash(df: DataFrame, rows: int, *ties: str) -> DataFrame:
    """The ``rows`` rows of least hash of ``doc_id``, then of ``ties``, with the hash as ``h``; ``df`` is read twice.

    Only hashes below a bound that leaves about four times as many are sorted, so that what tasks send doesn't grow with
    their number; where ids repeat so much that too few are below it, all are.
    """
    keyed, n = df.withColumn("h", F.xxhash64("doc_id")), df.count()
    if n > 4 * rows:
        few = keyed.filter(F.col("h") < F.lit((1 << 64) * 4 * rows // n - (1 << 63)))
        if few.count() >= rows:
            keyed = few
    return keyed.orderBy("h", *ties).limit(rows)


def _bytes(column: pa.Array) -> np.ndarray | int:
    kind = column.type
    if not (pa.types.is_string(kind) or pa.types.is_binary(kind) or pa.types.is_large_string(kind) or pa.types.is_large_binary(kind)):
        return 0
    return pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def slices(batch: pa.RecordBatch, rows: int = SLICE_ROWS, size: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Consecutive parts of a batch, each of at most ``rows`` rows and ``size`` bytes of text, or of one row."""
    n = batch.num_rows
    total = np.cumsum(sum((_bytes(c) for c in batch.columns), np.zeros(n, np.int64)))
    at = 0
    while at < n:
        full = int(np.searchsorted(total, (total[at - 1] if at else 0) + size, "right"))
        end = min(at + rows, max(at + 1, full))
        yield batch.slice(at, end - at)
        at = end


def hand_back() -> None:
    """Returns freed memory to the system: workers are kept for later tasks, and beside them the JVM needs room."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def map_slices(df: DataFrame, run: Callable[[Iterator[dict]], Iterator[dict]], schema: str) -> DataFrame:
    """``df`` through ``run``, which turns columns of a slice, as lists by name, into columns of ``schema``."""
    kind = StructType.fromDDL(schema)

    def arrow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        target = to_arrow_schema(kind)
        try:
            for out in run(part.to_pydict() for b in batches for part in slices(b)):
                yield pa.RecordBatch.from_pydict(out, schema=target)
        finally:
            hand_back()

    return df.mapInArrow(arrow, kind)


def column_of(fn: Callable[[list], list], kind: pa.DataType) -> Callable[[Iterator[pa.Array]], Iterator[pa.Array]]:
    """Body of an Arrow column function: ``fn`` on slices of the column."""

    def run(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        try:
            for a in arrays:
                whole = pa.RecordBatch.from_arrays([a], ["x"])
                done = [pa.array(fn(part.column(0).to_pylist()), kind) for part in slices(whole)]
                yield pa.concat_arrays(done) if done else pa.array([], kind)
        finally:
            hand_back()

    return run
