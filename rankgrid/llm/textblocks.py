"""Whole-column arithmetic on texts: flat byte and code-point buffers, words and their hashes, without a Python object per word."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

WHITE = np.zeros(256, bool)
WHITE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Odd multiplier that spreads lengths and numbers over 64 bits.
SPREAD = np.uint64(0x9E3779B97F4A7C15)
#: Values of spans that are hashed at once: the arrays of a step stay in a processor's cache.
STEP = 1 << 17
#: Bytes of an Arrow batch between Spark and a worker (one row may be larger).
ARROW_BYTES = 8 << 20


def give_back() -> None:
    """Freed memory of this worker to the system: workers live on between tasks, beside the next stage's."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def map_arrow(df: DataFrame, each: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """df.mapInArrow(each, schema) in batches of ARROW_BYTES, by workers that keep no freed memory when a task ends.

    The bound is a setting of the session that holds for later plans too; results don't depend on it.
    """

    def lean(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from each(batches)
        finally:
            give_back()

    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(ARROW_BYTES))
    return df.mapInArrow(lean, schema)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit (the 64-bit finalizer of a well-known public hash)."""
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> np.uint64(33))
    h = h * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


def placed(values: np.ndarray, places: np.ndarray | int) -> np.ndarray:
    """A mixed number for each value (below 2**32) at its place in a span: a pair of value and place always gives the same."""
    return mix((values.astype(np.uint64) | (np.asarray(places).astype(np.uint64) << np.uint64(32))) + SPREAD)


def closed(sums: np.ndarray, sizes: np.ndarray | int) -> np.ndarray:
    """The hash of a span from the sum of its placed values and its size."""
    return mix(sums + np.asarray(sizes).astype(np.uint64) * SPREAD)


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray, second: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of values[start:end] for each span, and on request independent second ones (else an empty array).

    Every value is mixed with its place before anything is added, so that no arrangement of values cancels as in a
    polynomial modulo a power of two. The first hash adds the mixed numbers, the second joins them by exclusive or.
    """
    sizes = ends - starts
    stops = np.cumsum(sizes)
    out, other = np.zeros(len(starts), np.uint64), np.zeros(len(starts) if second else 0, np.uint64)
    lo = 0
    while lo < len(starts):
        hi = max(lo + 1, int(np.searchsorted(stops, (stops[lo - 1] if lo else 0) + STEP, "right")))
        n = sizes[lo:hi]
        first = np.cumsum(n) - n
        place = np.arange(int(n.sum())) - np.repeat(first, n)
        numbers = np.append(placed(values[place + np.repeat(starts[lo:hi], n)], place), np.uint64(0))
        empty = n == 0
        sums = np.add.reduceat(numbers, first)
        sums[empty] = 0
        out[lo:hi] = closed(sums, n)
        if second:
            joined = np.bitwise_xor.reduceat(numbers, first)
            joined[empty] = 0
            other[lo:hi] = closed(joined, n)
        lo = hi
    return out, other


def span_hash(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    return span_hashes(values, starts, ends)[0]


def sliding_hash(words: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all runs of width words, of the words' hashes in their order."""
    n = max(len(words) - width + 1, 0)
    h = np.full(n, width, np.uint64)
    for k in range(width):
        h = mix((h ^ words[k : k + n]) * SPREAD)
    return h


def flat_text(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column in one buffer, and offsets; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column, "").cast(pa.large_string())
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None and buffers[2].size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def small_batches(batches: Iterable[pa.RecordBatch], text: str, limit: int = 1 << 22) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of at most limit bytes of text, or of one row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        at = 0
        while at < batch.num_rows:
            to = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + limit, "right")))
            yield batch.slice(at, to - at)
            at = to


def word_spans(data: np.ndarray, offsets: np.ndarray, white: np.ndarray = WHITE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs without bytes of white, and for each document its first word's index (one more at the end)."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    solid = ~white[data]
    first = np.zeros(len(data) + 1, bool)
    first[offsets] = True
    before = np.empty_like(solid)
    before[0], before[1:] = False, solid[:-1]
    after = np.empty_like(solid)
    after[-1], after[:-1] = False, solid[1:]
    starts = np.flatnonzero(solid & (~before | first[:-1]))
    ends = np.flatnonzero(solid & (~after | first[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words with A-Z lower-cased, and each document's first word's index."""
    starts, ends, first = word_spans(data, offsets)
    return span_hash(LOWER[data], starts, ends), first
