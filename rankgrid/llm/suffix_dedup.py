"""Repeated byte strings of a fixed length: suffixes are sampled by content, dealt by sampled splitters, and sorted in buckets.

Each window of `length` bytes is named by the smallest hash of the grams inside it, so equal windows have equal names
wherever they stand, and consecutive windows of one name make a segment. Only names that occur again matter. Segments
that are equal as a whole, by a 128-bit digest whose seed is drawn anew in each run, settle all their windows at once.
What is left (the ends of repeated passages, and segments that repeat within themselves) is range-partitioned by the
leading tokens of the suffixes that start at the segments' grams, and each bucket sorts its windows by multikey quicksort
on 8-byte tokens. A name with too many windows for one task is not one bucket's: its windows are dealt one by one by
sampled splitters over their leading tokens, digest and place, each bucket compares neighbours in sorted order, and the
first and last strings of the buckets are compared across the boundaries, so that even one string may fill many buckets.
"""

from __future__ import annotations

import hashlib
import secrets
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.skew import bitmap, filter_bits, is_set, left_join
from rankgrid.llm.textblocks import flat_text, map_arrow, mix, small_batches
from rankgrid.llm.token_counts import id_and_text
from rankgrid.session import written

#: Bytes of a gram; windows of one name that one task sorts at most.
GRAM, LOCAL = 64, 200_000
#: Odd multiplier of the gram hash and its inverse modulo 2**64.
BASE = 0x9E3779B97F4A7C15
BASE_INVERSE = pow(BASE, -1, 1 << 64)
#: Bytes of text whose hashes a worker holds at once.
BATCH = 1 << 20


def _sliding(values: np.ndarray, width: int, low: bool) -> np.ndarray:
    """Minimum (or maximum) of each run of width values, by running extrema of blocks from both sides."""
    n = len(values)
    blocks = -(-n // width) + 1
    edge = np.iinfo(np.uint64)
    x = np.full(blocks * width, edge.max if low else edge.min, np.uint64)
    x[:n] = values
    x = x.reshape(blocks, width)
    best = np.minimum if low else np.maximum
    before = best.accumulate(x, axis=1).ravel()
    after = best.accumulate(x[:, ::-1], axis=1)[:, ::-1].ravel()
    return best(after[: n - width + 1], before[width - 1 : n])


def gram_hashes(data: np.ndarray, gram: int) -> np.ndarray:
    """A hash of the gram at each byte, by a polynomial over prefixes. Names need no more than that equal grams have equal
    hashes: grams that share one only meet in a bucket, where their windows are compared."""
    n = len(data)
    up, down = (np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(n, b, np.uint64)])) for b in (BASE, BASE_INVERSE))
    prefix = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:n], out=prefix[1:])
    return mix((prefix[gram:] - prefix[:-gram]) * down[: n - gram + 1])


class Segments:
    """The segments of the texts of one buffer: name, row, first and last window, the place of the name's gram, and whether that gram comes again inside."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int, gram: int):
        width = length - gram + 1
        empty = np.zeros(0, np.int64)
        self.data, self.length = data, length
        self.names, self.row, self.first, self.last, self.anchor, self.inner = empty.astype(np.uint64), empty, empty, empty, empty, empty.astype(bool)
        if len(data) < length:
            return
        hashes = gram_hashes(data, gram)
        least = _sliding(hashes, width, True)
        sizes = np.diff(offsets)
        long = np.flatnonzero(sizes >= length)
        change = np.zeros(len(data) + 1, np.int8)
        np.add.at(change, offsets[long], 1)
        np.add.at(change, offsets[long] + sizes[long] - length + 1, -1)
        starts = np.flatnonzero(np.cumsum(change)[: len(least)])
        if not len(starts):
            return
        m = least[starts]
        new = np.ones(len(starts), bool)
        new[1:] = (m[1:] != m[:-1]) | (starts[1:] != starts[:-1] + 1)
        # windows of two documents can follow each other only if the first is as long as a window: part them
        own = np.searchsorted(offsets, starts, "right") - 1
        new[1:] |= own[1:] != own[:-1]
        lead = np.flatnonzero(new)
        self.names, self.row = m[lead], own[lead]
        self.first, self.last = starts[lead], starts[np.append(lead[1:], len(starts)) - 1]
        # grams that are the smallest of some window, to see where names stand and which occur twice in a segment
        padded = np.concatenate([np.zeros(width - 1, np.uint64), least, np.zeros(width - 1, np.uint64)])
        peak = np.flatnonzero(hashes == _sliding(padded, width, False)[: len(hashes)])
        _, code = np.unique(np.concatenate([hashes[peak], self.names]), return_inverse=True)
        marks = np.sort((code[: len(peak)].astype(np.int64) << 34) | peak)
        base = code[len(peak) :].astype(np.int64) << 34
        at = np.searchsorted(marks, base | self.first)
        self.anchor = marks[at] & ((1 << 34) - 1)
        self.inner = np.searchsorted(marks, base | (self.last + width)) - at > 1

    def text(self, k: int) -> memoryview:
        return self.data[self.first[k] : self.last[k] + self.length].data

    def digests(self, at: np.ndarray, seed: int) -> np.ndarray:
        """128 bits that stand for the bytes of the segments at these places, as two columns."""
        from xxhash import xxh3_128_digest

        return np.frombuffer(b"".join(xxh3_128_digest(self.text(k), seed) for k in at.tolist()), np.int64).reshape(-1, 2)


def _column(values: np.ndarray) -> pa.Array:
    return pa.array(values.view(np.int64) if values.dtype == np.uint64 else values)


def _names(texts: DataFrame, length: int) -> DataFrame:
    """name, n: how often each name occurs, counted within a batch first."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            s = Segments(*flat_text(b.column("text")), length, GRAM)
            names, lead, n = np.unique(s.names, return_index=True, return_counts=True)
            inner = np.zeros(len(names), bool)
            np.logical_or.at(inner, np.searchsorted(names, s.names), s.inner)
            yield pa.RecordBatch.from_arrays([_column(names), pa.array((n + inner).astype(np.int32))], ["name", "n"])

    return map_arrow(texts.select("text"), each, "name long, n int").groupBy("name").agg(F.sum("n").alias("n"))


def _names_bitmap(rows: DataFrame, column: str) -> np.ndarray:
    """A bitmap of the lowest bits of a column of hashes."""
    bits = filter_bits(rows.count())
    return bitmap(rows, F.pmod(F.col(column), F.lit(bits)), bits)


def _seen(bits: np.ndarray, names: np.ndarray) -> np.ndarray:
    return is_set(bits, (names & np.uint64(8 * len(bits) - 1)).astype(np.int64))


def _candidates(texts: DataFrame, shared, length: int, seed: int) -> DataFrame:
    """The segments whose names pass the filter: key of the document, where, name, digests."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            _, offsets = flat = flat_text(b.column("text"))
            s = Segments(*flat, length, GRAM)
            k = np.flatnonzero(_seen(shared.value, s.names))
            rows, d = pa.array(s.row[k]), s.digests(k, seed)
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id").take(rows), b.column("text_hash").take(rows), pa.array(s.first[k] - offsets[s.row[k]]), pa.array((s.last - s.first + 1)[k]), _column(s.names[k]), pa.array(d[:, 0]), pa.array(d[:, 1]), pa.array(s.inner[k])],
                ["doc_id", "text_hash", "first", "windows", "name", "d1", "d2", "inner"],
            )

    return map_arrow(texts, each, "doc_id long, text_hash long, first long, windows long, name long, d1 long, d2 long, inner boolean")


def _segment_bytes(texts: DataFrame, shared, length: int, seed: int) -> DataFrame:
    """name, d1, d2, lead (the leading tokens of the suffix at the gram) and bytes of the segments whose names pass the filter, each once a batch."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            s = Segments(*flat_text(b.column("text")), length, GRAM)
            k = np.flatnonzero(_seen(shared.value, s.names))
            if len(k):
                d = s.digests(k, seed)
                one = np.unique(d, axis=0, return_index=True)[1]
                k, d = k[one], d[one]
                leads = [s.data[p : p + GRAM].tobytes() for p in s.anchor[k].tolist()]
                yield pa.RecordBatch.from_arrays([_column(s.names[k]), pa.array(d[:, 0]), pa.array(d[:, 1]), pa.array(leads, pa.binary()), pa.array([bytes(s.text(x)) for x in k.tolist()], pa.binary())], ["b_name", "b_d1", "b_d2", "lead", "bytes"])

    return map_arrow(texts.select("text"), each, "b_name long, b_d1 long, b_d2 long, lead binary, bytes binary")


def tied_windows(group: np.ndarray, windows: np.ndarray) -> np.ndarray:
    """Which rows of windows (n x length bytes) equal another row of their group, by multikey quicksort on 8-byte tokens.

    Rows are ordered by group and first token; only rows still tied with a neighbour go on to the next token.
    """
    n, length = windows.shape
    padded = np.zeros((n, -(-length // 8) * 8), np.uint8)
    padded[:, :length] = windows
    tokens = padded.view(">u8")
    alive, part = np.arange(n), group.astype(np.int64)
    for k in range(tokens.shape[1]):
        token = tokens[alive, k].astype(np.uint64)
        order = np.lexsort((token, part))
        part, token, alive = part[order], token[order], alive[order]
        new = np.ones(len(alive), bool)
        new[1:] = (part[1:] != part[:-1]) | (token[1:] != token[:-1])
        single = new & np.append(new[1:], True)
        part = np.cumsum(new)[~single]
        alive = alive[~single]
        if not len(alive):
            break
    out = np.zeros(n, bool)
    out[alive] = True
    return out


def _runs(flags: np.ndarray) -> list[dict]:
    edge = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    return [{"lo": int(a), "hi": int(b) - 1} for a, b in zip(edge[::2], edge[1::2], strict=True)]


_RUNS = pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())]))


def _sorted_buckets(residue: DataFrame, length: int, window_limit: int = 50_000) -> DataFrame:
    """For each segment of the residue the runs of its windows that occur again in the residue of its name."""

    def flush(rows: list[tuple]) -> pa.RecordBatch:
        names = np.array([r[0] for r in rows], np.int64)
        views = [np.lib.stride_tricks.sliding_window_view(np.frombuffer(r[3], np.uint8), length) for r in rows]
        sizes = np.array([len(v) for v in views])
        tied = tied_windows(np.repeat(np.unique(names, return_inverse=True)[1], sizes), np.concatenate(views))
        ends = np.cumsum(sizes)
        runs = [_runs(tied[e - n : e]) for e, n in zip(ends, sizes, strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(names), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64()), pa.array(runs, _RUNS)], ["r_name", "r_d1", "r_d2", "runs"])

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            for row in zip(*(b.column(c).to_pylist() for c in ("name", "d1", "d2", "bytes")), strict=True):
                if size > window_limit and row[0] != held[-1][0]:
                    yield flush(held)
                    held, size = [], 0
                held.append(row)
                size += len(row[3]) - length + 1
        if held:
            yield flush(held)

    return map_arrow(residue, each, "r_name long, r_d1 long, r_d2 long, runs array<struct<lo:long,hi:long>>")


def _split_windows(residue: DataFrame, length: int, seed: int) -> DataFrame:
    """The same for names with too many windows for one task: a row for each window, sorted over all buckets.

    A row has the window's leading token, a 128-bit digest of it and its place. The splitters are sampled over all of
    these, so that equal windows may lie in several buckets; equal ones are neighbours in the order, and a window that is
    alone at the edge of its bucket is compared with the edges of the others.
    """

    def explode(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        for b in batches:
            for name, d1, d2, data in zip(*(b.column(c).to_pylist() for c in ("name", "d1", "d2", "bytes")), strict=True):
                n, view = len(data) - length + 1, memoryview(data)
                digest = np.frombuffer(b"".join(xxh3_128_digest(view[k : k + length], seed) for k in range(n)), np.int64).reshape(-1, 2)
                token = np.lib.stride_tricks.sliding_window_view(np.frombuffer(data, np.uint8), 8)[:n].copy().view(">u8").ravel().astype(np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(n, v)) for v in (name, d1, d2)] + [pa.array(np.arange(n)), pa.array(token), pa.array(digest[:, 0]), pa.array(digest[:, 1])], ["r_name", "r_d1", "r_d2", "at", "token", "w1", "w2"])

    rows = map_arrow(residue, explode, "r_name long, r_d1 long, r_d2 long, at long, token long, w1 long, w2 long")
    order = ["token", "w1", "w2", "r_d1", "r_d2", "at"]
    buckets = int(residue.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = rows.repartitionByRange(buckets, *order).sortWithinPartitions(*order)
    names = ["r_name", "r_d1", "r_d2", "at", "w1", "w2", "tied"]

    def neighbours(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows that equal a neighbour, and the rows at both edges; the last row of a batch waits for the next batch."""
        held, first, out = None, True, None
        for b in batches:
            if not b.num_rows:
                continue
            x = np.stack([b.column(c).to_numpy() for c in names[:6]], axis=1)
            x = x if held is None else np.concatenate([held[0], x])
            same = (x[1:, 4] == x[:-1, 4]) & (x[1:, 5] == x[:-1, 5])
            tied = np.concatenate([[held[1] if held else False], same]) | np.append(same, False)
            edge = np.zeros(len(x), bool)
            edge[0], first = first, False
            out = (tied | edge)[:-1]
            yield pa.RecordBatch.from_arrays([pa.array(x[:-1][out, k]) for k in range(6)] + [pa.array(tied[:-1][out])], names)
            held = x[-1:], bool(tied[-1])
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(held[0][:, k]) for k in range(6)] + [pa.array([held[1]])], names)

    compared = written(map_arrow(placed, neighbours, "r_name long, r_d1 long, r_d2 long, at long, w1 long, w2 long, tied boolean"), "compared_windows")
    # at most two rows a bucket are not tied yet; they are tied if their window comes again among all rows kept
    alone = compared.where("NOT tied")
    other = alone.select(F.col("w1").alias("v1"), F.col("w2").alias("v2")).distinct()
    again = compared.join(F.broadcast(other), (F.col("w1") == F.col("v1")) & (F.col("w2") == F.col("v2"))).groupBy("v1", "v2").agg(F.count("*").alias("n")).where("n > 1")
    across = alone.join(again, (F.col("w1") == F.col("v1")) & (F.col("w2") == F.col("v2")), "left_semi")
    tied = compared.where("tied").union(across)
    return tied.groupBy("r_name", "r_d1", "r_d2").agg(F.collect_list(F.struct(F.col("at").alias("lo"), F.col("at").alias("hi"))).alias("runs"))


def repeated_spans(docs: DataFrame, length: int = 200, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, text_hash, windows: for each document with any, the runs of starts (lo to hi) of windows that occur again."""
    texts = id_and_text(docs, id_col, text_col).withColumn("text_hash", F.xxhash64("text"))
    spark, seed = docs.sparkSession, secrets.randbits(63)
    repeated = written(_names(texts, length).where("n > 1").select("name"), "repeated_names")
    found = written(_candidates(texts, spark.sparkContext.broadcast(_names_bitmap(repeated, "name")), length, seed), "segments")
    classes = found.groupBy("name", "d1", "d2").agg(F.count("*").alias("copies"), F.max("inner").alias("inner"), F.max("windows").alias("windows"))
    classes = written(classes, "segment_classes")
    per_name = classes.groupBy("name").agg(F.count("*").alias("classes"), F.max("inner").alias("any_inner"), F.sum("windows").alias("load")).where("classes > 1 OR any_inner")
    open_names = written(per_name.select(F.col("name").alias("o_name"), "load", "classes"), "open_names")
    raw = _segment_bytes(texts, spark.sparkContext.broadcast(_names_bitmap(open_names, "o_name")), length, seed)
    one = raw.groupBy("b_name", "b_d1", "b_d2").agg(F.first("lead").alias("lead"), F.first("bytes").alias("bytes"))
    n = classes.count()
    named = one.select(F.col("b_name").alias("name"), F.col("b_d1").alias("d1"), F.col("b_d2").alias("d2"), "lead", "bytes")
    residue = written(left_join(named, open_names, {"name": "o_name"}, ["load"], "classes", n, F.xxhash64("d1")).where("load IS NOT NULL"), "residue")
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    local = residue.where(F.col("load") <= LOCAL).repartitionByRange(buckets, "lead", "name").sortWithinPartitions("lead", "name", "d1", "d2")
    runs = _sorted_buckets(local, length).union(_split_windows(residue.where(F.col("load") > LOCAL), length, seed))
    runs = written(runs.where(F.size("runs") > 0), "tied_runs")
    result = classes.drop("windows").join(runs, (F.col("name") == F.col("r_name")) & (F.col("d1") == F.col("r_d1")) & (F.col("d2") == F.col("r_d2")), "left")
    result = result.where("copies > 1 OR runs IS NOT NULL").select(F.col("name").alias("x_name"), F.col("d1").alias("x_d1"), F.col("d2").alias("x_d2"), "copies", "runs")
    hits = left_join(found, result, {"d1": "x_d1", "d2": "x_d2", "name": "x_name"}, ["copies", "runs"], "copies", found.count(), F.xxhash64("doc_id", "first")).where("copies IS NOT NULL")
    whole = F.array(F.struct(F.col("first").alias("lo"), (F.col("first") + F.col("windows") - 1).alias("hi")))
    part = F.transform("runs", lambda r: F.struct((F.col("first") + r["lo"]).alias("lo"), (F.col("first") + r["hi"]).alias("hi")))
    marked = hits.select("doc_id", "text_hash", F.when(F.col("copies") > 1, whole).otherwise(part).alias("runs"))
    return marked.groupBy("doc_id", "text_hash").agg(F.flatten(F.collect_set("runs")).alias("windows"))


def remove_repeats(docs: DataFrame, length: int = 200, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """One row per row of docs: doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and kept_bytes, what remains, on request).

    A byte goes when a string of length bytes that covers it also starts elsewhere, in the same document or another;
    strings are judged on the input and never cross documents. Null counts as empty; shorter texts stay whole; rows that
    repeat an id and text are copies of each other; a null id stays null; an empty table gives no rows; other columns
    are not read.
    """
    texts = id_and_text(docs, id_col, text_col).withColumn("text_hash", F.xxhash64("text"))
    spans = repeated_spans(docs, length, id_col, text_col).withColumnsRenamed({"doc_id": "s_id", "text_hash": "s_hash"})
    joined = texts.join(spans, F.col("doc_id").eqNullSafe(F.col("s_id")) & (F.col("text_hash") == F.col("s_hash")), "left").select("doc_id", "text", "windows")

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            size, removed, n_spans, sha, kept = [], [], [], [], []
            windows = b.column("windows").to_pylist()
            column = pc.fill_null(b.column("text"), "")
            for k in range(b.num_rows):
                text = column[k].as_buffer().to_pybytes()
                rest, gone, count, at = [], 0, 0, 0
                for lo, hi in sorted((w["lo"], w["hi"]) for w in windows[k] or ()):
                    if lo > at or not count:
                        rest.append(text[at:lo])
                        count += 1
                        gone += hi + length - lo
                        at = hi + length
                    elif hi + length > at:
                        gone += hi + length - at
                        at = hi + length
                rest.append(text[at:])
                out = b"".join(rest)
                size.append(len(text))
                removed.append(gone)
                n_spans.append(count)
                sha.append(hashlib.sha256(out).hexdigest())
                kept.append(out if with_text else None)
            arrays = [b.column("doc_id"), pa.array(size, pa.int64()), pa.array(removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(sha, pa.string())]
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(kept, pa.binary())] if with_text else arrays, [*names, "kept_bytes"] if with_text else names)

    return map_arrow(joined, each, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept_bytes binary" * with_text)
