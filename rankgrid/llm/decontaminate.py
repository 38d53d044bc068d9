"""Benchmark passages in documents by spaced seeds: masks that skip word positions, so that substituted words don't hide a passage."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.pretokens import HashIndex
from rankgrid.llm.textblocks import LOWER, WHITE, flat_text, map_arrow, mix, small_batches, span_hash, word_spans
from rankgrid.llm.token_counts import id_and_text

#: Words of a window that must overlap, and the share of them, in percent, that must agree.
WINDOW, PERCENT = 13, 80
#: Masks for full windows: every window of 13 words with at most 2 substituted is hit by one of them at some offset.
MASKS = ((0, 1, 2, 4, 6, 7), (0, 1, 3, 6, 7, 8))
#: Words of benchmark text in one broadcast: about 100 MB of tables. A larger benchmark is scanned against in blocks.
BLOCK_WORDS = 2_000_000
#: Distances at which a repeated seed is not looked up again; hits worked out at once.
REPEATS, EXPANDED = 3, 1 << 20

#: White space and ASCII punctuation end a word, so that neither counts in a comparison.
BREAKS = WHITE.copy()
BREAKS[[c for c in range(33, 127) if not chr(c).isalnum()]] = True


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    starts, ends, first = word_spans(data, offsets, BREAKS)
    return span_hash(LOWER[data], starts, ends), first


def allowed(n: int) -> int:
    """Substitutions that leave PERCENT of n words."""
    return n - -(-n * PERCENT // 100)


def masks_for(n: int) -> tuple[tuple[int, ...], ...]:
    """Masks for an item of n words; a short item gets runs that its allowed substitutions can't all break."""
    if n >= WINDOW:
        return MASKS
    e = allowed(n)
    return (tuple(range(max(1, (n - e) // (e + 1)))),)


@dataclass
class Benchmark:
    """Items as word numbers (from 1, 0 is any other word) and the seeds of each mask."""

    item_ids: np.ndarray
    first: np.ndarray
    words: np.ndarray
    vocabulary: np.ndarray
    seeds: list[tuple[tuple[int, ...], np.ndarray, np.ndarray, np.ndarray]]  # mask, keys, first posting, word positions

    def indexes(self) -> tuple[HashIndex, list[HashIndex]]:
        def of(keys: np.ndarray) -> HashIndex:
            out = HashIndex(max(len(keys), 1))
            out.add(keys, np.arange(len(keys), dtype=np.int32))
            return out

        return of(self.vocabulary), [of(keys) for _, keys, _, _ in self.seeds]


def _keys(words: np.ndarray, at: np.ndarray, mask: tuple[int, ...]) -> np.ndarray:
    h = np.full(len(at), len(mask), np.uint64)
    for o in mask:
        h = mix(h ^ words[at + o].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
    return h | np.uint64(1)


def benchmark_tables(ids: list, texts: list[str]) -> Benchmark:
    data, offsets = flat_text(pa.array(texts, pa.string()))
    hashes, first = words_of(data, offsets)
    vocabulary, words = np.unique(hashes, return_inverse=True)
    words = words.astype(np.int64) + 1
    sizes = np.diff(first)
    by_mask: dict[tuple[int, ...], list[np.ndarray]] = {}
    for n in np.unique(sizes[sizes > 0]).tolist():
        for mask in masks_for(n):
            span = mask[-1] + 1
            starts = first[:-1][sizes == n]
            by_mask.setdefault(mask, []).append((starts[:, None] + np.arange(n - span + 1)[None, :]).ravel())
    seeds = []
    for mask, parts in by_mask.items():
        at = np.concatenate(parts)
        keys = _keys(words, at, mask)
        order = np.argsort(keys, kind="stable")
        keys, starts = np.unique(keys[order], return_index=True)
        seeds.append((mask, keys, np.append(starts, len(order)), at[order]))
    return Benchmark(np.array(ids, np.int64), first, words, vocabulary, seeds)


class Scanner:
    def __init__(self, bench: Benchmark):
        self.bench = bench
        self.vocabulary, self.seeds = bench.indexes()
        self.thinned = [self._thinned(keys, postings, places) for _, keys, postings, places in bench.seeds]

    def _thinned(self, keys: np.ndarray, postings: np.ndarray, places: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For d = 0 to REPEATS, the postings that have none of their key d words before in their item (for 0 all): first
        place and number for each d and key, and the postings one list after another.

        Where a text has the same key d words before, only these need a look: any other hit is the one d words before on
        both sides, at the same shift. A word that a text and an item repeat is so not expanded into all its pairs.
        """
        key = np.repeat(np.arange(len(keys)), np.diff(postings))
        key_at = np.full(len(self.bench.words) + 1, -1)
        key_at[places] = key
        item = np.searchsorted(self.bench.first, places, "right") - 1
        firsts, counts, lists, base = [], [], [], 0
        for d in range(REPEATS + 1):
            before = places - d
            keep = np.ones(len(places), bool) if d == 0 else (before < self.bench.first[item]) | (key_at[before] != key)
            n = np.bincount(key[keep], minlength=len(keys))
            firsts.append(base + np.cumsum(n) - n)
            counts.append(n)
            lists.append(places[keep])
            base += len(lists[-1])
        return np.stack(firsts), np.stack(counts), np.concatenate(lists)

    def hits(self, column: pa.Array) -> list[tuple[int, int, int, int, int]]:
        """(row, item, first word, words compared, words equal) for each row and item with an overlap."""
        b = self.bench
        hashes, first = words_of(*flat_text(column))
        words = self.vocabulary.find(hashes).astype(np.int64) + 1
        row_of = np.repeat(np.arange(len(first) - 1), np.diff(first))
        found = []
        wide = len(words) + len(b.words) + 1
        for (mask, _, _, _), index, (firsts, sizes, places) in zip(b.seeds, self.seeds, self.thinned, strict=True):
            span = mask[-1] + 1
            if len(words) < span:
                continue
            n = len(words) - span + 1
            usable = row_of[:n] == row_of[span - 1 :]
            for o in mask:
                usable &= words[o : o + n] > 0
            at = np.flatnonzero(usable)
            seed = index.find(_keys(words, at, mask))
            at, seed = at[seed >= 0], seed[seed >= 0]
            key_of = np.full(len(words), -1)
            key_of[at] = seed
            variant = np.zeros(len(at), np.int64)
            for d in range(REPEATS, 0, -1):
                ago = np.maximum(at - d, 0)
                variant[(at >= d) & (key_of[ago] == seed) & (row_of[ago] == row_of[at])] = d
            start, counts = firsts[variant, seed], sizes[variant, seed]
            stops = np.cumsum(counts)
            lo = 0
            while lo < len(at):
                hi = max(lo + 1, int(np.searchsorted(stops, (stops[lo - 1] if lo else 0) + EXPANDED, "right")))
                n_each = counts[lo:hi]
                where = places[np.repeat(start[lo:hi] - (np.cumsum(n_each) - n_each), n_each) + np.arange(n_each.sum())]
                item = np.searchsorted(b.first, where, "right") - 1
                t = np.repeat(at[lo:hi], n_each)
                # one number for the document, the item and the shift between them
                found.append(np.unique((row_of[t] * len(b.item_ids) + item) * wide + (t - where + len(b.words))))
                lo = hi
        if not found:
            return []
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        # one comparison for each document, item and shift between them
        for code in np.unique(np.concatenate(found)).tolist():
            pair, shift = divmod(code, wide)
            (row, item), shift = divmod(pair, len(b.item_ids)), shift - len(b.words)
            lo, hi = max(b.first[item], first[row] - shift), min(b.first[item + 1], first[row + 1] - shift)
            need = int(min(WINDOW, b.first[item + 1] - b.first[item]))
            if hi - lo < need:
                continue
            same = np.concatenate([[0], np.cumsum(b.words[lo:hi] == words[lo + shift : hi + shift])])
            good = np.flatnonzero(same[need:] - same[:-need] >= need - allowed(need))
            if len(good):
                s, e = int(good[0]), int(good[-1]) + need
                mark = (int(same[e] - same[s]), e - s, int(lo + shift + s - first[row]))
                best[row, item] = max(best.get((row, item), (0, 0, 0)), mark)
        return [(row, item, at, n, equal) for (row, item), (equal, n, at) in best.items()]


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", block_words: int = BLOCK_WORDS) -> DataFrame:
    """One row for each document and benchmark item that overlap: doc_id, item_id, first_word, n_compared, n_equal, contaminated (true), kept (false).

    Words are runs without white space and ASCII punctuation, A-Z lower-cased. They overlap when, shifted against each
    other, some window of 13 words (or the whole of a shorter item) agrees in 80 percent of its words. Null, empty and
    wordless texts, and wordless items, overlap with nothing; repeated rows are judged each; a null id stays null, a null
    item id becomes -1; empty tables give no rows; long texts are read whole; other columns are not read.

    The benchmark is the stated query set: blocks of up to block_words words are broadcast one after another, whatever
    its size, and documents are never shuffled.
    """
    spark = docs.sparkSession
    texts = id_and_text(docs, id_col, text_col)
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), F.coalesce(F.col(item_text).cast("string"), F.lit("")).alias("text"))
    total = items.agg(F.sum(F.size(F.split("text", r"\s+")))).first()[0] or 0
    blocks = max(1, -(-int(total) // block_words))
    out = None
    for k in range(blocks):
        rows = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == k).orderBy("item_id", "text").collect()
        bench = benchmark_tables([r["item_id"] if r["item_id"] is not None else -1 for r in rows], [r["text"] for r in rows])
        part = _scan(texts, spark.sparkContext.broadcast(bench))
        out = part if out is None else out.union(part)
    return out


def _scan(texts: DataFrame, shared) -> DataFrame:
    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bench = shared.value
        scanner = Scanner(bench)
        for b in small_batches(batches, "text"):
            rows = scanner.hits(b.column("text"))
            if rows:
                r, item, at, n, equal = (np.array(x, np.int64) for x in zip(*rows, strict=True))
                yes = np.ones(len(r), bool)
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id").take(pa.array(r)), pa.array(bench.item_ids[item]), pa.array(at), pa.array(n), pa.array(equal), pa.array(yes), pa.array(~yes)],
                    ["doc_id", "item_id", "first_word", "n_compared", "n_equal", "contaminated", "kept"],
                )

    return map_arrow(texts, each, "doc_id long, item_id long, first_word long, n_compared long, n_equal long, contaminated boolean, kept boolean")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the documents that overlap with a benchmark item; columns stay as they are."""
    gone = contaminated(docs, benchmark, id_col, text_col).select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(gone, F.col(id_col) == F.col("__gone"), "left_anti")
