"""Documents cut into token pieces and packed into sequences of a fixed capacity by the sum-of-squares rule."""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.pretokens import broadcast_vocabulary, encoder
from rankgrid.llm.textblocks import map_arrow, small_batches
from rankgrid.llm.token_counts import id_and_text, texts_of
from rankgrid.session import written

#: Pieces packed together by one task; fixes the memory of a task, and costs at most a few sequences each.
PER_GROUP = 16_000


def token_pieces(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: a document's ids and an end id, whole if they fit, else the remainder first and then full pieces."""
    shared = broadcast_vocabulary(docs.sparkSession, tokenizer)

    def cut(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = encoder(shared.value)
        for b in small_batches(batches, "text"):
            flat, at = tokens.ids(texts_of(b))
            which, piece, start, length, crc = [], [], [], [], []
            for d in range(b.num_rows):
                ids = np.append(flat[at[d] : at[d + 1]], np.uint32(end_id)).astype("<u4")
                n = len(ids)
                cuts = [0, n] if n <= capacity else [0, *range(n % capacity or capacity, n + 1, capacity)]
                for k, (s, e) in enumerate(zip(cuts, cuts[1:], strict=False)):
                    which.append(d)
                    piece.append(k)
                    start.append(s)
                    length.append(e - s)
                    crc.append(zlib.crc32(ids[s:e].data))
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id").take(pa.array(which, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return map_arrow(id_and_text(docs, id_col, text_col), cut, "doc_id long, piece int, start long, length long, ids_crc32 long")


def sum_of_squares(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset) of each item, taken in the order given.

    An item goes where the sum over gaps of the squared number of open bins with that gap becomes smallest, the smaller
    remaining gap on a tie. A new bin is opened only where no open bin has room, as few bins are asked for.
    """
    count = np.zeros(capacity + 1, np.int64)
    open_bins: list[list[int]] = [[] for _ in range(capacity + 1)]
    bins, offsets, n = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64), 0
    never = np.int64(1 << 60)
    for k, s in enumerate(lengths.tolist()):
        have = count[s:capacity]
        change = np.where(have > 0, -2 * have, never)
        change[1:] += 2 * count[1 : capacity - s] + 1
        best = int(change.argmin()) if len(change) else -1
        if best < 0 or have[best] == 0:
            b, gap, n = n, capacity, n + 1
        else:
            gap = s + best
            b = open_bins[gap].pop()
            count[gap] -= 1
        bins[k], offsets[k] = b, capacity - gap
        if gap > s:
            open_bins[gap - s].append(b)
            count[gap - s] += 1
    return bins, offsets


def pack_pieces(pieces: DataFrame, capacity: int = 2048, per_group: int = PER_GROUP) -> DataFrame:
    """pieces with sequence_id and offset. Pieces are dealt by hash into groups of about per_group, each packed on its own."""
    groups = max(1, math.ceil(pieces.count() / per_group))

    def pack(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["length", "doc_id", "piece", "ids_crc32"], ascending=[False, True, True, True], kind="stable")
        bins, offsets = sum_of_squares(rows["length"].to_numpy(), capacity)
        return rows.drop(columns="deal").assign(sequence_id=(int(key[0]) << 32) + bins, offset=offsets)

    dealt = pieces.withColumn("deal", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(groups)).cast("int"))
    return dealt.groupBy("deal").applyInPandas(pack, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are one piece of the end id alone; repeated rows are packed each; a null id stays null; ties in
    length go by id, piece and content; an empty table gives no rows; other columns are not read.
    """
    return pack_pieces(written(token_pieces(docs, tokenizer, capacity, end_id, id_col, text_col), "token_pieces"), capacity)
