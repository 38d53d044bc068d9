"""Token ids on disk: fixed-size blocks, transposed into byte or bit planes, each plane compressed, with an index of the chunks.

A store is a table of segments. A segment holds whole consecutive documents of one shard (a range of ids in ascending
order): the ids of its documents and their lengths, the compressed planes one after another, and for each block its
place, number of ids and the sizes of its planes. A segment can so be read alone, and a shard by its ascending segments.
The table is written by Spark's own committers, so that a lost executor leaves no part of a segment behind.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rankgrid.llm.pretokens import broadcast_vocabulary, encoder
from rankgrid.llm.textblocks import map_arrow, small_batches
from rankgrid.llm.token_counts import id_and_text, texts_of
from rankgrid.session import written

#: Ids in a block, and ids after which a segment is closed at the next document.
BLOCK, SEGMENT = 16_384, 1 << 19
SCHEMA = "shard int, segment int, first long, n_ids long, planes string, doc_ids array<long>, doc_lengths array<long>, index array<struct<place:long,ids:int,sizes:array<int>>>, payload binary"
_ARROW = pa.schema([
    ("shard", pa.int32()), ("segment", pa.int32()), ("first", pa.int64()), ("n_ids", pa.int64()), ("planes", pa.string()),
    ("doc_ids", pa.list_(pa.int64())), ("doc_lengths", pa.list_(pa.int64())),
    ("index", pa.list_(pa.struct([("place", pa.int64()), ("ids", pa.int32()), ("sizes", pa.list_(pa.int32()))]))), ("payload", pa.binary()),
])


def to_planes(ids: np.ndarray, kind: str) -> list[bytes]:
    """The planes of one block, lowest first; planes above the highest used one are left out."""
    raw = ids.astype("<u4").view(np.uint8).reshape(-1, 4)
    if kind == "byte":
        planes = [np.ascontiguousarray(raw[:, k]).tobytes() for k in range(4)]
    else:
        bits = np.unpackbits(raw, axis=1, bitorder="little")
        planes = [np.packbits(bits[:, k], bitorder="little").tobytes() for k in range(32)]
    while len(planes) > 1 and not any(planes[-1]):
        planes.pop()
    return planes


def from_planes(planes: list[bytes], n: int, kind: str) -> np.ndarray:
    if kind == "byte":
        raw = np.zeros((n, 4), np.uint8)
        for k, p in enumerate(planes):
            raw[:, k] = np.frombuffer(p, np.uint8)
        return raw.reshape(-1).view("<u4")
    bits = np.zeros((n, 32), np.uint8)
    for k, p in enumerate(planes):
        bits[:, k] = np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little")
    return np.packbits(bits, axis=1, bitorder="little").reshape(-1).view("<u4")


def encode_segment(ids: np.ndarray, kind: str, block: int = BLOCK, level: int = 1) -> tuple[list[dict], bytes]:
    import zstandard

    press = zstandard.ZstdCompressor(level=level)
    index, out, place = [], [], 0
    for at in range(0, len(ids), block):
        part = ids[at : at + block]
        packed = [press.compress(p) for p in to_planes(part, kind)]
        index.append({"place": place, "ids": len(part), "sizes": [len(p) for p in packed]})
        place += sum(map(len, packed))
        out += packed
    return index, b"".join(out)


def decode_segment(index: list[dict], payload: bytes, kind: str) -> np.ndarray:
    import zstandard

    grow = zstandard.ZstdDecompressor()
    out = [np.zeros(0, "<u4")]
    for entry in index:
        at, planes = entry["place"], []
        for size in entry["sizes"]:
            planes.append(grow.decompress(payload[at : at + size]))
            at += size
        out.append(from_planes(planes, entry["ids"], kind))
    return np.concatenate(out)


def write_store(docs: DataFrame, tokenizer: str, end_id: int = 2, planes: str = "byte", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The segments of all documents in ascending id order, written to the shared folder and opened again.

    Null and empty texts are the end id alone; rows that repeat an id follow each other in the order of their texts; a
    null id comes first; an empty table gives no segments; other columns are not read.
    """
    spark = docs.sparkSession
    shared = broadcast_vocabulary(spark, tokenizer)

    def segments(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens, shard = encoder(shared.value), TaskContext.get().partitionId()
        held, names, sizes, n, number, first = [], [], [], 0, 0, 0

        def close() -> pa.RecordBatch:
            index, payload = encode_segment(np.concatenate(held), planes)
            row = {"shard": shard, "segment": number, "first": first, "n_ids": n, "planes": planes, "doc_ids": names, "doc_lengths": sizes, "index": index, "payload": payload}
            return pa.RecordBatch.from_pylist([row], schema=_ARROW)

        for b in small_batches(batches, "text"):
            flat, at = tokens.ids(texts_of(b))
            ids, ends = np.insert(flat, at[1:], np.uint32(end_id)), at[1:] + np.arange(1, b.num_rows + 1)
            docs, lo = b.column("doc_id").to_pylist(), 0
            while lo < len(docs):
                # documents up to the first that fills the segment
                begin = int(ends[lo - 1]) if lo else 0
                hi = min(int(np.searchsorted(ends, begin + SEGMENT - n)) + 1, len(docs))
                held.append(ids[begin : ends[hi - 1]])
                names += docs[lo:hi]
                sizes += np.diff(ends[lo:hi], prepend=begin).tolist()
                n, lo = n + int(ends[hi - 1]) - begin, hi
                if n >= SEGMENT:
                    yield close()
                    held, names, sizes, number, first, n = [], [], [], number + 1, first + n, 0
        if held:
            yield close()

    shards = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ordered = id_and_text(docs, id_col, text_col).repartitionByRange(shards, "doc_id").sortWithinPartitions("doc_id", "text")
    return written(map_arrow(ordered, segments, SCHEMA), "token_store")


def read_documents(store: DataFrame) -> DataFrame:
    """From a store's segments: doc_id, start (ids of all documents before it), n_tokens, ids_crc32."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                ids = decode_segment(row["index"], row["payload"], row["planes"])
                ends = np.cumsum(row["doc_lengths"])
                starts = ends - row["doc_lengths"]
                crc = [zlib.crc32(ids[s:e].data) for s, e in zip(starts, ends, strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([row["shard"]] * len(crc), pa.int32()), pa.array(row["doc_ids"], pa.int64()), pa.array(starts + row["first"]), pa.array(row["doc_lengths"], pa.int64()), pa.array(crc, pa.int64())],
                    ["shard", "doc_id", "within", "n_tokens", "ids_crc32"],
                )

    docs = map_arrow(store, each, "shard int, doc_id long, within long, n_tokens long, ids_crc32 long")
    # one row a shard: as many as shuffle partitions, whatever the input
    sizes = store.groupBy("shard").agg(F.sum("n_ids").alias("ids"))
    bases = sizes.select(F.col("shard").alias("of_shard"), (F.sum("ids").over(Window.orderBy("shard")) - F.col("ids")).alias("base"))
    return docs.join(bases, F.col("shard") == F.col("of_shard")).select("doc_id", (F.col("base") + F.col("within")).alias("start"), "n_tokens", "ids_crc32")


def read_ids(store: DataFrame) -> DataFrame:
    """doc_id and its ids as an array, for readers of the store."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                ids = decode_segment(row["index"], row["payload"], row["planes"])
                at = pa.array(np.concatenate([[0], np.cumsum(row["doc_lengths"])]), pa.int32())
                yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.ListArray.from_arrays(at, pa.array(ids, pa.int64()))], ["doc_id", "ids"])

    return map_arrow(store, each, "doc_id long, ids array<long>")
