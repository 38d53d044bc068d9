"""Near duplicates: fast similarity sketches, banding, and a check of every link on the full shingle sets.

Texts with equal sets are one class, so copies are never expanded. Within a bucket of equal bands members are first
compared with one member only, drawn anew in each bucket. Where that leaves a bucket in more than one component its
members are dealt into blocks, and pairs of blocks are compared inside tasks: no row stands for a pair, no task holds
more than two blocks, and no pair of a bucket that could join two components stays unchecked.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.components import components
from rankgrid.llm.skew import bitmap, copied, dealt, filter_bits, heavy_keys, is_set, left_join
from rankgrid.llm.textblocks import flat_text, map_arrow, mix, sliding_hash, small_batches, word_hashes
from rankgrid.llm.token_counts import id_and_text
from rankgrid.session import written

#: Coordinates of a sketch (a power of two) and coordinates in a band. A pair of similarity 0.8 shares no band with probability 3e-6.
COORDINATES, BAND = 256, 6
#: Members of a block; members up to which open buckets that overlap are compared as one group.
BLOCK, JOINT = 256, 8192
#: Bytes of text whose hashes a worker holds at once.
BATCH = 1 << 20


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int) -> list[np.ndarray]:
    """For each document the sorted distinct 64-bit hashes of its width-word shingles; fewer words make one shingle, no word none."""
    words, first = word_hashes(data, offsets)
    shingles = sliding_hash(words, width)
    out = []
    for s, e in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if e - s >= width:
            out.append(np.unique(shingles[s : e - width + 1]))
        elif e > s:
            out.append(sliding_hash(words[s:e], e - s))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


_SEEDS = mix(np.arange(1, 2 * COORDINATES + 1, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95))


def sketch(elements: np.ndarray, t: int = COORDINATES) -> np.ndarray:
    """A fast similarity sketch: in each of the first t rounds every element falls into a random bin, in round t + j all
    fall into bin j; a bin keeps the smallest value of the earliest round that reaches it. Two sketches agree in a
    coordinate with the probability of the sets' similarity, and 2t rounds fill every bin of a set that isn't empty."""
    out, filled, left = np.zeros(t, np.uint64), np.zeros(t, bool), t
    shift = np.uint64(64 - (t - 1).bit_length())
    for r in range(2 * t):
        values = mix(elements ^ _SEEDS[r])
        if r < t:
            values.sort()
            bins = (values >> shift).astype(np.int64)
            lead = np.ones(len(bins), bool)
            lead[1:] = bins[1:] != bins[:-1]
            bins, values = bins[lead], values[lead]
            new = ~filled[bins]
            bins, values = bins[new], values[new]
        else:
            if filled[r - t]:
                continue
            bins, values = np.array([r - t]), values.min(keepdims=True)
        out[bins], filled[bins] = values ^ _SEEDS[r], True
        left -= len(bins)
        if not left:
            break
    return out


def bands_of(signature: np.ndarray, rows: int = BAND) -> np.ndarray:
    n = len(signature) // rows
    up = mix(np.arange(1, rows + 1, dtype=np.uint64))
    return mix((signature[: n * rows].reshape(n, rows) * (up | np.uint64(1))).sum(axis=1, dtype=np.uint64) + np.arange(n, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def digests(docs: DataFrame, width: int) -> DataFrame:
    """doc_id, n_shingles, s1 and s2 (a cryptographic digest of the whole sorted set: equal ones are equal sets), bands."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            sets = shingle_sets(*flat_text(b.column("text")), width)
            hashes, bands = np.zeros((len(sets), 2), np.int64), []
            for k, s in enumerate(sets):
                if len(s):
                    hashes[k] = np.frombuffer(hashlib.blake2b(s.data, digest_size=16).digest(), np.int64)
                    bands.append(bands_of(sketch(s)).view(np.int64))
                else:
                    bands.append(np.zeros(0, np.int64))
            at = np.concatenate([[0], np.cumsum([len(x) for x in bands])])
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), pa.array([len(s) for s in sets], pa.int64()), pa.array(np.ascontiguousarray(hashes[:, 0])), pa.array(np.ascontiguousarray(hashes[:, 1])), pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(np.concatenate(bands)))],
                ["doc_id", "n_shingles", "s1", "s2", "bands"],
            )

    return map_arrow(docs, each, "doc_id long, n_shingles long, s1 long, s2 long, bands array<long>")


def _set_rows(docs: DataFrame, wanted: DataFrame, n: int, width: int) -> DataFrame:
    """id, hashes (the set as bytes) of the documents in wanted (n rows), and of a few more that share a place in the filter."""
    spark = docs.sparkSession
    bits = filter_bits(n)
    shared = spark.sparkContext.broadcast(bitmap(wanted, F.pmod(F.xxhash64("id"), F.lit(bits)), bits))

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small_batches(batches, "text", BATCH):
            keep = np.flatnonzero(is_set(shared.value, b.column("place").to_numpy(zero_copy_only=False)))
            if len(keep):
                part = b.take(pa.array(keep))
                sets = shingle_sets(*flat_text(part.column("text")), width)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([s.tobytes() for s in sets], pa.binary())], ["id", "hashes"])

    placed = docs.withColumn("place", F.pmod(F.xxhash64("doc_id"), F.lit(bits)))
    return map_arrow(placed, each, "id long, hashes binary")


def verified(docs: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets have 100 * intersection >= percent * union."""
    n = 2 * pairs.count()
    ends = pairs.select(F.explode(F.array("a", "b")).alias("id"))
    wanted = ends.groupBy("id").agg(F.count("*").alias("uses"))
    found = _set_rows(docs, wanted, n, width).join(wanted.select(F.col("id").alias("want")), F.col("id") == F.col("want"), "left_semi")
    # the member that a hot bucket is compared with is in very many pairs: its set is copied, and its pairs are dealt over the copies
    heavy = heavy_keys(wanted, "id", "uses", n)
    sets = copied(written(found.groupBy("id").agg(F.max("hashes").alias("hashes")), "shingle_sets"), "id", heavy, "copy")
    named = dealt(dealt(pairs, "a", heavy, F.col("b"), "copy_a"), "b", heavy, F.col("a"), "copy_b")
    left = named.join(sets.withColumnsRenamed({"id": "id_a", "hashes": "set_a", "copy": "ca"}), (F.col("a") == F.col("id_a")) & (F.col("copy_a") == F.col("ca")))
    right = sets.withColumnsRenamed({"id": "id_b", "hashes": "set_b", "copy": "cb"})
    both = left.select("a", "b", "copy_b", "set_a").join(right, (F.col("b") == F.col("id_b")) & (F.col("copy_b") == F.col("cb"))).select("a", "b", "set_a", "set_b")

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for k, (x, y) in enumerate(zip(batch.column("set_a"), batch.column("set_b"), strict=True)):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                if 100 * min(len(x), len(y)) < percent * max(len(x), len(y)):
                    continue
                joined = np.sort(np.concatenate([x, y]), kind="stable")
                common = int((joined[1:] == joined[:-1]).sum())
                if 100 * common >= percent * (len(x) + len(y) - common):
                    keep.append(k)
            part = batch.take(pa.array(keep, pa.int64()))
            yield pa.RecordBatch.from_arrays([part.column("a"), part.column("b")], ["a", "b"])

    return map_arrow(both, each, "a long, b long")


def _block_links(rows: pd.DataFrame, percent: int) -> list[tuple[int, int]]:
    """Links between rows of different components that hold, enough of them to join what can be joined."""
    sets = [np.frombuffer(x, np.uint64) for x in rows["hashes"]]
    ids, sizes = rows["id"].to_numpy(), np.array([len(s) for s in sets])
    values, at, uses = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    row = np.repeat(np.arange(len(sets)), sizes)
    column = np.cumsum(uses > 1) - 1
    shared = uses[at] > 1
    row, column = row[shared], column[at[shared]]
    common = np.zeros((len(sets), len(sets)), np.float32)
    order = np.argsort(column, kind="stable")
    row, column = row[order], column[order]
    for lo in range(0, int(column[-1]) + 1 if len(column) else 0, 8192):
        s, e = np.searchsorted(column, [lo, lo + 8192])
        part = np.zeros((len(sets), 8192), np.float32)
        part[row[s:e], column[s:e] - lo] = 1
        common += part @ part.T
    common = common.astype(np.int64)
    hold = 100 * common >= percent * (sizes[:, None] + sizes[None, :] - common)
    component = rows["component"].to_numpy()
    parent = {c: c for c in component.tolist()}

    def root(c: int) -> int:
        while parent[c] != c:
            parent[c] = c = parent[parent[c]]
        return c

    out = []
    for i, j in np.argwhere(np.triu(hold & (component[:, None] != component[None, :]), 1)).tolist():
        x, y = root(component[i]), root(component[j])
        if x != y:
            parent[max(x, y)] = min(x, y)
            out.append((min(ids[i], ids[j]), max(ids[i], ids[j])))
    return out


def compared_in_blocks(docs: DataFrame, groups: DataFrame, width: int, percent: int) -> DataFrame:
    """Links (a, b) between members of different components within groups (gid, id, component), checked on full sets.

    The members of a group's largest component need no comparison with each other. They and the others are dealt by hash
    into blocks of about BLOCK members; each pair of a block of others with any block is one task's work. No task holds
    more than two blocks whatever the group's size, no row stands for a pair, and a group that is nearly one component
    costs its size times the number of the others.
    """
    spark = docs.sparkSession
    n = groups.count()
    sizes = groups.groupBy("gid", "component").agg(F.count("*").alias("n")).groupBy("gid").agg(F.max(F.struct("n", "component")).alias("most"), F.sum("n").alias("all"))
    blocks = lambda count: F.ceil(count / F.lit(BLOCK)).cast("int")
    sizes = sizes.select(F.col("gid").alias("g2"), F.col("most.component").alias("main"), blocks(F.col("most.n")).alias("main_blocks"), blocks(F.col("all") - F.col("most.n")).alias("other_blocks"), "all")
    known = left_join(groups, sizes, {"gid": "g2"}, ["main", "main_blocks", "other_blocks"], "all", n, F.xxhash64("id"))
    is_main = F.col("component") == F.col("main")
    members = known.select("gid", F.col("id").alias("member"), "component", "main_blocks", "other_blocks", is_main.alias("is_main"), F.pmod(F.xxhash64("id", F.lit(7)), F.when(is_main, F.col("main_blocks")).otherwise(F.col("other_blocks"))).cast("int").alias("own"))
    # a cell (i, j): block i of the others with their block j, or with block -1 - j of the largest component
    upto = lambda count: F.sequence(F.lit(0), count - 1)
    with_others = F.transform(upto(F.col("other_blocks")), lambda k: F.struct(F.least("own", k).alias("i"), F.greatest("own", k).alias("j")))
    with_main = F.transform(upto(F.col("main_blocks")), lambda k: F.struct(F.col("own").alias("i"), (-1 - k).alias("j")))
    main_cells = F.transform(upto(F.col("other_blocks")), lambda k: F.struct(k.alias("i"), (-1 - F.col("own")).alias("j")))
    cells = members.select("gid", "member", "component", F.explode(F.when(F.col("is_main"), main_cells).otherwise(F.concat(with_others, with_main))).alias("cell"))
    sets = _set_rows(docs, groups.select("id"), n, width).groupBy("id").agg(F.max("hashes").alias("hashes"))
    rows = cells.join(sets, F.col("member") == F.col("id")).select("gid", F.col("cell.i").alias("i"), F.col("cell.j").alias("j"), "id", "component", "hashes")
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 1)
    rows = rows.repartition(parts, "gid", "i", "j")

    def each(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame(_block_links(rows, percent), columns=["a", "b"], dtype="int64")

    return rows.groupBy("gid", "i", "j").applyInPandas(each, "a long, b long")


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, n_shingles, component_id (the smallest linked id), kept (doc_id = component_id).

    Words are runs without white space, A-Z lower-cased; documents are linked when their sets of width-word shingles have
    100 * intersection >= percent * union. Null, empty and blank texts have no shingles and no links. Rows that repeat an
    id count as one document, which with several texts is linked by the greatest of their sets; a null id is in its own component; an empty table gives no rows; long texts are read whole.
    """
    texts = id_and_text(docs, id_col, text_col)
    table = written(digests(texts, width), "set_digests")
    n_rows = table.count()
    most = n_rows * (COORDINATES // BAND)
    classes = written(table.where("n_shingles > 0 AND doc_id IS NOT NULL").groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("size")).withColumnsRenamed({"s1": "c1", "s2": "c2"}), "set_classes")
    # by the id too, so that a class of very many documents is in no one task
    is_rep = (F.col("doc_id") == F.col("rep")) & (F.col("s1") == F.col("c1")) & (F.col("s2") == F.col("c2"))
    members = table.where("n_shingles > 0").join(classes, is_rep, "left_semi").select(F.col("doc_id").alias("id"), F.explode("bands").alias("key"))
    # a member is named by id XOR key, so that the smallest name is another member in each bucket
    buckets = members.groupBy("key").agg(F.count("*").alias("n"), F.min(F.col("id").bitwiseXOR(F.col("key"))).alias("name")).where("n > 1").select(F.col("key").alias("k"), "n", F.col("name").bitwiseXOR(F.col("key")).alias("hub"))
    in_bucket = left_join(members, buckets, {"key": "k"}, ["hub", "n"], "n", most, F.xxhash64("id")).where("hub IS NOT NULL")
    shared = written(in_bucket.select("key", "id", "hub", "n"), "bucket_members")
    pairs = written(shared.where("id <> hub").select(F.least("id", "hub").alias("a"), F.greatest("id", "hub").alias("b")).distinct(), "pairs")
    links = written(verified(texts, pairs, width, percent), "links")
    labels = components(links)
    # buckets whose members, the compared one aside, are in several components: nothing says yet that these can't be joined
    named = shared.join(labels, F.col("id") == F.col("node"), "left").where("n > 2 AND id <> hub").select("key", "id", F.coalesce("component", "id").alias("component"))
    open_keys = named.groupBy("key").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.min("id").alias("lead"), F.count("*").alias("members")).where("low <> high").select(F.col("key").alias("ok"), "lead", "members")
    left = left_join(named, open_keys, {"key": "ok"}, ["lead"], "members", most, F.xxhash64("id")).where("lead IS NOT NULL")
    left = written(left.select("key", "id", "component", "lead"), "open_members")
    if not left.isEmpty():
        # open buckets that overlap are one group, so that its pairs are compared once; past a size each bucket stands alone
        joint = components(left.where("id <> lead").select(F.col("id").alias("a"), F.col("lead").alias("b")))
        each_id = left.join(joint.withColumnRenamed("component", "cluster"), F.col("id") == F.col("node"), "left").select("key", "id", "component", F.coalesce("cluster", "id").alias("cluster"))
        # counted in two steps, so that a large cluster is in no one task
        ids = each_id.groupBy("cluster", "id").agg(F.count("*").alias("rows")).groupBy(F.col("cluster").alias("c3")).agg(F.count("*").alias("size"), F.sum("rows").alias("rows"))
        each_id = left_join(each_id, ids, {"cluster": "c3"}, ["size"], "rows", most, F.xxhash64("id"))
        gid = F.when(F.col("size") <= JOINT, F.xxhash64(F.lit(0), F.col("cluster"))).otherwise(F.xxhash64(F.lit(1), F.col("key")))
        groups = written(each_id.select(gid.alias("gid"), "id", "component").distinct(), "open_groups")
        more = written(compared_in_blocks(texts, groups, width, percent), "links")
        if not more.isEmpty():
            labels = components(links.union(more))
    roots = classes.join(labels, F.col("rep") == F.col("node"), "left").select("c1", "c2", "size", F.coalesce("component", "rep").alias("root"))
    # documents without shingles or id are in no class: they go under a key of their own
    classless = (F.col("n_shingles") == 0) | F.col("doc_id").isNull()
    rows = table.select("doc_id", "n_shingles", F.when(classless, F.xxhash64("doc_id")).otherwise(F.col("s1")).alias("s1"), F.when(~classless, F.col("s2")).alias("s2"))
    rows = left_join(rows, roots, {"s1": "c1", "s2": "c2"}, ["root"], "size", n_rows, F.xxhash64("doc_id"))
    found = F.coalesce("root", "doc_id")
    return rows.select("doc_id", "n_shingles", found.alias("component_id"), F.col("doc_id").eqNullSafe(found).alias("kept"))


def drop_near_copies(docs: DataFrame, width: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one document of each component, the one of the smallest id; columns stay as they are."""
    gone = near_duplicates(docs, width, percent, id_col, text_col).where("NOT kept").select(F.col("doc_id").alias("__gone")).distinct()
    return docs.join(gone, F.col(id_col) == F.col("__gone"), "left_anti")
