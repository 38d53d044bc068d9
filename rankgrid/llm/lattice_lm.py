"""Document likelihood under a unigram model over subword pieces, summed over all segmentations.

Pieces and their first weights come from an existing vocabulary (its scores are ranks, read as a power law); a few passes
of expectation maximisation over all distinct training words fit the weights. Words seen in training are further arcs of
the lattice, with their discounted share of all tokens; what the discount frees goes to the pieces. A document's lattice
falls apart at white space, so that its log probability is the sum over its words, each worked out once per distinct word.
Texts fall into a few classes by the function words they have; each class has its own weights, and a text's probability
is its class's share of the documents times its probability within the class.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.pretokens import HashIndex
from rankgrid.llm.textblocks import LOWER, SPREAD, closed, flat_text, map_arrow, mix, placed, small_batches, span_hash, span_hashes, word_spans
from rankgrid.llm.token_counts import id_and_text
from rankgrid.session import written

#: Distinct words held before a task sends them on; words whose values are broadcast.
HELD, FREQUENT = 400_000, 1 << 18
#: Fixed lists of function words that tell the classes apart; class 0 has none of them.
FUNCTION_WORDS = {
    1: "the of and to in is that it for was with as be this by at not are from or an which have".split(),
    2: "der die das und den von zu mit sich des auf für ist im dem nicht ein eine als auch werden einer".split(),
    3: "le la les des et du une est dans qui pour sur au par pas avec sont cette ou ces elle".split(),
    4: "el los las del y una por con se su para al lo como más pero sus o este".split(),
}
CLASSES = 1 + len(FUNCTION_WORDS)
#: The byte that starts each word in the lattice; it is white space and so in no word.
START = 0x20
#: Log probability of a word's bytes down to which its lattice is summed without logarithms.
LEAST_LOG = -500.0


@dataclass
class Pieces:
    """Hashes of the pieces as bytes, those that start a word with START, and log weights: of starting pieces among
    themselves, of the others together with the end of a word (the last weight). prefixes: hashes of what begins a piece
    and is none; without them every length is looked up at every place."""

    hashes: np.ndarray
    starting: np.ndarray
    longest: int
    log_p: np.ndarray
    prefixes: np.ndarray | None = None

    @property
    def end(self) -> float:
        return float(self.log_p[-1])

    def with_counts(self, counts: np.ndarray) -> Pieces:
        """Weights in proportion to counts; a small share of the old weights keeps every piece possible."""
        c = counts + 0.5 * np.exp(self.log_p)
        return Pieces(self.hashes, self.starting, self.longest, _normalised(c, self.starting), self.prefixes)


def _normalised(weights: np.ndarray, starting: np.ndarray) -> np.ndarray:
    out = np.empty_like(weights)
    first = np.append(starting, False)
    for part in (first, ~first):
        out[part] = np.log(weights[part]) - math.log(weights[part].sum())
    return out


def existing_pieces(model: str) -> Pieces:
    """The pieces of a sentencepiece model and all single bytes, with weights 1 / (100 + rank)."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model)
    weights: dict[bytes, float] = {}
    n = sp.get_piece_size()
    for i in range(n):
        if sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i):
            continue
        piece = sp.id_to_piece(i)
        raw = (chr(START) + piece[1:] if piece.startswith("▁") else piece).encode()
        if chr(START).encode() not in raw[1:] and raw.lower() == raw:
            weights[raw] = max(weights.get(raw, 0.0), 1 / (100 - sp.get_score(i)))
    least = 1 / (100 + n)
    for b in range(256):
        if b != START:
            weights.setdefault(bytes([b]), least)
        weights.setdefault(bytes([START]), least)
    names = sorted(weights)
    data, sizes = np.frombuffer(b"".join(names), np.uint8), np.array([len(x) for x in names])
    ends = np.cumsum(sizes)
    starting = np.array([x[0] == START for x in names])
    p = np.append(np.array([weights[x] for x in names]), 0.0)
    p[-1] = p[:-1][~starting].sum() / 3
    return Pieces(span_hash(data, ends - sizes, ends), starting, int(sizes.max()), _normalised(p, starting), _hash_words(sorted({x[:k] for x in names for k in range(1, len(x))} - weights.keys())))


class Lattice:
    """All segmentations of many words at once: words of equal length go through the recursion together."""

    def __init__(self, pieces: Pieces):
        self.pieces = pieces
        own, more = len(pieces.hashes), np.zeros(0, np.uint64) if pieces.prefixes is None else pieces.prefixes
        self.index = HashIndex(own + len(more))
        # a prefix that is no piece has the number after the last piece
        self.index.add(np.concatenate([pieces.hashes, more]), np.minimum(np.arange(own + len(more), dtype=np.int32), own))

    def _arcs(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Piece number of each arc [length - 1, position], -1 for none, over the words with START before each; word starts and sizes."""
        flat = np.frombuffer(b"".join(bytes([START]) + w for w in words), np.uint8)
        sizes = np.array([len(w) + 1 for w in words])
        ends = np.cumsum(sizes)
        left = np.repeat(ends, sizes) - np.arange(len(flat))
        every, own = np.arange(256), len(self.pieces.hashes)
        reach = min(self.pieces.longest, int(sizes.max(initial=0)))
        arcs = np.full((reach, len(flat)), -1, np.int32)
        at, sums = np.arange(len(flat)), np.zeros(len(flat), np.uint64)
        for n in range(1, reach + 1):
            # a longer piece begins only where this one, or what begins one, was found
            go = left[at] >= n
            at, sums = at[go], sums[go]
            sums = sums + placed(every, n - 1)[flat[at + n - 1]]
            found = self.index.find(closed(sums, n))
            arcs[n - 1, at] = np.where(found < own, found, -1)
            if self.pieces.prefixes is not None:
                at, sums = at[found >= 0], sums[found >= 0]
        return arcs, ends - sizes, sizes

    def _by_size(self, words: list[bytes], room: int = 1 << 19):
        """Words of one size: their places, the size, the arcs [length - 1, position, word], and the arcs' log weights."""
        arcs, starts, sizes = self._arcs(words)
        log_p = np.append(self.pieces.log_p[:-1], -np.inf)  # number -1 is no piece
        plain_p = np.exp(log_p)
        for size in np.unique(sizes).tolist():
            same = np.flatnonzero(sizes == size)
            reach = min(size, self.pieces.longest)  # no arc is longer than its word
            step = max(1, room // (size * reach))
            for k in range(0, len(same), step):
                rows = same[k : k + step]
                ids = arcs[:reach, starts[rows][None, :] + np.arange(size)[:, None]]
                # the longest arc that any of these words has
                reach_here = int(np.flatnonzero((ids >= 0).any(axis=(1, 2))).max(initial=0)) + 1
                ids = ids[:reach_here]
                # single bytes alone make a word, so that no sum is below their product: where that is far from the least
                # number there is, the recursion needs no logarithms
                plain = log_p[ids[0]].sum(axis=0) > LEAST_LOG
                for part, linear in ((plain, True), (~plain, False)):
                    if part.any():
                        which = ids if part.all() else ids[:, :, part]
                        yield rows[part], size, which, (plain_p if linear else log_p)[which], linear

    def _forward(self, p: np.ndarray, size: int, linear: bool) -> np.ndarray:
        """The sum (linear, or its log) over all segmentations of what is left of each place [position, word]."""
        add, times = (np.add, np.multiply) if linear else (np.logaddexp, np.add)
        f = np.full((size + 1, p.shape[2]), 0.0 if linear else -np.inf)
        f[0] = 1.0 if linear else 0.0
        for i in range(size):
            reach = min(size - i, len(p))
            f[i + 1 : i + 1 + reach] = add(f[i + 1 : i + 1 + reach], times(f[i], p[:reach, i]))
        return f

    def log_probability(self, words: list[bytes]) -> np.ndarray:
        """Natural log of the probability of each word, over all its segmentations."""
        out = np.full(len(words), -np.inf)
        for rows, size, _, p, linear in self._by_size(words):
            whole = self._forward(p, size, linear)[size]
            out[rows] = (np.log(whole) if linear else whole) + self.pieces.end
        return out

    def expected(self, words: list[bytes]) -> np.ndarray:
        """Expected uses of each piece, and of the end, over the words."""
        out = np.zeros(len(self.pieces.hashes) + 1)
        for _, size, ids, p, linear in self._by_size(words):
            add, times = (np.add, np.multiply) if linear else (np.logaddexp, np.add)
            f = self._forward(p, size, linear)
            back = np.empty_like(f)
            back[size] = 1.0 if linear else 0.0
            for i in range(size - 1, -1, -1):
                reach = min(size - i, len(p))
                onward = times(p[:reach, i], back[i + 1 : i + 1 + reach])
                back[i] = add.reduce(onward, axis=0)
                share = onward * (f[i] / f[size]) if linear else np.exp(onward + (f[i] - f[size]))
                # the weights of a place are not read again
                p[:reach, i] = share
                p[reach:, i] = 0.0
            used = ids >= 0
            out[:-1] += np.bincount(ids[used], weights=p[used], minlength=len(out) - 1)
            out[-1] += p.shape[2]
        return out


def held_out_fold(doc_id) -> F.Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(7)) == 2


class _Words:
    """The words of a batch: bytes, places, two hashes (128 bits that name a word), row of each, and the class of each row (most function words, the first class on a tie)."""

    def __init__(self, batch: pa.RecordBatch):
        data, offsets = flat_text(batch.column("text"))
        self.data = LOWER[data]
        self.starts, self.ends, self.first = word_spans(self.data, offsets)
        self.hashes, self.seconds = span_hashes(self.data, self.starts, self.ends, second=True)
        self.row = np.repeat(np.arange(batch.num_rows), np.diff(self.first))
        index, owner, seconds = _function_words()
        found = index.find(self.hashes)
        hit = (found >= 0) & (seconds[found] == self.seconds)
        score = np.bincount(self.row[hit] * CLASSES + owner[found[hit]], minlength=batch.num_rows * CLASSES).reshape(-1, CLASSES)
        self.kind = score.argmax(axis=1)


def _function_words() -> tuple[HashIndex, np.ndarray, np.ndarray]:
    if not _tables:
        words = [(w.encode(), k) for k, listed in FUNCTION_WORDS.items() for w in listed]
        index = HashIndex(len(words))
        names, seconds = _two_hashes([w for w, _ in words])
        index.add(names, np.arange(len(words), dtype=np.int32))
        _tables.append((index, np.array([k for _, k in words]), seconds))
    return _tables[0]


_tables: list[tuple[HashIndex, np.ndarray, np.ndarray]] = []


def _class_hash(hashes: np.ndarray, kind: np.ndarray) -> np.ndarray:
    return mix(hashes + kind.astype(np.uint64) * SPREAD)


def _distinct(h: np.ndarray, g: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First place of each distinct pair (h, g), which pair each place has, and how often each occurs."""
    _, lead, which, n = np.unique(h, return_index=True, return_inverse=True, return_counts=True)
    if (g[lead][which] != g).any():
        _, lead, which, n = np.unique(np.stack([h, g], axis=1), axis=0, return_index=True, return_inverse=True, return_counts=True)
        which = which.ravel()
    return lead, which, n


def _word_counts(texts: DataFrame) -> DataFrame:
    """word (lower-cased bytes), c0, c1, ... (uses in training documents of each class), n0, n1, ... (in all): counted within
    a task before the shuffle. The null word stands for the ends, one a document."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[bytes | None, int], tuple[int, int]] = {}

        def send() -> pa.RecordBatch:
            c = np.array(list(held.values()), np.int64).reshape(-1, 2)
            return pa.RecordBatch.from_arrays([pa.array([w for w, _ in held], pa.binary()), pa.array([k for _, k in held], pa.int32()), pa.array(c[:, 0]), pa.array(c[:, 1])], ["word", "k", "c", "n"])

        for b in small_batches(batches, "text"):
            w = _Words(b)
            held_out = b.column("held_out").to_numpy(zero_copy_only=False).astype(bool)
            for k, (x, y) in enumerate(zip(np.bincount(w.kind[~held_out], minlength=CLASSES).tolist(), np.bincount(w.kind, minlength=CLASSES).tolist(), strict=True)):
                old = held.get((None, k), (0, 0))
                held[None, k] = (old[0] + x, old[1] + y)
            out, kind = held_out[w.row], w.kind[w.row]
            lead, which, n = _distinct(_class_hash(w.hashes, kind), w.seconds)
            c = np.bincount(which[~out], minlength=len(n))
            raw = w.data.tobytes()
            for s, e, k, x, y in zip(w.starts[lead].tolist(), w.ends[lead].tolist(), kind[lead].tolist(), c.tolist(), n.tolist(), strict=True):
                name = raw[s:e], k
                old = held.get(name)
                held[name] = (x, y) if old is None else (old[0] + x, old[1] + y)
            if len(held) > HELD:
                yield send()
                held.clear()
        if held:
            yield send()

    rows = map_arrow(texts.select("text", "held_out"), each, "word binary, k int, c long, n long")
    return rows.groupBy("word").agg(*[F.sum(F.when(F.col("k") == k, F.col(x)).otherwise(0)).alias(f"{x}{k}") for x in "cn" for k in range(CLASSES)])


def _two_hashes(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    sizes = np.array([len(w) for w in words], np.int64)
    ends = np.cumsum(sizes)
    return span_hashes(np.frombuffer(b"".join(words), np.uint8), ends - sizes, ends, second=True)


def _hash_words(words: list[bytes]) -> np.ndarray:
    return _two_hashes(words)[0]


def fit_pieces(words: DataFrame, pieces: Pieces, rounds: int) -> list[Pieces]:
    """For each class, pieces with weights fitted to its distinct training words; only vectors of the vocabulary's size come back."""
    spark = words.sparkSession
    fitted = [pieces] * CLASSES
    for _ in range(rounds):
        shared = spark.sparkContext.broadcast(fitted)

        def each(batches: Iterable[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            lattices = [Lattice(p) for p in shared.value]
            total = np.zeros((CLASSES, len(shared.value[0].hashes) + 1))
            for b in batches:
                for k in range(CLASSES):
                    part = b.column("word").filter(pc.greater(b.column(f"c{k}"), 0)).to_pylist()
                    if part:
                        total[k] += lattices[k].expected(part)
            kind, used = np.nonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(kind), pa.array(used), pa.array(total[kind, used])], ["k", "piece", "uses"])

        rows = map_arrow(words.select("word", *[f"c{k}" for k in range(CLASSES)]), each, "k long, piece long, uses double").groupBy("k", "piece").agg(F.sum("uses").alias("uses")).toPandas()
        counts = np.zeros((CLASSES, len(pieces.hashes) + 1))
        counts[rows["k"].to_numpy(np.int64), rows["piece"].to_numpy(np.int64)] = rows["uses"].to_numpy(np.float64)
        fitted = [p.with_counts(c) for p, c in zip(fitted, counts, strict=True)]
    return fitted


@dataclass
class Totals:
    """Of one class: training tokens with ends, distinct training words with the end, ends, discount, and what it frees."""

    n: int
    v: int
    ends: int
    discount: float

    @property
    def freed(self) -> float:
        # without training documents the end has an even chance, and the pieces the other half
        return self.discount * self.v / self.n if self.n else 0.5


def _totals(words: DataFrame, ends: list[int]) -> list[Totals]:
    of = [(f"c{k}", F.col(f"c{k}")) for k in range(CLASSES)]
    r = words.agg(*[x for name, c in of for x in (F.sum(c).alias(f"{name}n"), F.count_if(c > 0).alias(f"{name}v"), F.count_if(c == 1).alias(f"{name}one"), F.count_if(c == 2).alias(f"{name}two"))]).first()
    out = []
    for (name, _), e in zip(of, ends, strict=True):
        one, two = r[f"{name}one"], r[f"{name}two"]
        # at most this discount, so that a word seen once keeps a share
        out.append(Totals((r[f"{name}n"] or 0) + e, r[f"{name}v"] + (e > 0), e, min(0.95, one / (one + 2 * two)) if one else 0.5))
    return out


def score_documents(docs: DataFrame, model: str, rounds: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10 probabilities).

    Learns from the documents whose crc32 of the id as text is not 2 modulo 7. Tokens are words (runs without white space,
    A-Z lower-cased) and one end a document, so null and empty texts have one token. Base is the word model with one added
    to each count; score is the lattice model. Repeated rows are scored, and learnt from, each; a null id counts as a
    training document. Without training documents every word goes by its pieces alone. An empty table gives no rows;
    other columns are not read.
    """
    spark = docs.sparkSession
    texts = id_and_text(docs, id_col, text_col).withColumn("held_out", F.coalesce(held_out_fold(F.col("doc_id")), F.lit(False)))
    counted = written(_word_counts(texts), "words")
    # how many training documents each class has
    last = counted.where("word IS NULL").first()
    ends = [last[f"c{k}"] if last else 0 for k in range(CLASSES)]
    words = counted.where("word IS NOT NULL")
    totals = _totals(words, ends)
    every = [F.col(f"c{k}") for k in range(CLASSES)]
    known = words.select(reduce(lambda x, y: x + y, every).alias("c")).agg(F.sum("c").alias("n"), F.count_if(F.col("c") > 0).alias("v")).first()
    n, v = (known["n"] or 0) + sum(ends), known["v"] + (sum(ends) > 0)
    shared = spark.sparkContext.broadcast(fit_pieces(words, existing_pieces(model), rounds if n else 0))

    def value(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattices = [Lattice(p) for p in shared.value]
        for b in batches:
            c = np.stack([b.column(f"c{k}").to_numpy() for k in range(CLASSES)])
            for k, t in enumerate(totals):
                uses = b.column(f"n{k}").to_numpy()
                at = np.flatnonzero(uses)
                if not len(at):
                    continue
                w = b.column("word").take(pa.array(at)).to_pylist()
                lp = lattices[k].log_probability(w) + math.log(t.freed)
                own = c[k, at]
                seen = own > t.discount
                lp[seen] = np.logaddexp(lp[seen], np.log((own[seen] - t.discount) / max(t.n, 1)))
                h, g = _two_hashes(w)
                h = _class_hash(h, np.full(len(w), k))
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(g.view(np.int64)), pa.array(c[:, at].sum(0)), pa.array(uses[at]), pa.array(lp / math.log(10))], ["h", "g", "c", "n", "lp"])

    values = written(map_arrow(words, value, "h long, g long, c long, n long, lp double"), "word_values")
    # the most frequent words, up to a fixed number, are looked up in the map task; all others are joined
    top_n = 1 << 14
    by_n = values.groupBy(F.least("n", F.lit(top_n)).alias("n")).count().orderBy(F.desc("n")).limit(top_n).collect()
    total, least = 0, top_n + 1
    for r in by_n:
        total += r["count"]
        if total > FREQUENT:
            break
        least = r["n"]
    top = values.where(F.col("n") >= least).select("h", "g", "c", "lp").toPandas()
    # words of the table that share their first hash go by the join with the rest
    twins = top["h"].duplicated(keep=False)
    joined_words = (F.col("n") < least) | F.col("h").isin(top["h"][twins].unique().tolist())
    top = top[~twins]
    floor = math.log10(n + v + 1)
    end_base = math.log10(sum(ends) + 1) - floor
    all_ends = sum(ends)
    # of a document's class: its share of the documents, one added to each, and the end of the text
    end_lp = np.array([math.log10((t.ends + 1) / (all_ends + CLASSES)) + (math.log10((t.ends - t.discount) / t.n) if t.ends else math.log10(0.5)) for t in totals])
    table = spark.sparkContext.broadcast((top["h"].to_numpy(np.int64).view(np.uint64), top["g"].to_numpy(np.int64).view(np.uint64), top["c"].to_numpy(np.int64), top["lp"].to_numpy(np.float64)))

    def scan(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, seconds, c, lp = table.value
        index = HashIndex(max(1, len(hashes)))
        index.add(hashes, np.arange(len(hashes), dtype=np.int32))
        base = np.log10(c + 1) - floor
        key = TaskContext.get().partitionId() << 40
        for b in small_batches(batches, "text"):
            w = _Words(b)
            h = _class_hash(w.hashes, w.kind[w.row])
            at = index.find(h)
            hit = at >= 0
            hit[hit] = seconds[at[hit]] == w.seconds[hit]
            sums = [np.bincount(w.row[hit], weights=x[at[hit]], minlength=b.num_rows) for x in (c > 0, base, lp)]
            rare, other, rare_row = h[~hit], w.seconds[~hit], w.row[~hit]
            order = np.lexsort((other, rare, rare_row))
            rare, other, rare_row = rare[order], other[order], rare_row[order]
            new = np.ones(len(rare), bool)
            new[1:] = (rare[1:] != rare[:-1]) | (other[1:] != other[:-1]) | (rare_row[1:] != rare_row[:-1])
            lead = np.flatnonzero(new)
            tf = np.diff(np.append(lead, len(rare))).astype(np.int32)
            lists = pa.array(np.searchsorted(rare_row[lead], np.arange(b.num_rows + 1)), pa.int32())
            yield pa.RecordBatch.from_arrays(
                [pa.array(key + np.arange(b.num_rows)), b.column("doc_id"), b.column("held_out"), pa.array(np.diff(w.first) + 1), pa.array(sums[0].astype(np.int64)), pa.array(sums[1]), pa.array(sums[2] + end_lp[w.kind]),
                 pa.ListArray.from_arrays(lists, pa.array(rare[lead].view(np.int64))), pa.ListArray.from_arrays(lists, pa.array(other[lead].view(np.int64))), pa.ListArray.from_arrays(lists, pa.array(tf))],
                ["row", "doc_id", "held_out", "n_tokens", "known", "base", "lp", "rare", "other", "tf"],
            )
            key += b.num_rows

    scanned = written(map_arrow(texts, scan, "row long, doc_id long, held_out boolean, n_tokens long, known long, base double, lp double, rare array<long>, other array<long>, tf array<int>"), "scanned")
    rare = scanned.select("row", F.explode(F.arrays_zip("rare", "other", "tf")).alias("x")).select("row", F.col("x.rare").alias("w"), F.col("x.other").alias("w2"), F.col("x.tf").alias("tf"))
    joined = rare.join(values.where(joined_words).select("h", "g", "c", "lp"), (F.col("w") == F.col("h")) & (F.col("w2") == F.col("g")))
    more = joined.groupBy("row").agg(
        F.sum(F.when(F.col("c") > 0, F.col("tf")).otherwise(0)).alias("known2"),
        F.sum(F.col("tf") * (F.log10(F.col("c") + 1) - F.lit(floor))).alias("base2"),
        F.sum(F.col("tf") * F.col("lp")).alias("lp2"),
    )
    rows = scanned.drop("rare", "other", "tf").join(more.withColumnRenamed("row", "row2"), F.col("row") == F.col("row2"), "left")
    return rows.select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("known") + F.coalesce("known2", F.lit(0)) + F.lit(1 if all_ends else 0)).alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("base2", F.lit(0.0)) + F.lit(end_base)).alias("base_score"),
        (F.col("lp") + F.coalesce("lp2", F.lit(0.0))).alias("score"),
    )
