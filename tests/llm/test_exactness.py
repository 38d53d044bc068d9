"""Queries' results against brute force, and texts that a weak hash would confuse."""

import collections
import itertools
import math
import random
import re
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest

from rankgrid.llm import decontaminate, exact_dedup, lattice_lm, line_crf, near_dedup, packing, pretokens, suffix_dedup, textblocks, token_counts, token_store, toxicity
from rankgrid.llm.pretokens import default_tokenizer
from tests.llm.test_operators import linked, prose

DOCS = "doc_id long, text string"


def thue_morse(letters, n=1024):
    return "".join(letters[bin(k).count("1") % 2] for k in range(n))


#: Two words whose polynomial hashes modulo a power of two are equal for every odd base.
TWINS = [thue_morse("ab"), thue_morse("ba")]


@pytest.fixture(scope="module")
def tokenizer():
    return pretokens._load(default_tokenizer())


@pytest.fixture(scope="module")
def twins(spark):
    return spark.createDataFrame(list(enumerate(TWINS)), DOCS)


def test_twins_in_token_queries(twins, tokenizer):
    ids = [tokenizer.encode(t, add_special_tokens=False).ids for t in TWINS]
    crc = lambda k, end: zlib.crc32(np.array([*ids[k], end], "<u4").tobytes())
    assert {r["doc_id"]: r["n_tokens"] for r in token_counts.token_counts(twins, default_tokenizer()).collect()} == {k: len(x) for k, x in enumerate(ids)}
    assert {r["doc_id"]: r["ids_crc32"] for r in packing.pack_documents(twins, default_tokenizer()).collect()} == {k: crc(k, 0) for k in (0, 1)}
    store = token_store.write_store(twins, default_tokenizer(), 2)
    assert {r["doc_id"]: r["ids_crc32"] for r in token_store.read_documents(store).collect()} == {k: crc(k, 2) for k in (0, 1)}


def test_twins_stay_apart(spark, twins):
    assert {r["component_id"] for r in near_dedup.near_duplicates(twins, 2, 80).collect()} == {0, 1}
    two = spark.createDataFrame([(0, "x" + TWINS[0]), (1, "y" + TWINS[1])], DOCS)
    raw = [("x" + TWINS[0]).encode(), ("y" + TWINS[1]).encode()]
    seen = collections.Counter(b[k : k + 200] for b in raw for k in range(len(b) - 199))
    gone = []
    for b in raw:
        flags = np.zeros(len(b), bool)
        for k in range(len(b) - 199):
            flags[k : k + 200] |= seen[b[k : k + 200]] > 1
        gone.append(int(flags.sum()))
    assert [r["n_removed"] for r in suffix_dedup.remove_repeats(two, 200).orderBy("doc_id").collect()] == gone
    item = spark.createDataFrame([(1, " ".join([TWINS[0]] * 13))], "item_id long, text string")
    assert [r["doc_id"] for r in decontaminate.contaminated(spark.createDataFrame([(k, " ".join([t] * 13)) for k, t in enumerate(TWINS)], DOCS), item).collect()] == [0]


def test_encoder_with_a_hash_of_few_values(monkeypatch, tokenizer):
    """Every pre-token shares its hash with many others, and is told apart by its text."""
    monkeypatch.setattr(pretokens, "span_hash", lambda v, s, e: textblocks.span_hash(v, s, e) % np.uint64(211) + np.uint64(1))
    enc = pretokens.Encoder(pretokens.vocabulary(default_tokenizer()), cached=1 << 10, window=500)
    texts = [prose(k, 40) + " the quick brown fox 12 don't <|endoftext|>x" for k in range(12)] + TWINS
    flat, at = enc.ids(texts)
    for k, e in enumerate(tokenizer.encode_batch(texts, add_special_tokens=False)):
        assert flat[at[k] : at[k + 1]].tolist() == e.ids


def test_span_hashes_depend_on_the_span_alone():
    rng = np.random.default_rng(0)
    data = rng.integers(0, 256, 5000).astype(np.uint8)
    data[3000:3040] = data[100:140]
    h, g = textblocks.span_hashes(data, np.array([100, 3000, 100, 7]), np.array([140, 3040, 139, 7]), second=True)
    assert (h[0], g[0]) == (h[1], g[1])
    assert len({*h.tolist()}) == len({*g.tolist()}) == 3


def test_repeated_rows_leave_one(spark):
    rows = [(1, "a b", 1), (1, "a b", 2), (2, "ab", 3), (3, "c", 4), (3, "c", 5), (3, "d", 6), (None, "e", 7), (None, "e", 8)]
    left = exact_dedup.drop_exact_copies(spark.createDataFrame(rows, "doc_id long, text string, n int")).collect()
    assert sorted((r["doc_id"] or -1, r["text"]) for r in left) == [(-1, "e"), (1, "a b"), (3, "c"), (3, "d")]


def test_heavy_groups_are_broadcast(spark, monkeypatch):
    """With a low bound of what is heavy, both ways of the join are taken and give one result."""
    from rankgrid.llm import skew

    rows = [(k, "the same text") for k in range(60)] + [(k, f"text {k // 2}") for k in range(100, 140)]
    docs = spark.createDataFrame(rows, DOCS)
    want = sorted(tuple(r) for r in exact_dedup.duplicate_groups(docs).collect())
    near = sorted(tuple(r) for r in near_dedup.near_duplicates(docs, 2, 80).collect())
    monkeypatch.setattr(skew, "HEAVY", 3)
    assert sorted(tuple(r) for r in exact_dedup.duplicate_groups(docs).collect()) == want
    assert sorted(tuple(r) for r in near_dedup.near_duplicates(docs, 2, 80).collect()) == near
    assert {r[1] for r in want if r[0] < 60} == {0}


def test_near_components_of_a_hot_bucket(spark, monkeypatch):
    """Most members are one component, some stand apart, and some are linked only to one of those."""
    rng = random.Random(3)
    base = prose(21, 100).split()

    def changed(words, n, k):
        out = list(words)
        for at in rng.sample(range(100), n):
            out[at] = f"w{k}x{at}"
        return out

    rows = [(k, " ".join(changed(base, 2, k))) for k in range(150)]
    far = [changed(base, 13, 1000 + k) for k in range(30)]
    rows += [(1000 + k, " ".join(f)) for k, f in enumerate(far)] + [(2000 + k, " ".join(changed(f, 3, 3000 + k))) for k, f in enumerate(far[:10])]
    monkeypatch.setattr(near_dedup, "BLOCK", 16)
    want, _ = linked(rows, 2, 80)
    got = {r["doc_id"]: r["component_id"] for r in near_dedup.near_duplicates(spark.createDataFrame(rows, DOCS), 2, 80).collect()}
    assert got == want


@pytest.mark.parametrize("local", [200_000, 50])
def test_repeated_bytes_of_a_common_passage(spark, monkeypatch, local):
    """A passage between other words in every document, runs of one byte and of a short period."""
    rng = random.Random(5)
    passage = prose(31, 60)
    rows = [(k, "".join(rng.choice("abcdef ") for _ in range(60 + k)) + passage + "".join(rng.choice("abcdef ") for _ in range(50))) for k in range(40)]
    rows += [(100, "x" * 900), (101, "y" + "x" * 450 + "z"), (102, "ab" * 300), (103, "abc" * 150 + passage[:250])]
    raw = [t.encode() for _, t in rows]
    seen = collections.Counter(b[k : k + 200] for b in raw for k in range(len(b) - 199))
    want = {}
    for (i, _), b in zip(rows, raw, strict=True):
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - 199):
            if seen[b[k : k + 200]] > 1:
                gone[k : k + 200] = True
        want[i] = int(gone.sum())
    monkeypatch.setattr(suffix_dedup, "LOCAL", local)
    assert {r["doc_id"]: r["n_removed"] for r in suffix_dedup.remove_repeats(spark.createDataFrame(rows, DOCS), 200).collect()} == want


def test_lattice_scores_against_enumeration(spark):
    """Scores worked out from the definition, without fitted weights: class share, end, discounted words, and all segmentations."""
    import public_tokenizers

    texts = ["the cat of the hat", "the dog", "of the the cat", None, "der hund und die katze", "a b", "zz the zz", "", "le chat et la table", "the cat"]
    rows = [(k, t) for k, t in enumerate(texts)]
    model = public_tokenizers.path("piece_bpe_32k.model")
    pieces = lattice_lm.existing_pieces(model)
    known = {int(h): math.exp(p) for h, p in zip(pieces.hashes, pieces.log_p[:-1], strict=True)}

    def spelled(raw):
        if not raw:
            return 1.0
        return sum(known[h] * spelled(raw[k:]) for k in range(1, len(raw) + 1) if (h := int(lattice_lm._hash_words([raw[:k]])[0])) in known)

    words = [(t or "").split() for t in texts]
    kind = []
    for ws in words:
        score = [0] + [sum(w in listed for w in ws) for listed in lattice_lm.FUNCTION_WORDS.values()]
        kind.append(int(np.argmax(score)))
    train = [zlib.crc32(str(k).encode()) % 7 != 2 for k in range(len(texts))]
    counts = [collections.Counter(w for ws, c, x in zip(words, kind, train, strict=True) if x and c == k for w in ws) for k in range(lattice_lm.CLASSES)]
    ends = [sum(x and c == k for c, x in zip(kind, train, strict=True)) for k in range(lattice_lm.CLASSES)]

    def of(k):
        one, two = sum(c == 1 for c in counts[k].values()), sum(c == 2 for c in counts[k].values())
        d = min(0.95, one / (one + 2 * two)) if one else 0.5
        n, v = sum(counts[k].values()) + ends[k], len(counts[k]) + (ends[k] > 0)
        freed = d * v / n if n else 0.5
        end = (ends[k] - d) / n if ends[k] else 0.5
        assert sum(c - d for c in counts[k].values()) / max(n, 1) + end + freed == pytest.approx(1)
        return d, n, freed, end

    for r in lattice_lm.score_documents(spark.createDataFrame(rows, DOCS), model, rounds=0).collect():
        k = kind[r["doc_id"]]
        d, n, freed, end = of(k)
        p = math.log10((ends[k] + 1) / (sum(ends) + lattice_lm.CLASSES)) + math.log10(end)
        for w in words[r["doc_id"]]:
            p += math.log10(freed * spelled(b" " + w.encode()) * math.exp(pieces.end) + (max(counts[k][w] - d, 0) / n if n else 0))
        assert r["score"] == pytest.approx(p, abs=1e-6)


def test_pieces_of_documents_against_the_library(spark, tokenizer):
    texts = [None, "", prose(1, 30), prose(2, 400), prose(3, 900), "x y", prose(2, 400)]
    want = []
    for k, t in enumerate(texts):
        ids = [*tokenizer.encode(t or "", add_special_tokens=False).ids, 0]
        size = len(ids) % 512 or 512 if len(ids) > 512 else len(ids)
        cuts = [0, *range(size, len(ids) + 1, 512)]
        want += [(k, n, s, e - s, zlib.crc32(np.array(ids[s:e], "<u4").tobytes())) for n, (s, e) in enumerate(itertools.pairwise(cuts))]
    rows = packing.pack_documents(spark.createDataFrame(list(enumerate(texts)), DOCS), default_tokenizer(), capacity=512).collect()
    assert sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == sorted(want)


def test_sum_of_squares_against_trying_every_bin():
    rng = random.Random(8)
    for _ in range(20):
        lengths = [rng.randrange(1, 13) for _ in range(60)]
        gaps, offsets = [], []
        for s in lengths:
            best = None
            for k, g in enumerate(gaps):
                if g >= s:
                    after = collections.Counter(g2 for j, g2 in enumerate(gaps) if j != k and g2)
                    after[g - s] += g > s
                    cost = sum(c * c for c in after.values()), g
                    best = min(best or (cost, k), (cost, k))
            if best is None:
                gaps.append(12)
                best = None, len(gaps) - 1
            offsets.append(12 - gaps[best[1]])
            gaps[best[1]] -= s
        bins, at = packing.sum_of_squares(np.array(lengths), 12)
        assert at.tolist() == offsets
        assert bins.max() + 1 == len(gaps)


def lexicon():
    names, values = zip(*sorted(toxicity._lexicon().items()), strict=True)
    return toxicity.Grammar(np.array([h for h, _ in names], np.uint64), np.array([z for _, z in names]), np.array([c for c, _ in values], np.int8), np.array([w for _, w in values]), np.zeros(6))


def test_composed_machine_is_its_parts():
    rng = random.Random(2)
    parts = list(toxicity.transducers().values())
    machine, states = toxicity.compose(parts)
    symbols = np.array([rng.randrange(toxicity.HARD + 1) for _ in range(3000)])
    starts = np.array([0, 700, 701, 2000])
    before = toxicity.run(machine, symbols, starts)
    alone = [0] * len(parts)
    for k, a in enumerate(symbols.tolist()):
        if k in starts:
            alone = [0] * len(parts)
        assert states[before[k]].tolist() == alone
        assert machine.weight[before[k], a] == pytest.approx(math.prod(p.weight[s, a] for p, s in zip(parts, alone, strict=True)))
        alone = [int(p.next[s, a]) for p, s in zip(parts, alone, strict=True)]


def read_by_hand(text):
    """Summed and largest weight and whether a threat has a target, clause by clause."""
    total, most, threat = 0.0, 0.0, 0.0
    lists = {w: c for c, ws in toxicity.LEXICON.items() for w in ws}
    for sentence in re.split(r"[.;!?\n|]", text.lower()):
        told = None
        for n, clause in enumerate(re.split(r"[,:]", sentence)):
            reported, negated, weights, target, threatens = told == n - 1 and told is not None, -99, [], False, False
            for k, w in enumerate(clause.split()):
                c = lists.get(w, 0)
                if c == toxicity.NEGATION:
                    negated = k
                elif c == toxicity.REPORT:
                    reported, told = True, n
                elif c == toxicity.TARGET:
                    target = True
                elif c:
                    weights.append((toxicity.PRIOR if c == toxicity.INSULT else 1.0) * (toxicity.NEGATED if k - negated <= toxicity.REACH else 1) * (toxicity.REPORTED if reported else 1))
                    threatens |= c == toxicity.THREAT
            weights = [w * (toxicity.TARGETED if target else toxicity.AIMLESS if threatens else 1) for w in weights]
            total, most = total + sum(weights), max([most, *weights])
            threat = max(threat, float(bool(weights) and threatens and target))
    return total, most, threat


def test_grammar_against_reading_by_hand():
    rng = random.Random(6)
    some = ["idiot", "kill", "you", "not", "said", "tree", "house", "clown", "never", "he"]
    texts = ["".join(rng.choice(some) + rng.choice([" ", " ", " ", ", ", ". ", ": ", ",, ", "\n"]) for _ in range(rng.randrange(40))) for _ in range(300)]
    x = lexicon().machine().features(pa.array(texts))
    for row, t in zip(x, texts, strict=True):
        total, most, threat = read_by_hand(t)
        assert (np.expm1(row[0]), row[1], row[3]) == pytest.approx((total, most, threat))


def overlap(doc, item):
    """(equal, compared, first word) of the best shift, or None."""
    need = min(13, len(item))
    best = None
    for shift in range(-len(item), len(doc) + 1):
        lo, hi = max(0, -shift), min(len(item), len(doc) - shift)
        same = [item[k] == doc[k + shift] for k in range(lo, hi)]
        good = [k for k in range(len(same) - need + 1) if sum(same[k : k + need]) >= need - decontaminate.allowed(need)]
        if good and need:
            s, e = good[0], good[-1] + need
            best = max(best or (0, 0, 0), (sum(same[s:e]), e - s, lo + shift + s))
    return best


def test_overlaps_against_every_shift(spark):
    rng = random.Random(4)
    words = [f"w{k}" for k in range(300)] + ["ha"] * 20
    items = [[rng.choice(words) for _ in range(n)] for n in (3, 8, 13, 14, 30, 60)] + [["ha"] * 40, ["ha", "ho"] * 15]
    docs = []
    for _ in range(60):
        d = [rng.choice(words) for _ in range(rng.randrange(60))]
        item = list(rng.choice(items))
        for k in rng.sample(range(len(item)), rng.randrange(len(item) // 4 + 1)):
            item[k] = "other"
        docs.append(d + item[rng.randrange(len(item) // 3 + 1) :] + d[:9])
    docs += [["ha"] * 70, ["ha", "ho"] * 20, ["ho", "ha", "ha"] * 20, []]
    want = {(k, n): o for k, d in enumerate(docs) for n, i in enumerate(items) if (o := overlap(d, i))}
    got = decontaminate.contaminated(spark.createDataFrame([(k, " ".join(d)) for k, d in enumerate(docs)], DOCS), spark.createDataFrame([(n, " ".join(i)) for n, i in enumerate(items)], "item_id long, text string")).collect()
    assert {(r["doc_id"], r["item_id"]): (r["n_equal"], r["n_compared"], r["first_word"]) for r in got} == want
    assert len(got) == len(want)


def test_overlaps_of_a_repeated_word_are_cheap():
    scanner = decontaminate.Scanner(decontaminate.benchmark_tables([1], [" ".join(["ha"] * 1000)]))
    began = time.process_time()
    assert scanner.hits(pa.array([" ".join(["ha"] * 10_000)])) == [(0, 0, 9000, 1000, 1000)]
    assert time.process_time() - began < 10


def test_quality_scores_against_enumeration(spark):
    """The query's scores from the field's definition, with every labelling of the lines written out."""
    rng = np.random.default_rng(3)
    texts = ["\n".join(prose(7 * k + j, 3 + j) + "." for j in range(k % 5 + 1)) + ("\n\n| $$ ##" if k % 3 == 0 else "") for k in range(12)] + [None, "", "  \n "]
    width = line_crf.Lines(pa.array(["a b"])).with_neighbours().shape[1]
    f = line_crf.Field(rng.standard_normal(width), np.ones(width), rng.standard_normal(width) / 5, 0.1, rng.standard_normal((2, 2)), np.array([0.7, -0.4, 0.3, 0.2]))
    for r in line_crf.score(spark.createDataFrame(list(enumerate(texts)), DOCS), f).collect():
        lines = line_crf.Lines(pa.array([texts[r["doc_id"]]], pa.string()))
        s = np.clip(f.line_scores(lines.with_neighbours()), -30, 30)
        weights = {y: math.exp(sum((v if b else -v) / 2 for v, b in zip(s, y, strict=True)) + sum(f.step[a, b] for a, b in itertools.pairwise(y))) for y in itertools.product((0, 1), repeat=len(s))}
        good = np.array([sum(w for y, w in weights.items() if y[k]) for k in range(len(s))]) / sum(weights.values())
        size = lines.size.sum()
        mean = float(np.clip((good * lines.size).sum() / size, 1e-3, 1 - 1e-3)) if size else 0.5
        x = [math.log(mean / (1 - mean)), ((good > 0.5) * lines.size).sum() / size if size else 0.0, math.log1p(size) / 10]
        assert r["score"] == pytest.approx(1 / (1 + math.exp(-(np.dot(x, f.model[:3]) + f.model[3]))), abs=1e-9)
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2)
