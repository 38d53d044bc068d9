"""The training-data operators against brute force, on planted cases and on odd inputs."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from rankgrid.llm import components, decontaminate, exact_dedup, lattice_lm, line_crf, near_dedup, packing, pretokens, suffix_dedup, token_counts, token_store, toxicity
from rankgrid.llm.pretokens import default_tokenizer

SCHEMA = "doc_id long, text string, h1 long, key string, windows int"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def prose(seed, n):
    rng = random.Random(seed)
    return " ".join(rng.choice(WORDS) + rng.choice(["", "", ",", "s"]) + str(rng.randrange(40)) for _ in range(n))


@pytest.fixture(scope="module")
def cases():
    """Nulls, empty and blank texts, ties, repeated rows, copies, near copies, self-repeats, a long text, clashing columns."""
    base = prose(1, 120)
    near = base.split()
    near[60] = "changed"
    texts = [None, "", " \n\t", "one", "ONE", base, base, base.replace(" ", "  "), " ".join(near), prose(2, 90), prose(3, 40) + " " + base[:400] + " " + prose(4, 40), "ab " * 300, prose(5, 9000), "ünï<|endoftext|> don't  'stop\n\n漢字 x", "x" * 3000]
    rows = [(k, t) for k, t in enumerate(texts)] + [(5, base), (None, "no id"), (None, None)]
    return rows


@pytest.fixture(scope="module")
def docs(spark, cases):
    return spark.createDataFrame([(i, t, 7, "clash", 1) for i, t in cases], SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def tokenizer():
    return pretokens._load(default_tokenizer())


def test_exact_groups(docs, cases, empty):
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]", "", t or "")
    groups = collections.defaultdict(list)
    for i, t in cases:
        groups[norm(t)].append((-len(t or ""), -1 if i is None else i))
    for r in exact_dedup.duplicate_groups(docs).collect():
        match = next(g for n, g in groups.items() if hashlib.sha256(n.encode()).hexdigest() == r["text_sha256"])
        assert r["group_size"] == len(match)
        assert (-1 if r["keep_id"] is None else r["keep_id"]) == min(match)[1]
    assert exact_dedup.duplicate_groups(empty).count() == 0
    left = [r["doc_id"] for r in exact_dedup.drop_exact_copies(docs).collect()]
    assert 7 in left  # of equal texts the longest original stays
    assert 6 not in left
    assert set(exact_dedup.drop_exact_copies(docs).columns) == set(docs.columns)


def test_token_counts_and_ids(docs, cases, empty, tokenizer):
    got = sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_bytes"], r["n_tokens"]) for r in token_counts.token_counts(docs, default_tokenizer()).collect())
    want = sorted((-1 if i is None else i, len((t or "").encode()), len(tokenizer.encode(t or "", add_special_tokens=False).ids)) for i, t in cases)
    assert got == want
    assert token_counts.token_counts(empty, default_tokenizer()).count() == 0


def test_encoder_against_the_library(tokenizer):
    rng = random.Random(4)
    enc = pretokens.Encoder(pretokens.vocabulary(default_tokenizer()), cached=1 << 10, window=300)
    alphabet = [*"ab'sStTrevmldl  \n\t!.12é漢٣½ 　\x1c\x85", "<|endoftext|>", "'re", " 't", "\U0001f600"]
    for _ in range(60):
        texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(80))) for _ in range(15)] + ["y" * 900, "a b " * 400]
        flat, at = enc.ids(texts)
        for k, e in enumerate(tokenizer.encode_batch(texts, add_special_tokens=False)):
            assert flat[at[k] : at[k + 1]].tolist() == e.ids


def shingles(text, width):
    words = [w for w in re.split(rb"[\x20\x09-\x0D]+", (text or "").encode().lower()) if w]
    return {tuple(words[k : k + width]) for k in range(len(words) - width + 1)} if len(words) >= width else ({tuple(words)} if words else set())


def linked(rows, width, percent):
    sets = {i: shingles(t, width) for i, t in rows if i is not None}
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}, sets


@pytest.mark.parametrize("width", [2, 5])
def test_near_components(docs, cases, empty, width):
    want, sets = linked(cases, width, 80)
    for r in near_dedup.near_duplicates(docs, width, 80).collect():
        if r["doc_id"] is not None:
            assert (r["component_id"], r["n_shingles"], r["kept"]) == (want[r["doc_id"]], len(sets[r["doc_id"]]), want[r["doc_id"]] == r["doc_id"])
    assert near_dedup.near_duplicates(empty, width, 80).count() == 0


def test_near_components_of_a_chained_group(spark):
    """A group whose links form chains, so that one comparison a bucket does not settle it."""
    rng = random.Random(9)
    base = prose(11, 100).split()
    rows = []
    for k in range(120):
        words = list(base)
        for at in rng.sample(range(100), 7):
            words[at] = f"w{k}x{at}"
        rows.append((k, " ".join(words)))
    want, _ = linked(rows, 2, 80)
    near_dedup.BLOCK, old = 32, near_dedup.BLOCK
    try:
        got = {r["doc_id"]: r["component_id"] for r in near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), 2, 80).collect()}
    finally:
        near_dedup.BLOCK = old
    assert got == want


def test_sketch_fills_and_estimates():
    a, b = np.arange(1, 2001, dtype=np.uint64), np.arange(201, 2201, dtype=np.uint64)
    x, y = (near_dedup.sketch(near_dedup.mix(s)) for s in (a, b))
    assert abs((x == y).mean() - 1800 / 2200) < 0.12
    assert len(near_dedup.sketch(near_dedup.mix(a[:1]))) == near_dedup.COORDINATES
    assert (near_dedup.sketch(near_dedup.mix(a[:1])) != 0).all()


def test_components_of_a_path(spark):
    rows = [(k, k + 1) for k in range(0, 40)] + [(100, 101)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(rows, "a long, b long")).collect()}
    assert got == {**{k: 0 for k in range(1, 41)}, 101: 100}


@pytest.mark.parametrize("local", [200_000, 10])
def test_repeated_bytes(docs, cases, empty, local):
    length = 200
    raw = [(t or "").encode() for _, t in cases]
    seen = collections.Counter(b[k : k + length] for b in raw for k in range(len(b) - length + 1))
    want = []
    for (i, _), b in zip(cases, raw, strict=True):
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - length + 1):
            if seen[b[k : k + length]] > 1:
                gone[k : k + length] = True
        spans = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        want.append((-1 if i is None else i, len(b), int(gone.sum()), spans, hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()))
    suffix_dedup.LOCAL, old = local, suffix_dedup.LOCAL
    try:
        got = [(-1 if r["doc_id"] is None else r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(docs, length).collect()]
    finally:
        suffix_dedup.LOCAL = old
    assert sorted(got) == sorted(want)
    assert suffix_dedup.remove_repeats(empty, length).count() == 0


def test_multikey_quicksort_ties():
    rng = np.random.default_rng(0)
    rows = rng.integers(0, 2, (400, 11)).astype(np.uint8)
    group = rng.integers(0, 3, 400)
    count = collections.Counter((g, r.tobytes()) for g, r in zip(group, rows, strict=True))
    assert suffix_dedup.tied_windows(group, rows).tolist() == [count[g, r.tobytes()] > 1 for g, r in zip(group, rows, strict=True)]


def test_language_model(docs, cases, empty):
    import public_tokenizers

    model = public_tokenizers.path("piece_bpe_32k.model")
    words = [[w for w in re.split(rb"[\x20\x09-\x0D]+", (t or "").encode().lower()) if w] for _, t in cases]
    train = [i is None or zlib.crc32(str(i).encode()) % 7 != 2 for i, _ in cases]
    counts = collections.Counter(w for ws, x in zip(words, train, strict=True) if x for w in ws)
    n, v = sum(counts.values()) + sum(train), len(counts) + 1
    want = sorted((len(ws) + 1, sum(counts[w] > 0 for w in ws) + 1, round(sum(np.log10((counts[w] + 1) / (n + v + 1)) for w in ws) + np.log10((sum(train) + 1) / (n + v + 1)), 6)) for ws in words)
    rows = lattice_lm.score_documents(docs, model).collect()
    assert sorted((r["n_tokens"], r["n_known"], round(r["base_score"], 6)) for r in rows) == want
    assert all(r["train_tokens"] == n and r["score"] < 0 for r in rows)
    assert lattice_lm.score_documents(empty, model).count() == 0


def test_lattice_sums_all_segmentations():
    import public_tokenizers

    pieces = lattice_lm.existing_pieces(public_tokenizers.path("piece_bpe_32k.model"))
    lattice = lattice_lm.Lattice(pieces)
    known = {int(h): p for h, p in zip(pieces.hashes, pieces.log_p[:-1], strict=True)}

    def brute(raw):
        if not raw:
            return 1.0
        return sum(np.exp(known[int(lattice_lm._hash_words([raw[:k]])[0])]) * brute(raw[k:]) for k in range(1, len(raw) + 1) if int(lattice_lm._hash_words([raw[:k]])[0]) in known)

    for w in (b"the", b"tionen", b"x\xc3\xa9"):
        assert lattice.log_probability([w])[0] == pytest.approx(np.log(brute(b" " + w)) + pieces.end, abs=1e-9)
    assert np.exp(pieces.log_p[:-1][pieces.starting]).sum() == pytest.approx(1)
    assert np.exp(pieces.log_p[:-1][~pieces.starting]).sum() + np.exp(pieces.end) == pytest.approx(1)


def test_lattice_keeps_long_pieces():
    import public_tokenizers

    pieces = lattice_lm.existing_pieces(public_tokenizers.path("piece_bpe_32k.model"))
    known = {int(h) for h in pieces.hashes}
    assert all(int(lattice_lm._hash_words([w])[0]) in known for w in (b" understanding", b" international", b" particularly", b" representation"))
    assert pieces.longest > 12


def test_packing(docs, cases, empty, tokenizer):
    rows = packing.pack_documents(docs, default_tokenizer(), capacity=512).collect()
    by = collections.defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for pieces in by.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 512
    assert sum(r["length"] for r in rows) == sum(len(tokenizer.encode(t or "", add_special_tokens=False).ids) + 1 for _, t in cases)
    assert packing.pack_documents(empty, default_tokenizer()).count() == 0


def test_sum_of_squares_is_tight():
    rng = np.random.default_rng(1)
    lengths = np.sort(rng.integers(1, 2049, 3000))[::-1]
    bins, offsets = packing.sum_of_squares(lengths, 2048)
    assert bins.max() + 1 <= np.ceil(lengths.sum() / 2048) * 1.02 + 1
    assert (offsets + lengths <= 2048).all()


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_store_round_trip(docs, cases, empty, tokenizer, kind):
    store = token_store.write_store(docs, default_tokenizer(), 2, planes=kind)
    want = sorted((-1 if i is None else i, t or "", zlib.crc32(np.array([*tokenizer.encode(t or "", add_special_tokens=False).ids, 2], "<u4").tobytes())) for i, t in cases)
    got = token_store.read_documents(store).orderBy("start").collect()
    assert [(-1 if r["doc_id"] is None else r["doc_id"], r["ids_crc32"]) for r in got] == [(i, c) for i, _, c in want]
    assert [r["start"] for r in got] == (np.cumsum([0] + [r["n_tokens"] for r in got])[:-1]).tolist()
    assert sum(len(r["ids"]) for r in token_store.read_ids(store).collect()) == sum(r["n_tokens"] for r in got)
    assert token_store.read_documents(token_store.write_store(empty, default_tokenizer())).count() == 0


def test_planes():
    ids = np.array([0, 1, 255, 256, 50256, 2**31, 2**32 - 1], np.uint32)
    for kind in ("byte", "bit"):
        assert token_store.from_planes(token_store.to_planes(ids, kind), len(ids), kind).tolist() == ids.tolist()


def test_masks_lose_no_window():
    from itertools import combinations

    for n in range(1, decontaminate.WINDOW + 1):
        for gone in combinations(range(n), decontaminate.allowed(n)):
            assert any(not any(o + m in gone for m in mask) for mask in decontaminate.masks_for(n) for o in range(n - mask[-1]))


def test_contamination(spark, docs, empty):
    item = " ".join(f"word{k}" for k in range(40))
    swapped = item.split()
    swapped[5] = swapped[18] = "other"
    bench = spark.createDataFrame([(1, item), (2, "short but odd phrase"), (3, None), (4, "")], "item_id long, text string")
    rows = [(100, f"Intro. {item.upper()}! End."), (101, f"intro {' '.join(swapped)} end"), (102, " ".join(f"word{k}" for k in range(0, 40, 4))), (103, "A SHORT, but odd phrase."), (104, prose(6, 100)), (105, " ".join(item.split()[:13]))]
    mine = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(mine, bench).collect()}
    assert got == {(100, 1), (101, 1), (103, 2), (105, 1)}
    assert {(r["doc_id"], r["item_id"]) for r in decontaminate.contaminated(mine, bench, block_words=10).collect()} == got
    assert sorted(r["doc_id"] for r in decontaminate.drop_contaminated(mine, bench).collect()) == [102, 104]
    assert decontaminate.contaminated(docs, bench).count() == 0
    assert decontaminate.contaminated(empty, bench).count() == 0
    assert decontaminate.contaminated(mine, bench.limit(0)).count() == 0


def labelled(spark, good, bad, n=160):
    rows, labels = [], []
    for k in range(n):
        rows.append((k, (bad if k % 4 == 0 else good)(k)))
        labels.append((k, int(k % 4 != 0), int(k % 4 == 0)))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_toxicity(spark, docs, empty):
    mine, labels = labelled(spark, lambda k: prose(k, 60), lambda k: prose(k, 30) + " you are an idiot and zorblax" + str(k % 3) + " " + prose(k + 500, 30))
    g = toxicity.fit(mine, labels)
    rows = toxicity.score(mine, g).collect()
    assert np.mean([r["predicted"] == (r["doc_id"] % 4 == 0) for r in rows if r["held_out"]]) > 0.9
    assert all(0 <= r["score"] <= 1 for r in toxicity.score(docs, g).collect())
    assert toxicity.score(empty, g).count() == 0
    assert toxicity.fit(mine, labels.limit(0)).model is not None


def test_grammar_reads_clauses():
    names, values = zip(*sorted(toxicity._lexicon().items()), strict=True)
    g = toxicity.Grammar(np.array([h for h, _ in names], np.uint64), np.array([z for _, z in names]), np.array([c for c, _ in values], np.int8), np.array([w for _, w in values]), np.zeros(6))
    x = g.machine().features(pa.array(["you idiot", "an idiot", "not an idiot", "he said idiot", "I will kill you", "kill time", "fine", None, ""]))
    most = x[:, 1]
    assert most[0] > most[1] > most[2] > 0
    assert most[4] > most[5]
    assert x[4, 3] == 1
    assert x[5, 3] == 0
    assert not x[6:].any()


def test_grammar_reads_contractions_and_reports():
    names, values = zip(*sorted(toxicity._lexicon().items()), strict=True)
    g = toxicity.Grammar(np.array([h for h, _ in names], np.uint64), np.array([z for _, z in names]), np.array([c for c, _ in values], np.int8), np.array([w for _, w in values]), np.zeros(6))
    texts = ["an idiot", "isn't an idiot", "isn’t an idiot", "don t idiot", "she said, an idiot", "he wrote: an idiot", "she said. An idiot", "she said, well, an idiot"]
    plain, *most = g.machine().features(pa.array(texts))[:, 1]
    assert most[0] == most[1] == pytest.approx(plain * toxicity.NEGATED)
    assert most[3] == most[4] == pytest.approx(plain * toxicity.REPORTED)
    assert most[2] == most[5] == most[6] == plain


def test_quality(spark, docs, empty):
    mine, labels = labelled(spark, lambda k: "\n".join(prose(k + 1000 * j, 30) + "." for j in range(4)), lambda k: "\n".join("| $$ ## ** " * 20 for _ in range(5)))
    f = line_crf.fit(mine, labels)
    rows = line_crf.score(mine, f).collect()
    assert np.mean([r["predicted"] == (r["doc_id"] % 4 != 0) for r in rows if r["held_out"]]) > 0.9
    assert all(0 <= r["score"] <= 1 for r in line_crf.score(docs, f).collect())
    assert line_crf.score(empty, f).count() == 0
    assert line_crf.drop_bad(mine, f).count() >= 110


def test_forward_backward_against_enumeration():
    from itertools import product

    rng = np.random.default_rng(2)
    scores, row, step = rng.standard_normal(7), np.array([0, 0, 0, 1, 2, 2, 2]), rng.standard_normal((2, 2))
    good, _ = line_crf.forward_backward(scores, row, 3, step)
    for r in range(3):
        s = scores[row == r]
        weights = {y: np.exp(sum((v if b else -v) / 2 for v, b in zip(s, y, strict=True)) + sum(step[a, b] for a, b in zip(y, y[1:], strict=False))) for y in product((0, 1), repeat=len(s))}
        total = sum(weights.values())
        for k in range(len(s)):
            assert good[row == r][k] == pytest.approx(sum(w for y, w in weights.items() if y[k]) / total)
