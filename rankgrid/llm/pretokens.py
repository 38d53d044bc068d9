"""Byte-level BPE for whole Arrow columns: pre-tokens are cut, hashed and looked up as arrays; the tokenizer sees only new ones.

A first table, made once on the driver from the vocabulary itself and broadcast (its size is bounded by the vocabulary),
holds the ids of the pre-tokens that are frequent enough to have their own entries. What it misses goes to a cache in
the worker, and what that misses to the tokenizers library, once per distinct pre-token. No pre-token is ever shuffled.
Entries are found by a hash and keep their text: a pre-token whose text differs from its entry's is looked up by itself.
"""

from __future__ import annotations

import os
import re
from dataclasses import dataclass
from itertools import chain

import numpy as np

from rankgrid.llm.textblocks import span_hash

LETTER, NUMBER, OTHER, SPACE = 0, 1, 2, 3
#: No letter, number or space of Unicode lies above; the rest is OTHER.
LAST_CLASSED = 0x32400
#: Code points of pre-tokens after which a worker's cache starts anew.
TEXT_ROOM = 1 << 24
#: Words that go to the library as one text.
JOINED = 1000


@dataclass
class Vocabulary:
    """What workers get: the tokenizer's file, classes of code points, and the first table."""

    path: str
    classes: np.ndarray
    hashes: np.ndarray
    starts: np.ndarray
    lengths: np.ndarray
    ids: np.ndarray
    special: list[str]
    sizes: np.ndarray
    text: np.ndarray


def _load(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def code_point_classes(tokenizer) -> np.ndarray:
    """The class of each code point as the tokenizer's own pre-tokenizer treats it, so that Unicode versions can't differ."""
    out = np.full(LAST_CLASSED, OTHER, np.uint8)
    points = np.array([c for c in range(LAST_CLASSED) if not 0xD800 <= c < 0xE000])
    for some in np.array_split(points, 16):
        cut = {}
        for before, after in (("a", "1"), ("!", "a")):
            ends = np.zeros(3 * len(some) + 1, bool)
            ends[[e for _, (_, e) in tokenizer.pre_tokenizer.pre_tokenize_str("".join(before + chr(c) + after for c in some))]] = True
            cut[before] = (ends[1:-1:3], ends[2::3])
        out[some] = np.select([~cut["a"][0], ~cut["a"][1], ~cut["!"][0]], [LETTER, NUMBER, OTHER], SPACE)
    out[0x20] = SPACE
    return out


def cuts(classes: np.ndarray, points: np.ndarray, parts: np.ndarray) -> np.ndarray:
    """Where pre-tokens start; parts: starts of stretches that are cut each on its own."""
    kind = np.full(len(points), OTHER, np.uint8)
    low = points < LAST_CLASSED
    kind[low] = classes[points[low]]
    edge = np.zeros(len(points) + 3, bool)
    edge[parts] = True
    edge[len(points) :] = True
    run = np.ones(len(points), bool)
    run[1:] = kind[1:] != kind[:-1]
    run |= edge[: len(points)]
    start = run.copy()
    after_space = np.flatnonzero(run[1:] & (kind[1:] != SPACE) & (kind[:-1] == SPACE) & ~edge[1 : len(points)]) + 1
    start[after_space - 1] = True
    start[after_space] = points[after_space - 1] != 0x20
    # an apostrophe that stands alone before letters takes one or two of them
    quote = np.flatnonzero((points == 0x27) & start & run)
    quote = quote[~edge[quote + 1]]
    quote = quote[run[quote + 1] & (kind[quote + 1] == LETTER)]
    if len(quote):
        one = points[quote + 1]
        inside = ~edge[quote + 2]
        two = np.where(inside, points[np.minimum(quote + 2, len(points) - 1)], 0)
        s, t, m, d, r, v, el, e = (ord(c) for c in "stmdrvle")
        takes = np.where(np.isin(one, [s, t, m, d]), 1, np.where(((one == r) & (two == e)) | ((one == v) & (two == e)) | ((one == el) & (two == el)), 2, 0))
        quote, takes = quote[takes > 0], takes[takes > 0]
        start[quote + 1] = False
        ends = quote + 1 + takes
        start[ends[ends < len(points)]] = True
    return start


def vocabulary(path: str) -> Vocabulary:
    t = _load(path)
    classes = code_point_classes(t)
    special = [x.content for x in t.get_added_tokens_decoder().values()]
    words = t.decode_batch([[i] for i in range(t.get_vocab_size())], skip_special_tokens=False)
    words = sorted({w for w in words if w and "\ufffd" not in w and w not in special})
    sizes = np.array([len(w) for w in words], np.int64)
    points, ends = _points("".join(words)), np.cumsum(sizes)
    single = np.add.reduceat(cuts(classes, points, ends - sizes), ends - sizes, dtype=np.int64) == 1
    words, hashes = [w for w, one in zip(words, single.tolist(), strict=True) if one], span_hash(points, ends - sizes, ends)[single]
    ids = [x.ids for x in t.encode_batch(words, add_special_tokens=False)] + [[t.token_to_id(s)] for s in special]
    lengths = np.array([len(x) for x in ids], np.int64)
    flat = np.concatenate([np.asarray(x, np.uint32) for x in ids])
    hashes = np.append(hashes, np.array([_special_hash(k) for k in range(len(special))], np.uint64))
    texts = [*words, *special]
    return Vocabulary(path, classes, hashes, np.cumsum(lengths) - lengths, lengths, flat, special, np.array([len(w) for w in texts], np.int64), _points("".join(texts)))


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), np.uint32)


def _special_hash(k: int) -> int:
    return (1 << 63) + 2 * k + 1


class HashIndex:
    """64-bit keys to positions, open addressing in arrays; all operations take arrays."""

    def __init__(self, capacity: int):
        size = 1 << (2 * capacity - 1).bit_length()
        self.mask = np.uint64(size - 1)
        self.keys = np.zeros(size, np.uint64)
        self.values = np.full(size, -1, np.int32)
        self.n = 0

    def find(self, h: np.ndarray) -> np.ndarray:
        h = h + (h == 0)
        out = np.full(len(h), -1, np.int32)
        rest, slot = np.arange(len(h)), h & self.mask
        while len(rest):
            k = self.keys[slot]
            hit = k == h[rest]
            out[rest[hit]] = self.values[slot[hit]]
            more = ~hit & (k != 0)
            rest, slot = rest[more], (slot[more] + np.uint64(1)) & self.mask
        return out

    def add(self, h: np.ndarray, values: np.ndarray) -> None:
        """h: distinct and absent."""
        h = h + (h == 0)
        self.n += len(h)
        rest, slot = np.arange(len(h)), h & self.mask
        while len(rest):
            free = self.keys[slot] == 0
            self.keys[slot[free]] = h[rest[free]]
            won = self.keys[slot] == h[rest]
            self.values[slot[won]] = values[rest[won]]
            rest, slot = rest[~won], (slot[~won] + np.uint64(1)) & self.mask


class Encoder:
    """Token counts or ids of texts as the tokenizers library gives them, special strings inside texts included."""

    def __init__(self, vocab: Vocabulary, cached: int = 1 << 20, window: int = 1 << 20):
        """cached: distinct pre-tokens kept before the cache starts anew. window: code points handled at once."""
        self.vocab, self.cached, self.window = vocab, cached, window
        self.tokenizer = _load(vocab.path)
        # each word is encoded once, so that the library's own cache of words would only cost time
        if hasattr(self.tokenizer.model, "_resize_cache"):
            self.tokenizer.model._resize_cache(0)
        self.first = HashIndex(len(vocab.hashes))
        self.first.add(vocab.hashes, np.arange(len(vocab.hashes), dtype=np.int32))
        self.special = re.compile("(" + "|".join(map(re.escape, sorted(vocab.special, key=len, reverse=True))) + ")") if vocab.special else None
        # a special token that takes no space beside it may stand between words
        plain = [(t.content, k) for k, t in self.tokenizer.get_added_tokens_decoder().items() if t.special and not (t.lstrip or t.rstrip or t.single_word or t.normalized)]
        self.between = plain[0] if plain else None
        self.special_at = {s: _special_hash(k) for k, s in enumerate(vocab.special)}
        self._fresh()

    def _fresh(self) -> None:
        """The cache without anything but the first table. Entry arrays: place and number of ids, place and size of the text."""
        n = len(self.vocab.hashes)
        self.second = HashIndex(self.cached)
        self.starts, self.lengths, self.text_at, self.text_sizes = (np.zeros(n + self.cached + (1 << 18), np.int64) for _ in range(4))
        self.starts[:n], self.lengths[:n], self.text_sizes[:n] = self.vocab.starts, self.vocab.lengths, self.vocab.sizes
        self.text_at[:n] = np.cumsum(self.vocab.sizes) - self.vocab.sizes
        self.entries, self.filled, self.written = n, len(self.vocab.ids), len(self.vocab.text)
        self.flat, self.text = np.zeros(max(1 << 20, 2 * self.filled), np.uint32), np.zeros(max(1 << 20, 2 * self.written), np.uint32)
        self.flat[: self.filled], self.text[: self.written] = self.vocab.ids, self.vocab.text
        self.apart: dict[str, int] = {}

    def _encode(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The number of ids of each word, and the ids of all. Words go to the library as texts of many with a special
        token between two, which it cuts at; one by one where that does not give as many pieces as words."""
        if self.between and len(words) > 1:
            special, token = self.between
            texts = [special.join(words[k : k + JOINED]) for k in range(0, len(words), JOINED)]
            found = np.concatenate([np.array([*x.ids, token], np.uint32) for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)])
            ends = np.flatnonzero(found == token)
            if len(ends) == len(words):
                return np.diff(ends, prepend=-1) - 1, found[found != token]
        found = [x.ids for x in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
        lengths = np.array([len(x) for x in found], np.int64)
        return lengths, np.fromiter(chain.from_iterable(found), np.uint32, int(lengths.sum()))

    def _store(self, words: list[str]) -> int:
        """New entries for words; the number of the first."""
        lengths, ids = self._encode(words)
        sizes = np.array([len(w) for w in words], np.int64)
        total, points, n, at = int(lengths.sum()), _points("".join(words)), len(words), self.entries
        while self.filled + total > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        while self.written + len(points) > len(self.text):
            self.text = np.concatenate([self.text, np.zeros_like(self.text)])
        if at + n > len(self.starts):
            self.starts, self.lengths, self.text_at, self.text_sizes = (np.concatenate([x, np.zeros(max(n, len(x)), np.int64)]) for x in (self.starts, self.lengths, self.text_at, self.text_sizes))
        self.starts[at : at + n], self.text_at[at : at + n] = self.filled + np.cumsum(lengths) - lengths, self.written + np.cumsum(sizes) - sizes
        self.lengths[at : at + n], self.text_sizes[at : at + n] = lengths, sizes
        self.flat[self.filled : self.filled + total] = ids
        self.text[self.written : self.written + len(points)] = points
        self.entries, self.filled, self.written = at + n, self.filled + total, self.written + len(points)
        return at

    def _learn(self, hashes: np.ndarray, words: list[str]) -> None:
        at = self._store(words)
        self.second.add(hashes, np.arange(at, self.entries, dtype=np.int32))

    def _compare(self, entry: np.ndarray, points: np.ndarray, starts: np.ndarray, ends: np.ndarray, text: str) -> None:
        """Gives pre-tokens whose text is not that of their entry, which only shares its hash, an entry of their own."""
        sizes = ends - starts
        wrong = self.text_sizes[entry] != sizes
        stored = self.text[np.minimum(np.arange(len(points)) + np.repeat(self.text_at[entry] - starts, sizes), len(self.text) - 1)]
        wrong[np.searchsorted(starts, np.flatnonzero(stored != points), "right") - 1] = True
        for k in np.flatnonzero(wrong).tolist():
            word = text[starts[k] : ends[k]]
            if word not in self.apart:
                self.apart[word] = self._store([word])
            entry[k] = self.apart[word]

    def _look_up(self, parts: list[tuple[str, int]]) -> tuple[np.ndarray, np.ndarray]:
        """Entry of each pre-token of the parts (text, hash of a special token or 0), and each part's first pre-token (one more at the end)."""
        text = "".join(p for p, _ in parts)
        sizes = np.array([len(p) for p, _ in parts], np.int64)
        at = np.cumsum(sizes) - sizes
        points = _points(text)
        if not len(points):
            return np.zeros(0, np.int32), np.zeros(len(parts) + 1, np.int64)
        start = cuts(self.vocab.classes, points, at[sizes > 0])
        for (p, h), a in zip(parts, at, strict=True):
            if h:
                start[a + 1 : a + len(p)] = False
        starts = np.flatnonzero(start)
        ends = np.append(starts[1:], len(points))
        hashes = span_hash(points, starts, ends)
        for (_, h), a in zip(parts, at, strict=True):
            if h:
                hashes[np.searchsorted(starts, a)] = h
        entry = self.first.find(hashes)
        missed = np.flatnonzero(entry < 0)
        if len(missed):
            if self.second.n > self.cached // 2 or self.written > TEXT_ROOM:
                self._fresh()
            known = self.second.find(hashes[missed])
            new = missed[known < 0]
            entry[missed] = known
            while len(new):
                fresh, where = np.unique(hashes[new], return_index=True)
                room = max(self.cached - self.second.n, 0)
                if room < len(fresh) and self.second.n:
                    # entries already looked up for this batch would lose their place: make the table larger instead
                    larger = HashIndex(2 * max(self.cached, self.second.n + len(fresh)))
                    kept = self.second.keys != 0
                    larger.add(self.second.keys[kept], self.second.values[kept])
                    self.second = larger
                elif room < len(fresh):
                    self.second = HashIndex(2 * len(fresh))
                self._learn(fresh, [text[starts[k] : ends[k]] for k in new[where]])
                entry[new] = self.second.find(hashes[new])
                new = new[entry[new] < 0]
        self._compare(entry, points, starts, ends, text)
        return entry, np.searchsorted(starts, np.append(at, len(points)))

    def _pieces(self, text: str):
        """A text as parts no longer than the window where it can be cut safely: before a single space between two solid characters."""
        parts = self.special.split(text) if self.special and any(s in text for s in self.vocab.special) else [text]
        for p in parts:
            h = self.special_at.get(p, 0) if len(parts) > 1 else 0
            while not h and len(p) > self.window:
                k = self.window - 1
                while k > 0 and not (p[k] == " " and not p[k - 1].isspace() and not p[k + 1].isspace()):
                    k -= 1
                if k == 0:
                    break
                yield p[:k], 0
                p = p[k:]
            yield p, h

    def _rounds(self, texts: list[str]):
        """(entries, first pre-token of each part, the text of each part) for parts of up to a window in all."""
        parts, owner, size = [], [], 0
        for n, text in enumerate(texts):
            for p in self._pieces(text):
                if parts and size + len(p[0]) > self.window:
                    yield (*self._look_up(parts), np.array(owner))
                    parts, owner, size = [], [], 0
                parts.append(p)
                owner.append(n)
                size += len(p[0])
        if parts:
            yield (*self._look_up(parts), np.array(owner))

    def counts(self, texts: list[str]) -> np.ndarray:
        out = np.zeros(len(texts), np.int64)
        for entry, first, owner in self._rounds(texts):
            total = np.concatenate([[0], np.cumsum(self.lengths[entry])])[first]
            np.add.at(out, owner, np.diff(total))
        return out

    def ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in one array, and each text's first place (one more at the end)."""
        flats, n = [np.zeros(0, np.uint32)], np.zeros(len(texts), np.int64)
        for entry, first, owner in self._rounds(texts):
            lengths = self.lengths[entry]
            before = np.cumsum(lengths) - lengths
            flats.append(self.flat[np.repeat(self.starts[entry] - before, lengths) + np.arange(lengths.sum())])
            np.add.at(n, owner, np.diff(np.append(before, lengths.sum())[first]))
        return np.concatenate(flats), np.concatenate([[0], np.cumsum(n)])


_encoders: dict[str, Encoder] = {}


def encoder(vocab: Vocabulary) -> Encoder:
    """One encoder a worker process, whose cache serves all its tasks."""
    if vocab.path not in _encoders:
        _encoders[vocab.path] = Encoder(vocab)
    return _encoders[vocab.path]


_vocabularies: dict[str, Vocabulary] = {}


def broadcast_vocabulary(spark, path: str):
    if path not in _vocabularies:
        _vocabularies[path] = vocabulary(path)
    return spark.sparkContext.broadcast(_vocabularies[path])


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")
