"""Toxicity by a weighted pattern grammar over clauses: insult, threat, target, negation and reported-speech transducers.

A word is read as a symbol, its class in the lexicon (a public word list, and stems learnt from labelled rows) or none;
the end of a clause and of a sentence are symbols too. Each transducer is a table of next states and one of weights that
it writes while it reads. The five are composed once into one machine, whose weights are the products of theirs, and the
machine runs over all sentences of a batch side by side, one symbol a step. A clause's state at its end (was there a
target, a threat) sets the weight of the clause; a document's score is a logistic function of its clauses' weights.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankgrid.llm.decontaminate import BREAKS
from rankgrid.llm.learn import fold, labelled_sample, logistic, probability
from rankgrid.llm.pretokens import HashIndex
from rankgrid.llm.textblocks import LOWER, flat_text, map_arrow, small_batches, span_hash, word_spans
from rankgrid.llm.token_counts import id_and_text

#: Symbols: no class, the classes, and the ends of a clause within a sentence and of a sentence.
OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT, SOFT, HARD = range(8)
#: Fixed word lists of the transducers, from general knowledge; stems from labelled rows come on top.
LEXICON = {
    INSULT: "idiot idiots moron morons loser losers stupid pathetic worthless disgusting scum trash clown clowns fool fools imbecile jerk dumb garbage vermin filthy coward creep pig bastard retard degenerate parasite crap bitch whore asshole idiota imbécil estúpido estúpida basura asqueroso cabrón idiote imbécile connard ordure dégoûtant salaud crétin abruti dumm dummkopf trottel abschaum widerlich arschloch wertlos schwein".split(),
    THREAT: "kill murder hurt destroy beat stab shoot strangle punch burn hang matar golpear tuer frapper töten schlagen umbringen".split(),
    TARGET: "you your yours yourself u ur he she they him her them his their tú usted ustedes tu vous toi votre du dich dir ihr euch".split(),
    NEGATION: "not never no nor cannot don't isn't nicht kein keine nie pas jamais nunca".split(),
    REPORT: "said says wrote quoted reported claimed allegedly called dijo dit sagte".split(),
}
#: Weight of an entry before the labels are seen, factors of the flags and the target, and words a negation reaches.
PRIOR, NEGATED, REPORTED, TARGETED, REACH = 2.0, 0.5, 0.7, 1.3, 3
#: Factor of a clause with a threat and no target, and the share of a learnt stem's toxic documents where its clause has a target that makes it a threat.
AIMLESS, AIMED = 0.2, 0.8
#: Bounds: labelled rows learnt from, learnt stems, and the lengths of stems in bytes.
SAMPLE, STEMS, STEM_BYTES = 12_000, 3_000, (4, 5, 6, 7, 8, 9, 10)
#: Bytes that end a clause.
CLAUSE = np.zeros(256, bool)
CLAUSE[[ord(c) for c in ".,;:!?\n|"]] = True
#: Those of them that reported speech doesn't reach over.
SENTENCE = CLAUSE.copy()
SENTENCE[[ord(c) for c in ",:"]] = False


def folded(data: np.ndarray) -> np.ndarray:
    """Bytes with A-Z and the capital letters of Latin-1 in lower case."""
    out = LOWER[data]
    second = np.flatnonzero((data[1:] >= 0x80) & (data[1:] <= 0x9E) & (data[1:] != 0x97) & (data[:-1] == 0xC3)) + 1
    out[second] += 0x20
    return out


class Words:
    """The words of a buffer (runs of letters and digits) with hashes of whole words and of their first bytes."""

    def __init__(self, column: pa.Array):
        data, offsets = flat_text(column)
        self.data = folded(data)
        self.starts, self.ends, self.first = word_spans(self.data, offsets, BREAKS)
        self.row = np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))

    def whole(self) -> np.ndarray:
        return span_hash(self.data, self.starts, self.ends)

    def stems(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Words longer than size, and the hashes of their first size bytes."""
        at = np.flatnonzero(self.ends - self.starts > size)
        return at, span_hash(self.data, self.starts[at], self.starts[at] + size)

    def clauses(self) -> np.ndarray:
        """A number for the clause of each word; clauses don't cross documents."""
        return self._parts(CLAUSE)

    def sentences(self) -> np.ndarray:
        """A number for the sentence of each word, where commas and colons don't end one."""
        return self._parts(SENTENCE)

    def _parts(self, ends: np.ndarray) -> np.ndarray:
        stops = np.concatenate([[0], np.cumsum(ends[self.data])])
        return stops[self.starts] + self.row if len(self.starts) else np.zeros(0, np.int64)

    def contractions(self) -> tuple[np.ndarray, np.ndarray]:
        """Words that an apostrophe joins to the word before, and the hashes of both with the apostrophe."""
        joined = (self.starts[1:] == self.ends[:-1] + 1) & (self.row[1:] == self.row[:-1])
        at = np.flatnonzero(joined) + 1
        at = at[self.data[self.ends[at - 1]] == ord("'")]
        return at, span_hash(self.data, self.starts[at - 1], self.ends[at])


def _word_hash(word: bytes) -> int:
    return int(span_hash(np.frombuffer(word, np.uint8), np.array([0]), np.array([len(word)]))[0])


@dataclass
class Grammar:
    """Entries of all transducers: hash, bytes (0 for a whole word, else a stem's length), class and weight; and the logistic weights."""

    hashes: np.ndarray
    sizes: np.ndarray
    classes: np.ndarray
    weights: np.ndarray
    model: np.ndarray

    def machine(self) -> Machine:
        return Machine(self)


@dataclass(frozen=True)
class Transducer:
    """next[state, symbol], and weight[state, symbol] that is written while the symbol is read. It starts in state 0."""

    next: np.ndarray
    weight: np.ndarray

    @staticmethod
    def of(states: int, move, write=lambda state, symbol: 1.0) -> Transducer:
        cells = [[(move(s, a), write(s, a)) for a in range(HARD + 1)] for s in range(states)]
        return Transducer(np.array([[c[0] for c in row] for row in cells]), np.array([[c[1] for c in row] for row in cells], np.float64))


def _flag(symbol: int) -> Transducer:
    """State 1 from the symbol to the end of the clause."""
    return Transducer.of(2, lambda s, a: 0 if a in (SOFT, HARD) else 1 if a == symbol else s)


def transducers() -> dict[int, Transducer]:
    """Negation counts down the words it still reaches; reported speech holds for its clause (1) and the next of the sentence (2)."""
    hot = (INSULT, THREAT)
    negation = Transducer.of(REACH + 1, lambda s, a: 0 if a in (SOFT, HARD) else REACH if a == NEGATION else max(s - 1, 0), lambda s, a: NEGATED if s and a in hot else 1.0)
    report = Transducer.of(3, lambda s, a: {0: 0, 1: 2, 2: 0}[s] if a == SOFT else 0 if a == HARD else 1 if a == REPORT else s, lambda s, a: REPORTED if s and a in hot else 1.0)
    return {INSULT: _flag(INSULT), THREAT: _flag(THREAT), TARGET: _flag(TARGET), NEGATION: negation, REPORT: report}


def compose(parts: list[Transducer]) -> tuple[Transducer, np.ndarray]:
    """The machine that runs all parts at once, with the states that can be reached, and the parts' states of each of its states."""
    start = (0,) * len(parts)
    number, todo, moves, weights = {start: 0}, [start], [], []
    for state in todo:
        to = [tuple(int(p.next[s, a]) for p, s in zip(parts, state, strict=True)) for a in range(HARD + 1)]
        for t in to:
            if t not in number:
                number[t] = len(number)
                todo.append(t)
        moves.append([number[t] for t in to])
        weights.append([float(np.prod([p.weight[s, a] for p, s in zip(parts, state, strict=True)])) for a in range(HARD + 1)])
    return Transducer(np.array(moves), np.array(weights)), np.array(todo)


def run(machine: Transducer, symbols: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """The state before each symbol; stretches from each start to the next run side by side, each from state 0."""
    sizes = np.diff(np.append(starts, len(symbols)))
    order = np.argsort(-sizes, kind="stable")
    starts, sizes = starts[order], sizes[order]
    before, state = np.zeros(len(symbols), np.int64), np.zeros(len(starts), np.int64)
    for t in range(int(sizes[0]) if len(sizes) else 0):
        n = int(np.searchsorted(-sizes, -t, "left"))
        at = starts[:n] + t
        before[at] = state[:n]
        state[:n] = machine.next[state[:n], symbols[at]]
    return before


class Machine:
    def __init__(self, grammar: Grammar):
        self.grammar = grammar
        self.parts = []
        for size in np.unique(grammar.sizes).tolist():
            at = np.flatnonzero(grammar.sizes == size)
            index = HashIndex(len(at))
            index.add(grammar.hashes[at], at.astype(np.int32))
            self.parts.append((size, index))
        parts = transducers()
        self.machine, states = compose(list(parts.values()))
        of = dict(zip(parts, states.T, strict=True))
        self.aimed_threat = (of[THREAT] == 1) & (of[TARGET] == 1)
        self.clause_weight = np.where(of[TARGET] == 1, TARGETED, np.where(of[THREAT] == 1, AIMLESS, 1.0))

    def read(self, words: Words) -> tuple[np.ndarray, np.ndarray]:
        """Class and weight of each word, 0 for none; a longer entry wins over a shorter one, a whole word over a stem."""
        kind, weight = np.zeros(len(words.starts), np.int8), np.zeros(len(words.starts))
        for size, index in sorted(self.parts, key=lambda p: p[0] or 99):
            at, h = words.stems(size) if size else (np.arange(len(words.starts)), words.whole())
            entry = index.find(h)
            hit = entry >= 0
            kind[at[hit]], weight[at[hit]] = self.grammar.classes[entry[hit]], self.grammar.weights[entry[hit]]
            if not size:
                at, h = words.contractions()
                entry = index.find(h)
                hit = entry >= 0
                kind[at[hit]], weight[at[hit]] = self.grammar.classes[entry[hit]], self.grammar.weights[entry[hit]]
        return kind, weight

    def features(self, column: pa.Array) -> np.ndarray:
        """One row per text: log of 1 + summed weight, largest weight, log of 1 + matched clauses, any aimed threat, share of words matched."""
        words = Words(column)
        kind, weight = self.read(words)
        out = np.zeros((len(column), 5))
        hot = (kind == INSULT) | (kind == THREAT)
        if not hot.any():
            return out
        clause, sentence = words.clauses(), words.sentences()
        # the words that can matter: in sentences with an insult or threat, with a class or in reach of a negation
        reached = np.zeros(len(kind), bool)
        for k in range(1, REACH + 1):
            reached[k:] |= kind[:-k] == NEGATION
        at = np.flatnonzero(np.isin(sentence, sentence[hot]) & ((kind > 0) | reached))
        new = np.ones(len(at), bool)
        new[1:] = sentence[at[1:]] != sentence[at[:-1]]
        # before each word but a sentence's first as many clause ends as lie between (two say the same as more), after the last a sentence end
        stops = np.zeros(len(at), np.int64)
        stops[1:] = np.where(new[1:], 0, np.minimum(clause[at[1:]] - clause[at[:-1]], 2))
        width = stops + 1 + np.append(new[1:], True)
        ends = np.cumsum(width)
        place = ends - width + stops
        symbols = np.full(int(ends[-1]), SOFT)
        symbols[place] = kind[at]
        symbols[ends[np.append(new[1:], True)] - 1] = HARD
        before = run(self.machine, symbols, (ends - width)[new])
        close = np.flatnonzero(symbols >= SOFT)
        closing = before[close]
        which = np.flatnonzero(hot[at])
        its = np.searchsorted(close, place[which])
        w = weight[at[which]] * self.machine.weight[before[place[which]], symbols[place[which]]] * self.clause_weight[closing[its]]
        row = words.row[at[which]]
        sums, most, threats = np.zeros(len(column)), np.zeros(len(column)), np.zeros(len(column))
        np.add.at(sums, row, w)
        np.maximum.at(most, row, w)
        np.maximum.at(threats, row, self.aimed_threat[closing[its]].astype(np.float64))
        matched = np.bincount(row, minlength=len(column))
        clauses = np.bincount(row[np.unique(its, return_index=True)[1]], minlength=len(column))
        return np.stack([np.log1p(sums), most, np.log1p(clauses), threats, np.sqrt(matched / np.maximum(1, np.diff(words.first)))], axis=1)


def _pattern_counts(texts: DataFrame, sample: DataFrame) -> DataFrame:
    """pattern (hash), size, toxic, clean, aimed: documents of the sample with a word or stem, and those of the toxic with a target in a clause of it; counted within a task first."""

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = np.array([_word_hash(w.encode()) for w in LEXICON[TARGET]], np.uint64)
        targets = HashIndex(len(names))
        targets.add(names, np.arange(len(names), dtype=np.int32))
        for b in small_batches(batches, "text"):
            words, label = Words(b.column("text")), b.column("label").to_numpy()
            clause = words.clauses()
            near_target = np.isin(clause, clause[targets.find(words.whole()) >= 0])
            for size in (0, *STEM_BYTES):
                at, h = words.stems(size) if size else (np.arange(len(words.starts)), words.whole())
                order = np.lexsort((~near_target[at], words.row[at], h))
                h, row, near = h[order], words.row[at][order], near_target[at][order]
                lead = np.ones(len(h), bool)
                lead[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
                h, its, near = h[lead], label[row[lead]], near[lead]
                names, which = np.unique(h, return_inverse=True)
                toxic, aimed = (np.bincount(which, weights=x, minlength=len(names)).astype(np.int64) for x in (its, its * near))
                n = np.bincount(which, minlength=len(names))
                yield pa.RecordBatch.from_arrays([pa.array(names.view(np.int64)), pa.array(np.full(len(names), size, np.int32)), pa.array(toxic), pa.array(n - toxic), pa.array(aimed)], ["pattern", "size", "toxic", "clean", "aimed"])

    rows = texts.join(F.broadcast(sample), F.col("doc_id") == F.col("sample_id")).select("text", "label")
    return map_arrow(rows, each, "pattern long, size int, toxic long, clean long, aimed long").groupBy("pattern", "size").agg(*[F.sum(c).alias(c) for c in ("toxic", "clean", "aimed")])


def _lexicon() -> dict[tuple[int, int], tuple[int, float]]:
    return {(_word_hash(form.encode()), 0): (c, PRIOR if c == INSULT else 1.0) for c, words in LEXICON.items() for w in words for form in {w, w.replace("'", "’")}}


def fit(docs: DataFrame, labels: DataFrame, modulus: int = 5, held_out: int = 0, sample_rows: int = SAMPLE, id_col: str = "doc_id", text_col: str = "text") -> Grammar:
    """The grammar learnt from at most sample_rows labelled rows outside the held-out fold.

    A word or stem becomes an insult entry where labelled documents that have it are toxic far more often than others, a
    threat entry where besides its clauses there mostly have a target; an entry of the word list keeps its class. The
    weight is the smoothed log odds. The logistic weights are fitted to the clause features of the same rows.
    """
    texts = id_and_text(docs, id_col, text_col)
    sample = labelled_sample(labels, "toxic", modulus, held_out, sample_rows)
    totals = sample.agg(F.sum("label").alias("t"), F.count("*").alias("n")).first()
    toxic, clean = int(totals["t"] or 0), int((totals["n"] or 0) - (totals["t"] or 0))
    entries = _lexicon()
    if toxic and clean:
        odds = F.log((F.col("toxic") + 0.2) / (toxic + 0.4)) - F.log((F.col("clean") + 0.2) / (clean + 0.4))
        rows = _pattern_counts(texts, sample).where((F.col("toxic") >= 3) & (F.col("toxic") > 5 * F.col("clean"))).withColumn("odds", odds)
        for r in rows.where("odds > 2").orderBy(F.desc(F.col("toxic") * F.col("odds")), "pattern").limit(STEMS).collect():
            name = r["pattern"] % (1 << 64), r["size"]
            learnt = THREAT if r["aimed"] >= AIMED * r["toxic"] else INSULT
            known = entries.get(name, (learnt, 0.0))[0]
            if known in (INSULT, THREAT):
                entries[name] = (known, float(min(r["odds"], 6.0)))
    names = sorted(entries)
    grammar = Grammar(np.array([h for h, _ in names], np.uint64), np.array([s for _, s in names]), np.array([entries[k][0] for k in names], np.int8), np.array([entries[k][1] for k in names]), np.zeros(6))
    x, y = sample_features(texts, sample, grammar)
    if len(y) and y.min() != y.max():
        grammar.model = logistic(x, y, ridge=0.5)
    else:
        grammar.model = np.array([1.0, 0.5, 0.0, 0.5, 0.0, -3.0])
    return grammar


def sample_features(texts: DataFrame, sample: DataFrame, grammar: Grammar) -> tuple[np.ndarray, np.ndarray]:
    shared = texts.sparkSession.sparkContext.broadcast(grammar)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = shared.value.machine()
        for b in small_batches(batches, "text"):
            x = machine.features(b.column("text"))
            yield pa.RecordBatch.from_arrays([b.column("label"), *[pa.array(x[:, k]) for k in range(x.shape[1])]], ["label", *[f"x{k}" for k in range(x.shape[1])]])

    rows = map_arrow(texts.join(F.broadcast(sample), F.col("doc_id") == F.col("sample_id")).select("text", "label"), each, "label int, x0 double, x1 double, x2 double, x3 double, x4 double").toPandas()
    return rows.drop(columns="label").to_numpy(np.float64), rows["label"].to_numpy(np.float64)


def score(docs: DataFrame, grammar: Grammar, modulus: int = 5, held_out: int = 0, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, held_out, score (0 to 1), predicted (score >= threshold).

    Null, empty and wordless texts get the score of a text without matches; repeated rows are scored each; a null id
    stays null and is not held out; an empty table gives no rows; long texts are read whole; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(grammar)

    def each(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = shared.value.machine()
        for b in small_batches(batches, "text"):
            p = probability(machine.features(b.column("text")), shared.value.model)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(p), pa.array((p >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    texts = id_and_text(docs, id_col, text_col).withColumn("held_out", F.coalesce(fold(F.col("doc_id"), modulus) == held_out, F.lit(False)))
    return map_arrow(texts, each, "doc_id long, held_out boolean, score double, predicted int")
