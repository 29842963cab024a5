"""Toxicity by a weighted finite-state pattern grammar.

Words become symbols (insult, threat, target, negation, report, ...) through a
lexical transducer.  Three small transducers are composed into one table over
those symbols: negation softens an insult in its scope, reported speech marks it
as quoted, and the clause grammar weighs what is left: insults, insults with a
target, threats with an actor.  Clauses are scored as wholes, never single
words out of their clause; a document's score is a calibrated logistic of its
clause weights.

The lexicon is a short fixed list of general words plus all words and word stems
that labelled rows outside the held-out fold (a bounded sample of them) show to be
toxic.  Learning and scoring cut and fold words by one function: runs of letters
and marks of any script with the apostrophes between them, lower-cased in all of Unicode, so quotes,
dashes and full-width punctuation end a word.

Defined cases: null, empty and blank texts have no clause and get the score of a
document without matches; a text of any length is scored whole; without labels
the fixed list and default weights apply; rows that repeat are scored alike;
further columns, whatever their names, are not read; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .labelled import FIT_ROWS, fit_sample, remainder
from .store import Scratch

THRESHOLD = 0.3
FOLDS, HELD = 4, 2
MIN_SUPPORT, MIN_PRECISION, STRONG = 4, 0.92, 0.96
STEMS = (5, 6, 7, 8, 9, 10)  # stem lengths in bytes

# fixed values: symbols of the grammar
OTHER, INSULT, MILD, THREAT, WILL, TARGET, NEGATION, REPORT, INTENSIFIER, COPULA = range(10)
SOFT, QUOTED = 10, 11  # only between transducers
SYMBOLS = 12

# fixed values: general English word lists
WORDS = {
    INSULT: "idiot idiots moron morons imbecile scum vermin worthless pathetic disgusting loser losers trash filth degenerate subhuman bastard scumbag lowlife",
    MILD: "stupid dumb fool fools clown clowns jerk ugly garbage liar coward ridiculous useless",
    THREAT: "kill hurt destroy murder strangle shoot stab beat crush hang",
    WILL: "will gonna shall going want 'll",
    TARGET: "you your yours you're u ur he she they them him her his their these those this",
    NEGATION: "not never no nobody neither nor isn't aren't wasn't weren't don't doesn't didn't cannot can't won't without",
    REPORT: "said says saying wrote writes claimed claims called quoted reported according allegedly asked told",
    INTENSIFIER: "very such total totally complete completely absolute absolutely so utterly really",
    COPULA: "is are am was were be been being 're",
}

_LETTER = np.zeros(256, bool)
_LETTER[np.frombuffer(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ", np.uint8)] = True
_BREAK = np.zeros(256, bool)
_BREAK[np.frombuffer(b".!?;\n", np.uint8)] = True
_WIDE_BREAKS = "\u2026\u3002\uff01\uff0e\uff1b\uff1f"  # ellipsis, and the same marks of other scripts


def words_of(column: pa.Array) -> tuple[K.Texts, K.Words]:
    texts = K.Texts(pc.replace_substring(column, "\u2019", "'"), lower=True)
    return texts, K.Words(texts, True, _LETTER, K.LETTERS, ord("'"))


def breaks_of(texts: K.Texts) -> np.ndarray:
    """For each byte and the end, how many clause ends lie before it."""
    ends = _BREAK[texts.data]
    if len(texts.data) and texts.data.max() >= 0x80:
        for mark in _WIDE_BREAKS:
            a, b, c = mark.encode()
            at = np.flatnonzero(texts.data[:-2] == a)
            ends[at[(texts.data[at + 1] == b) & (texts.data[at + 2] == c)]] = True
    return np.concatenate([[0], np.cumsum(ends, dtype=np.int64)])


@dataclass
class Transducer:
    """A deterministic weighted transducer that reads and writes one symbol a step."""

    arcs: dict[tuple[int, int], tuple[int, int, float]] = field(default_factory=dict)  # (state, in) -> (state, out, weight)
    states: int = 1

    def compose(self, after: Transducer) -> Transducer:
        """This machine's output read by ``after``; weights add up."""
        out, number, todo = Transducer({}, 0), {(0, 0): 0}, [(0, 0)]
        while todo:
            pair = todo.pop()
            for symbol in range(SYMBOLS):
                if (pair[0], symbol) not in self.arcs:
                    continue
                p, middle, w = self.arcs[pair[0], symbol]
                q, written, v = after.arcs[pair[1], middle]
                if (p, q) not in number:
                    number[p, q] = len(number)
                    todo.append((p, q))
                out.arcs[number[pair], symbol] = (number[p, q], written, w + v)
        out.states = len(number)
        return out


def negation(scope: int = 3) -> Transducer:
    """Insults up to ``scope`` words behind a negation become SOFT."""
    t = Transducer({}, scope + 1)
    for state in range(scope + 1):
        for x in range(SYMBOLS):
            soft = x in (INSULT, MILD, THREAT) and state
            t.arcs[state, x] = (scope if x == NEGATION else max(0, state - 1), SOFT if soft else x, 0.0)
    return t


def reported() -> Transducer:
    """Insults after a reporting word become QUOTED to the clause's end."""
    t = Transducer({}, 2)
    for state in range(2):
        for x in range(SYMBOLS):
            quoted = state and x in (INSULT, MILD, THREAT)
            t.arcs[state, x] = (1 if x == REPORT else state, QUOTED if quoted else x, 0.0)
    return t


def clause_grammar() -> Transducer:
    """Weights of a clause; state bits: target seen, copula or intensifier just seen, intention seen."""
    # fixed values: clause weights
    base = {INSULT: 3.0, MILD: 2.0, SOFT: 0.25, QUOTED: 0.75}
    t = Transducer({}, 8)
    for state in range(8):
        target, near, will = state & 1, state & 2, state & 4
        for x in range(SYMBOLS):
            w = base.get(x, 0.0)
            if x in (INSULT, MILD):
                w += 1.0 * bool(target) + 0.5 * bool(near)
            if x == THREAT:
                w = 3.0 if will else 0.5
            now = (target or x == TARGET) | (2 if x in (COPULA, INTENSIFIER) else 0) | (4 if will or x == WILL else 0)
            t.arcs[state, x] = (int(now), x, w)
    return t


def grammar() -> Transducer:
    return negation().compose(reported()).compose(clause_grammar())


@dataclass
class ToxicityModel:
    """The lexicon (exact words, stems by length) and the logistic over clause features."""

    words: dict[int, int]
    stems: dict[int, dict[int, int]]
    weights: np.ndarray
    mean: np.ndarray
    scale: np.ndarray

    def prepare(self):
        machine = grammar()
        self._next = np.zeros((machine.states, SYMBOLS), np.int64)
        self._weight = np.zeros((machine.states, SYMBOLS))
        for (state, x), (to, _, w) in machine.arcs.items():
            self._next[state, x], self._weight[state, x] = to, w
        self._exact = K.HashLookup(self.words)
        self._stem = {n: K.HashLookup(t) for n, t in self.stems.items() if t}
        return self

    def features(self, column: pa.Array) -> np.ndarray:
        """(log total weight, log best clause, matched clauses, weight per 100 words) of each text."""
        texts, words = words_of(column)
        out = np.zeros((len(column), 4))
        hashes = words.hashes()
        symbol = np.zeros(len(hashes), np.int64)
        for n, lookup in self._stem.items():
            long = words.longer(n)
            at, value = lookup.find(words.prefix_hashes(long, n))
            symbol[long[at]] = value
        at, value = self._exact.find(hashes)
        symbol[at] = value
        breaks = breaks_of(texts)
        counts = np.diff(words.first)
        doc = np.repeat(np.arange(len(column)), counts)
        clause = breaks[words.starts] + doc  # a text's start also begins a clause
        hot = np.isin(symbol, (INSULT, MILD, THREAT))
        if not hot.any():
            return out
        some = np.flatnonzero((symbol != OTHER) & np.isin(clause, np.unique(clause[hot])))
        last, state, previous, weight = -1, 0, 0, 0.0

        def close(d):
            if weight > 0.9:
                out[d, 0] += weight
                out[d, 1] = max(out[d, 1], weight)
                out[d, 2] += 1

        owner = 0
        for i in some.tolist():
            if clause[i] != last:
                close(owner)
                last, state, weight, previous, owner = clause[i], 0, 0.0, i - 1, doc[i]
            for _ in range(min(4, i - previous - 1)):  # longer gaps change no state further
                weight += self._weight[state, OTHER]
                state = self._next[state, OTHER]
            weight += self._weight[state, symbol[i]]
            state = self._next[state, symbol[i]]
            previous = i
        close(owner)
        out[:, 3] = 100 * out[:, 0] / np.maximum(20, counts)
        out[:, :2] = np.log1p(out[:, :2])
        return out

    def scores(self, column: pa.Array) -> np.ndarray:
        x = (self.features(column) - self.mean) / self.scale
        return 1 / (1 + np.exp(-np.clip(x @ self.weights[1:] + self.weights[0], -50, 50)))


def _fixed_lexicon() -> dict[int, int]:
    return {int(words_of(pa.array([w]))[1].hashes()[0]): kind for kind, line in WORDS.items() for w in line.split()}


def _forms(batches):
    """(size, pattern, label) of the distinct words and stems of each text; a pattern is the hash that scoring looks up."""
    for batch in K.chunks(batches, "text"):
        _, words = words_of(batch.column(1))
        owner = np.repeat(np.arange(batch.num_rows), np.diff(words.first))
        found = [(0, words.hashes(), owner)]
        for n in STEMS:
            long = words.longer(n)
            found.append((n, words.prefix_hashes(long, n), owner[long]))
        sizes, patterns, owners = [], [], []
        for n, values, of in found:
            order = np.lexsort((values, of))
            values, of = values[order], of[order]
            new = np.append(True, (values[1:] != values[:-1]) | (of[1:] != of[:-1]))[: len(values)]
            sizes.append(np.full(int(new.sum()), n, np.int32))
            patterns.append(values[new])
            owners.append(of[new])
        yield pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate(sizes)), K.long_array(np.concatenate(patterns)), batch.column(2).take(pa.array(np.concatenate(owners)))], names=["size", "pattern", "label"]
        )


def _patterns(sample: DataFrame) -> DataFrame:
    """(stem length or 0, pattern, toxic documents, all documents) over the sample, each row of which counts."""
    each = sample.select("doc_id", "text", "label").mapInArrow(_forms, "size int, pattern long, label int")
    return each.groupBy("size", "pattern").agg(F.sum("label").alias("toxic"), F.count("*").alias("seen"))


def _logistic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    mean, scale = x.mean(0), x.std(0) + 1e-3
    z = np.concatenate([np.ones((len(x), 1)), (x - mean) / scale], axis=1)
    w, ridge = np.zeros(z.shape[1]), np.diag([1e-4] + [2e-2] * x.shape[1]) * len(x)
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        hess = (z * (p * (1 - p))[:, None]).T @ z + ridge
        w -= np.linalg.solve(hess, z.T @ (p - y) + ridge @ w)
    return w, mean, scale


def fit(documents: DataFrame, labels: DataFrame, rows: int = FIT_ROWS, scratch: Scratch | None = None) -> ToxicityModel:
    """Learn lexicon entries and calibrate on at most ``rows`` labelled documents outside the held-out fold.

    Entries are learnt on one half of the sample and the logistic on the other,
    so that the calibration sees the entries' true precision.
    """
    scratch = scratch or Scratch(documents.sparkSession, "toxic")
    sample = scratch.keep(fit_sample(documents, labels, "toxic", FOLDS, HELD, rows), "sample")
    base = ToxicityModel(_fixed_lexicon(), {}, np.array([-3.0, 2.5, 1.0, 0.5, 0.0]), np.zeros(4), np.ones(4))

    def lexicon(part: DataFrame) -> ToxicityModel:
        rate = F.col("toxic") / F.col("seen")
        found = _patterns(part).where((F.col("toxic") >= MIN_SUPPORT) & (rate >= MIN_PRECISION)).collect()  # bounded by the sample's words
        model = ToxicityModel(dict(base.words), {}, base.weights, base.mean, base.scale)
        for r in sorted(found):
            kind, value = INSULT if r.toxic / r.seen >= STRONG else MILD, r.pattern & K.MASK
            if r.size:
                model.stems.setdefault(r.size, {})[value] = kind
            else:
                model.words.setdefault(value, kind)
        return model

    half = F.pmod(F.xxhash64("doc_id", F.lit("half")), F.lit(2)) == 0
    model = lexicon(sample.where(half)).prepare()

    def features(batches):
        model.prepare()
        for batch in K.chunks(batches, "text"):
            x = model.features(batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), *(pa.array(x[:, j]) for j in range(4))], names=["doc_id", "label", "a", "b", "c", "d"])

    # at most ``rows`` rows of four numbers
    got = sorted(sample.where(~half).select("doc_id", "text", "label").mapInArrow(features, "doc_id long, label int, a double, b double, c double, d double").collect())
    y = np.array([r.label for r in got], np.float64)
    if 0 < y.sum() < len(y):
        weights, mean, scale = _logistic(np.array([r[2:] for r in got]), y)
        model = lexicon(sample)
        model.weights, model.mean, model.scale = weights, mean, scale
    scratch.drop("sample")
    return model


def score(documents: DataFrame, model: ToxicityModel) -> DataFrame:
    """(doc_id, score, clauses) of every row, from whole texts only."""

    def run(batches):
        model.prepare()
        for batch in K.chunks(batches, "text"):
            x = model.features(batch.column(1))
            p = 1 / (1 + np.exp(-np.clip((x - model.mean) / model.scale @ model.weights[1:] + model.weights[0], -50, 50)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p), pa.array(x[:, 2].astype(np.int64))], names=["doc_id", "score", "clauses"])

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(run, "doc_id long, score double, clauses long")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity scores of all documents, with the held-out fold marked."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    scored = score(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select(
        "doc_id", (remainder(FOLDS) == HELD).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), "clauses"
    )
