"""Quality classifier: random-indexing word vectors and a two-layer network.

Words (and shape words: character classes, length band and repetition of the
word before) get sparse ternary index vectors from their hash; words whose hashes
agree in WORD_BITS bits share one, which bounds the table of vectors.  A word's vector
is its index vector plus the decayed sum of its neighbours' index vectors over
the fitting sample.  A document is the mean of its word vectors and of its shape
vectors over the whole text.  A two-layer network in numpy gives a logit, whose
temperature is calibrated on rows kept from the fit.

Defined cases: null, empty and blank texts have zero vectors and get the score
of such a document; without labels of both kinds every score is the share of
label 1 in the sample, or 1 where there is no sample; texts of any length are
scored whole; rows that repeat are scored alike; further columns go along, and the
score takes a free name; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .labelled import FIT_ROWS, fit_sample, remainder
from .store import Scratch

THRESHOLD = 0.3
FOLDS, HELD = 5, 0
DIMS, NONZERO = 32, 4
WORD_BITS, SHAPES = 15, 1 << 12
WINDOW = 2
HIDDEN = 32
FIT_PARTS = 4

_CLASS = np.zeros(256, np.uint8)
for _bit, _chars in enumerate(("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", ".,;:'\"()-", "!?", "#$%&*", "|/\\<>=_~^@[]{}+`")):
    _CLASS[np.frombuffer(_chars.encode(), np.uint8)] |= 1 << _bit
_CLASS[128:] |= 128


def index_vectors(ids: np.ndarray) -> np.ndarray:
    """Sparse ternary random vectors, the same for the same ids everywhere."""
    out = np.zeros((len(ids), DIMS), np.float32)
    for j in range(NONZERO):
        h = K.mix(ids.astype(np.uint64) * K.STEP + np.uint64(j + 1))
        sign = np.where(h >> np.uint64(63), 1.0, -1.0).astype(np.float32)
        np.add.at(out, (np.arange(len(ids)), (h % np.uint64(DIMS)).astype(np.int64)), sign)
    return out


def tokens(texts: K.Texts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word ids, shape ids, first word of each text) of a batch."""
    words = K.Words(texts)
    if not len(words.starts):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), words.first
    hashes = words.hashes()
    kinds = np.bitwise_or.reduceat(_CLASS[texts.data], words.starts).astype(np.int64)
    size = words.ends - words.starts
    band = (size > 1).astype(np.int64) + (size > 3) + (size > 12)
    inside = np.arange(len(hashes)) - np.repeat(words.first[:-1], np.diff(words.first))
    again = np.zeros(len(hashes), np.int64)
    again[1:] += (hashes[1:] == hashes[:-1]) & (inside[1:] > 0)
    again[2:] += 2 * ((hashes[2:] == hashes[:-2]) & (inside[2:] > 1))
    return (hashes >> np.uint64(64 - WORD_BITS)).astype(np.int64), kinds << 4 | band << 2 | again, words.first


def _pool(table: np.ndarray, ids: np.ndarray, first: np.ndarray) -> np.ndarray:
    out = np.zeros((len(first) - 1, table.shape[1]), np.float32)
    full = np.flatnonzero(np.diff(first))
    if len(full):
        out[full] = np.add.reduceat(table[ids], first[:-1][full], axis=0)
    return out / np.maximum(1, np.diff(first))[:, None]


def document_vectors(words: np.ndarray, shapes: np.ndarray, texts: K.Texts) -> np.ndarray:
    w, s, first = tokens(texts)
    n = np.diff(first).astype(np.float32)
    return np.concatenate([_pool(words, w, first), _pool(shapes, s, first), np.log1p(n)[:, None]], axis=1)


def _contexts(batches):
    """Summed neighbour index vectors of every word bucket over a task's texts."""
    base = index_vectors(np.arange(1 << WORD_BITS))
    total = np.zeros((1 << WORD_BITS, DIMS), np.float64)
    for batch in K.chunks(batches, "text"):
        w, _, first = tokens(K.Texts(batch.column(0)))
        if len(w) < 2:
            continue
        doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
        for d in range(1, WINDOW + 1):
            same = np.flatnonzero(doc[d:] == doc[:-d])
            for x, y in ((same, same + d), (same + d, same)):
                order = np.argsort(w[x], kind="stable")
                at = w[x][order]
                if len(at):
                    heads = np.flatnonzero(np.diff(at, prepend=-1))
                    total[at[heads]] += np.add.reduceat(base[w[y][order]], heads, axis=0) / d
    yield pa.RecordBatch.from_arrays([pa.array([total.astype(np.float32).tobytes()], pa.binary())], names=["sums"])


@dataclass
class Network:
    """Two layers over standardised inputs; ``temperature`` divides the logit."""

    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        hidden = np.tanh(((x - self.mean) / self.scale) @ self.w1 + self.b1)
        return (hidden @ self.w2 + self.b2).astype(np.float64)

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -50, 50)))


def fit_network(x: np.ndarray, y: np.ndarray, seed: int = 7, epochs: int = 120) -> Network:
    """Adam on the log loss with weight decay; a fifth of the rows calibrates the temperature."""
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(y))
    kept, fit = order[: len(y) // 5], order[len(y) // 5 :]
    mean, scale = x[fit].mean(0), x[fit].std(0) + 1e-3
    net = Network(mean, scale, rng.normal(0, x.shape[1] ** -0.5, (x.shape[1], HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, HIDDEN), 0.0)
    z = (x - mean) / scale
    params = [net.w1, net.b1, net.w2, np.zeros(1)]
    first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    step, batch = 0, 64
    for _ in range(epochs):
        rng.shuffle(fit)
        for at in range(0, len(fit), batch):
            rows = fit[at : at + batch]
            h = np.tanh(z[rows] @ params[0] + params[1])
            p = 1 / (1 + np.exp(-np.clip(h @ params[2] + params[3], -50, 50)))
            g = (p - y[rows]) / len(rows)
            gh = g[:, None] * params[2] * (1 - h * h)
            grads = [z[rows].T @ gh + 1e-3 * params[0], gh.sum(0), h.T @ g + 1e-3 * params[2], g.sum(keepdims=True)]
            step += 1
            for i, d in enumerate(grads):
                first[i] = 0.9 * first[i] + 0.1 * d
                second[i] = 0.999 * second[i] + 0.001 * d * d
                params[i] -= 3e-3 * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8)
    net.w1, net.b1, net.w2, net.b2 = params[0], params[1], params[2], float(params[3][0])
    if len(kept):
        logit, label = net.logits(x[kept]), y[kept]
        grid = np.exp(np.linspace(np.log(0.25), np.log(8), 61))
        loss = [np.mean(np.logaddexp(0, -np.where(label == 1, 1, -1) * logit / t)) for t in grid]
        net.temperature = float(grid[int(np.argmin(loss))])
    return net


@dataclass
class QualityModel:
    """Word and shape vectors with the network, or a constant score."""

    words: np.ndarray | None
    shapes: np.ndarray | None
    network: Network | None
    constant: float = 1.0

    def scores(self, column: pa.Array) -> np.ndarray:
        if self.network is None:
            return np.full(len(column), self.constant)
        return self.network.scores(document_vectors(self.words, self.shapes, K.Texts(column)))


def fit(documents: DataFrame, labels: DataFrame, rows: int = FIT_ROWS, scratch: Scratch | None = None) -> QualityModel:
    """Fit on at most ``rows`` labelled documents outside the held-out fold."""
    scratch = scratch or Scratch(documents.sparkSession, "quality")
    sample = scratch.keep(fit_sample(documents, labels, "quality", FOLDS, HELD, rows).repartition(FIT_PARTS, "doc_id"), "sample")
    counts = {r.label: r["count"] for r in sample.groupBy("label").count().collect()}  # two rows
    n = sum(counts.values())
    if len(counts) < 2 or n < 20:
        scratch.drop("sample")
        return QualityModel(None, None, None, counts.get(1, 0) / n if n else 1.0)
    sums = np.zeros((1 << WORD_BITS, DIMS), np.float32)
    for row in sample.coalesce(FIT_PARTS).select("text").mapInArrow(_contexts, "sums binary").collect():  # one of 4 MB for each of FIT_PARTS tasks
        sums += np.frombuffer(row.sums, np.float32).reshape(sums.shape)
    norm = np.linalg.norm(sums, axis=1, keepdims=True)
    words = index_vectors(np.arange(1 << WORD_BITS)) + 2 * sums / np.maximum(norm, 1)
    shapes = index_vectors(np.arange(SHAPES) + (1 << 20))

    def vectors(batches):
        for batch in K.chunks(batches, "text"):
            x = document_vectors(words, shapes, K.Texts(batch.column(1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array([r.tobytes() for r in x.astype(np.float32)], pa.binary())], names=["doc_id", "label", "x"])

    # at most ``rows`` rows of DIMS * 2 + 1 numbers
    got = sorted(sample.select("doc_id", "text", "label").mapInArrow(vectors, "doc_id long, label int, x binary").collect())
    x = np.stack([np.frombuffer(r.x, np.float32) for r in got]).astype(np.float64)
    y = np.array([r.label for r in got], np.float64)
    scratch.drop("sample")
    return QualityModel(words.astype(np.float32), shapes, fit_network(x, y))


def score(documents: DataFrame, model: QualityModel) -> DataFrame:
    """``documents`` with a column ``score``, from whole texts only."""
    from pyspark.sql.types import DoubleType, StructField, StructType

    name = "score"
    while name in documents.columns:
        name = "_" + name
    schema = StructType([*documents.schema.fields, StructField(name, DoubleType())])
    at = documents.columns.index("text")

    def run(batches):
        for batch in K.chunks(batches, "text"):
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(model.scores(batch.column(at)), pa.float64())], names=schema.names)

    return documents.mapInArrow(run, schema)


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality scores of all documents, with the held-out fold marked."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    scored = score(docs, fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select(
        "doc_id", (remainder(FOLDS) == HELD).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted")
    )
