"""Quality classifier on supervised subword embeddings.

A word's vector is the mean of the learned vectors of its hash bucket and of the buckets of its
character n-grams; a document's vector is the mean over its words plus the mean over a few shape
tokens (length, repetition). A softmax layer gives the score. The model is trained by minibatch
stochastic gradient descent in numpy.

It is fitted on a bounded sample: at most Settings.sample labelled rows, those of smallest hash. The
model's size is fixed, so broadcasting it with the plan is safe. Scores cover all rows and whole texts.

Defined results: null and empty texts have shape tokens only and get a score from those. If no labelled
row is left for training, or only one label, the score is the share of label 1 (one half without rows).
Repeats, ties and null ids need no care; extra columns are left alone.
"""

from __future__ import annotations

import hashlib
import zlib
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import per_worker, read_table

WORDS_KEPT = 150_000  # word vectors that a worker remembers before it starts anew


@dataclass(frozen=True)
class Settings:
    sample: int = 4000
    buckets: int = 1 << 16
    dim: int = 8
    grams: tuple[int, ...] = (3, 4, 5)
    epochs: int = 8
    rate: float = 0.5
    batch: int = 32
    vector_rate: float = 2.0
    shape_weight: float = 2.0
    seed: int = 7
    threshold: float = 0.3


def word_features(words: list[bytes], s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all features of all words, in order of the words, and how many each word has."""
    marked = [b"<" + w + b">" for w in words]
    sizes = np.array([len(w) for w in marked], np.int64)
    data = np.frombuffer(b"".join(marked), np.uint8).astype(np.uint64) + np.uint64(1)
    owner = np.repeat(np.arange(len(words)), sizes)
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(data))  # bytes left in the word
    buckets, owners = [np.array([zlib.crc32(w) % s.buckets for w in words], np.int64)], [np.arange(len(words))]
    for n in s.grams:
        if len(data) < n:
            continue
        h = np.full(len(data) - n + 1, 14695981039346656037 % (1 << 64), np.uint64)
        for k in range(n):
            h = (h ^ data[k : len(data) - n + 1 + k]) * np.uint64(1099511628211)
        h ^= h >> np.uint64(29)
        inside = left[: len(h)] >= n
        buckets.append((h[inside] % np.uint64(s.buckets)).astype(np.int64))
        owners.append(owner[: len(h)][inside])
    who = np.concatenate(owners)
    order = np.argsort(who, kind="stable")
    return np.concatenate(buckets)[order], np.bincount(who, minlength=len(words))


def shape_tokens(words: list[bytes], text: str) -> list[bytes]:
    """Tokens for what the bag of words can't show; a blank inside keeps them apart from words."""
    n, kinds = len(words), len(set(words))
    lines = text.split("\n")
    stutter = sum(map(eq, words, words[1:]))
    marks = sum(text.count(c) for c in "#*$%&|<>")
    return [
        b"shape length %d" % n.bit_length(),
        b"shape kinds %d" % (10 * kinds // max(1, n)),
        b"shape stutter %d" % (20 * stutter // max(1, n)),
        b"shape width %d" % min(30, sum(map(len, words)) // max(1, n)),
        b"shape lines %d" % (10 * len(set(lines)) // len(lines)),
        b"shape marks %d" % min(12, (1000 * marks // max(1, len(text))).bit_length()),
    ]


@dataclass
class Model:
    settings: Settings
    vectors: np.ndarray
    weights: np.ndarray
    bias: np.ndarray
    digest: str = ""  # of all parameters, made once; it tells the word tables of models apart

    def __post_init__(self):
        parts = (repr(self.settings).encode(), *(np.ascontiguousarray(x).data for x in (self.vectors, self.weights, self.bias)))
        whole = hashlib.sha256()
        for part in parts:
            whole.update(part)
        self.digest = whole.hexdigest()

    def word_vectors(self, words: list[bytes]) -> np.ndarray:
        features, counts = word_features(words, self.settings)
        ends = np.cumsum(counts)
        return np.add.reduceat(self.vectors[features], ends - counts, axis=0) / counts[:, None]

    def scores(self, texts: list[str | None]) -> list[float]:
        number, table = per_worker("quality_classifier", self.digest, lambda: ({}, [np.zeros((0, self.settings.dim))]))
        if len(number) > WORDS_KEPT:
            number.clear()
            table[0] = table[0][:0]
        split = [((t or "").encode("utf-8", "replace").split(), t or "") for t in texts]
        tokens = [(w, shape_tokens(w, t)) for w, t in split]
        new = list({x for both in tokens for part in both for x in part if x not in number})
        if new:
            for x in new:
                number[x] = len(number)
            table[0] = np.concatenate([table[0], *(self.word_vectors(new[i : i + 50_000]) for i in range(0, len(new), 50_000))])
        rows = table[0]
        out = np.empty((len(texts), self.settings.dim))
        for i, (words, shape) in enumerate(tokens):
            out[i] = rows[[number[x] for x in shape]].mean(axis=0) * self.settings.shape_weight
            if words:
                out[i] += rows[np.fromiter(map(number.__getitem__, words), np.int64, len(words))].mean(axis=0)
        return softmax(out @ self.weights + self.bias)[:, 1].tolist()


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def train(texts: list[str | None], labels: list[int], s: Settings = Settings()) -> Model:
    """Fit the model by stochastic gradient descent; the same input gives the same model."""
    rng = np.random.default_rng(s.seed)
    vectors = rng.uniform(-1, 1, (s.buckets, s.dim)) / s.dim
    y = np.array(labels, np.int64)
    if len(set(labels)) < 2:
        share = float(y.mean()) if len(y) else 0.5
        share = min(max(share, 1e-3), 1 - 1e-3)
        return Model(s, vectors * 0, np.zeros((s.dim, 2)), np.log(np.array([1 - share, share])))
    docs: list[tuple[np.ndarray, np.ndarray]] = []
    known: dict[bytes, np.ndarray] = {}
    for text in texts:
        words = (text or "").encode("utf-8", "replace").split()
        bag: dict[bytes, float] = {}
        for group, share in ((words, 1.0), (shape_tokens(words, text or ""), s.shape_weight)):
            for w in group:
                bag[w] = bag.get(w, 0.0) + share / len(group)
        fresh = [w for w in bag if w not in known]
        if fresh:
            features, counts = word_features(fresh, s)
            for w, f in zip(fresh, np.split(features.astype(np.int32), np.cumsum(counts)[:-1]), strict=True):
                known[w] = f
        if len(known) > WORDS_KEPT:
            known = {w: known[w] for w in bag}
        index = np.concatenate([known[w] for w in bag])
        weight = np.concatenate([np.full(len(known[w]), v / len(known[w]), np.float32) for w, v in bag.items()])
        kinds, where = np.unique(index, return_inverse=True)
        docs.append((kinds.astype(np.int32), np.bincount(where, weight).astype(np.float32)))
    weights, bias = np.zeros((s.dim, 2)), np.zeros(2)
    steps, done = s.epochs * -(-len(docs) // s.batch), 0
    for _ in range(s.epochs):
        order = rng.permutation(len(docs))
        for at in range(0, len(order), s.batch):
            own = order[at : at + s.batch]
            rate = s.rate * (1 - done / steps)
            done += 1
            sizes = np.array([len(docs[i][0]) for i in own])
            index = np.concatenate([docs[i][0] for i in own])
            weight = np.concatenate([docs[i][1] for i in own]).astype(np.float64)
            hidden = np.add.reduceat(vectors[index] * weight[:, None], np.cumsum(sizes) - sizes, axis=0)
            error = softmax(hidden @ weights + bias)
            error[np.arange(len(own)), y[own]] -= 1
            back = np.repeat(error @ weights.T, sizes, axis=0) * weight[:, None]
            weights -= rate * hidden.T @ error / len(own) * 4
            bias -= rate * error.mean(axis=0)
            for k in range(s.dim):  # the vectors see small weights, so their step is scaled up
                vectors[:, k] -= s.vector_rate * rate * np.bincount(index, back[:, k], minlength=s.buckets)
    return Model(s, vectors, weights, bias)


def remainder():
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5


def fit(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> Model:
    """Train on labelled rows whose remainder isn't 0. The sample is drawn by id before texts are read."""
    known = labels.select("doc_id", F.col("quality").alias("label")).where(F.col("doc_id").isNotNull() & F.col("label").isNotNull() & (remainder() != 0))
    chosen = known.groupBy("doc_id").agg(F.max("label").alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.sample)
    texts = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "label").agg(F.max("text").alias("text"))
    rows = sorted(texts.collect())  # bounded: s.sample rows
    return train([r.text for r in rows], [int(r.label) for r in rows], s)


def score(docs: DataFrame, model: Model) -> DataFrame:
    threshold = model.settings.threshold

    def run(batches):
        for batch in batches:
            for part in range(0, batch.num_rows, 2000):
                rows = batch.slice(part, 2000)
                p = model.scores(rows.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([rows.column(0).cast(pa.int64()), pa.array(p, pa.float64()), pa.array([int(x >= threshold) for x in p], pa.int32())], ["doc_id", "score", "predicted"])

    out = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double, predicted int")
    return out.select("doc_id", F.coalesce(remainder() == 0, F.lit(False)).alias("held_out"), "score", "predicted")


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return score(docs, fit(docs, read_table(spark, sf_dir, "labels")))
