"""Quality: random-indexing word vectors, pooled per document, and a two-layer network in numpy.

A token is a word's core (A-Z lower-cased, end punctuation off) or its shape (case pattern, end punctuation);
both are hashed into ``BUCKETS`` buckets. Each bucket has a fixed random index vector of a few +1 and -1. One pass
over all documents adds, to each bucket's context vector, the index vectors of the tokens up to two words away:
each task sums its own buckets, so a task sends at most ``BUCKETS`` rows and the sum has ``BUCKETS`` rows in all,
however large the corpus. A document is the mean and spread of its tokens' (centred, normalised) vectors and how
alike successive words are; a two-layer network turns this into a score, calibrated by a temperature.

The network learns from at most ``PER_CLASS`` labelled rows of each class; the word vectors cover all documents.
Defined results: null and empty texts get the score of a text without words; very long texts are read whole, in
chunks; without labelled rows of both classes each score is 0.5; repeated rows count in the vectors as often as
they come and are scored one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow

from .labelled import Adam, sample, sigmoid, temperature

#: Buckets of cores, of shapes, and dimensions and non-zeros of an index vector.
CORES, SHAPES, DIM, NONZERO = 6144, 2048, 32, 4
BUCKETS = CORES + SHAPES
PER_CLASS = 3000
HIDDEN, EPOCHS, BATCH = 24, 60, 64
CHUNK = 100_000
_END = re.compile(r"[^\w]+$")


def index_vectors() -> np.ndarray:
    """The random index vectors, alike everywhere; the last row, of no token, is zero."""
    rng = np.random.default_rng(11)
    out = np.zeros((BUCKETS + 1, DIM), dtype=np.float32)
    for row in out[:-1]:
        row[rng.choice(DIM, NONZERO, replace=False)] = rng.choice((-1, 1), NONZERO)
    return out


def _shape(w: str, tail: str) -> str:
    kind = "d" if w.isdigit() else "A" if w.isupper() and len(w) > 1 else "Aa" if w[:1].isupper() else "a" if w.isalpha() else "x"
    return f"{kind}{tail}" if w else f"|{tail}"


class Tokens(dict):
    """word -> core bucket * 2^16 + shape bucket; emptied at 100,000 words."""

    def __missing__(self, word: str) -> int:
        if len(self) >= 100_000:
            self.clear()
        end = _END.search(word)
        tail = word[end.start() :] if end else ""
        core = word[: end.start()] if end else word
        a = xxhash.xxh64_intdigest(core.lower()) % CORES
        b = CORES + xxhash.xxh64_intdigest("\x00" + _shape(core, tail)) % SHAPES
        value = self[word] = a << 16 | b
        return value

    def pairs(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        x = np.fromiter(map(self.__getitem__, words), dtype=np.int64, count=len(words))
        return x >> 16, x & 0xFFFF


def _chunks(texts, memo: Tokens) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Core and shape buckets of many texts in pieces of about ``CHUNK`` words; the bucket of no token separates."""
    core, shape, n = [], [], 0
    gap = np.full(2, BUCKETS, dtype=np.int64)
    for t in texts:
        for w in _pieces(t):
            a, b = memo.pairs(w)
            core += [a, gap]
            shape += [b, gap]
            n += len(w) + 2
            if n >= CHUNK:
                yield np.concatenate(core), np.concatenate(shape)
                core, shape, n = [], [], 0
    if n:
        yield np.concatenate(core), np.concatenate(shape)


def _pieces(text: str | None) -> Iterator[list[str]]:
    w = (text or "").split()
    for s in range(0, len(w), CHUNK):
        yield w[s : s + CHUNK]


def contexts(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """The context vectors of all buckets over all documents: (BUCKETS, DIM) whole numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index, memo = index_vectors(), Tokens()
        total = np.zeros((BUCKETS + 1, DIM))
        for b in batches:
            for core, shape in _chunks((t.as_py() for t in b.column(0)), memo):
                both = index[core] + index[shape]
                near = np.zeros_like(both)
                for d in (1, 2):
                    near[d:] += both[:-d]
                    near[:-d] += both[d:]
                for ids in (core, shape):
                    order = np.argsort(ids, kind="stable")
                    own, start = np.unique(ids[order], return_index=True)
                    total[own] += np.add.reduceat(near[order], start, axis=0)
        rows = np.flatnonzero(np.abs(total[:-1]).sum(axis=1))
        cols = [pa.array(rows, pa.int32()), *[pa.array(total[rows, j].astype(np.int64)) for j in range(DIM)]]
        yield pa.RecordBatch.from_arrays(cols, names=["bucket", *[f"v{j}" for j in range(DIM)]])

    each = arrow(docs.select(F.col(text_col).cast("string")), run, "bucket int, " + ", ".join(f"v{j} bigint" for j in range(DIM)))
    rows = each.groupBy("bucket").agg(*[F.sum(f"v{j}").alias(f"v{j}") for j in range(DIM)]).collect()
    out = np.zeros((BUCKETS, DIM))
    for r in rows:
        out[r["bucket"]] = [r[f"v{j}"] for j in range(DIM)]
    return out


def word_vectors(context: np.ndarray) -> np.ndarray:
    """Unit vectors from context vectors without their common direction; a last row of zeros for no token."""
    size = np.linalg.norm(context, axis=1, keepdims=True)
    unit = np.divide(context, size, out=np.zeros_like(context), where=size > 0)
    unit[size[:, 0] > 0] -= unit[size[:, 0] > 0].mean(axis=0) if (size > 0).any() else 0
    size = np.linalg.norm(unit, axis=1, keepdims=True)
    unit = np.divide(unit, size, out=np.zeros_like(unit), where=size > 0)
    return np.concatenate([unit, np.zeros((1, context.shape[1]))]).astype(np.float32)


def pool(text: str | None, vectors: np.ndarray, memo: Tokens) -> np.ndarray:
    """Mean and spread of the core vectors, mean of the shape vectors, likeness of words one, two and three apart, log length."""
    n, total, square, shapes, alike = 0, np.zeros(DIM), np.zeros(DIM), np.zeros(DIM), np.zeros(3)
    for w in _pieces(text):
        core, shape = memo.pairs(w)
        x = vectors[core]
        n += len(w)
        total += x.sum(axis=0)
        square += np.einsum("ij,ij->j", x, x)
        counts = np.bincount(shape - CORES, minlength=SHAPES)
        at = np.flatnonzero(counts)
        shapes += counts[at] @ vectors[CORES + at]
        for d in (1, 2, 3):
            if len(x) > d:
                alike[d - 1] += np.einsum("ij,ij->", x[:-d], x[d:])
    k = max(n, 1)
    mean = total / k
    return np.concatenate([mean, np.sqrt(np.maximum(square / k - mean * mean, 0)), shapes / k, alike / k, [np.log1p(n) / 10, float(n == 0)]]).astype(np.float32)


@dataclass
class Model:
    vectors: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    params: list[np.ndarray]
    temperature: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        w1, b1, w2, b2 = self.params
        return np.maximum(((x - self.mean) / self.scale) @ w1 + b1, 0) @ w2 + b2[0]

    def scores(self, x: np.ndarray) -> np.ndarray:
        return sigmoid(self.logits(x) / self.temperature)


def train(x: np.ndarray, y: np.ndarray, vectors: np.ndarray, seed: int = 5) -> Model | None:
    """Fit on four fifths of the rows, with the temperature from the others."""
    y = np.asarray(y, dtype=np.float32)
    if not (y > 0).any() or not (y == 0).any():
        return None
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(y))
    apart, fit = order[: len(y) // 5], order[len(y) // 5 :]
    if not (y[fit] > 0).any() or not (y[fit] == 0).any():
        fit = order
    mean, scale = x[fit].mean(axis=0), x[fit].std(axis=0) + 1e-3
    params = [rng.normal(0, (2 / x.shape[1]) ** 0.5, (x.shape[1], HIDDEN)).astype(np.float32), np.zeros(HIDDEN, np.float32), rng.normal(0, 0.3, HIDDEN).astype(np.float32), np.zeros(1, np.float32)]
    model = Model(vectors, mean, scale, params, 1.0)
    z = ((x - mean) / scale).astype(np.float32)
    adam = Adam(params, 0.003, 1e-3)
    for _ in range(max(EPOCHS, int(np.ceil(600 * BATCH / len(fit))))):
        mixed = rng.permutation(fit)
        for s in range(0, len(mixed), BATCH):
            i = mixed[s : s + BATCH]
            h = z[i] @ params[0] + params[1]
            a = np.maximum(h, 0)
            g = (sigmoid(a @ params[2] + params[3][0]) - y[i]) / len(i)
            gh = (g[:, None] * params[2]) * (h > 0)
            adam.step([z[i].T @ gh, gh.sum(axis=0), a.T @ g, np.array([g.sum()], np.float32)])
    model.temperature = min(4.0, max(0.25, temperature(model.logits(x[apart]), y[apart])))
    return model


def _features(docs: DataFrame, vectors: np.ndarray, id_col: str, text_col: str) -> DataFrame:
    held = docs.sparkSession.sparkContext.broadcast(vectors)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = Tokens()
        for b in batches:
            x = [pool(t.as_py(), held.value, memo).tolist() for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x, pa.list_(pa.float32())), b.column(2)], names=["id", "x", "y"])

    return arrow(docs.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string"), F.col("y").cast("int")), run, "id bigint, x array<float>, y int")


def fit(docs: DataFrame, labels: DataFrame, learn: Column, label: str = "quality", per_class: int = PER_CLASS, id_col: str = "doc_id", text_col: str = "text") -> Model | None:
    """Word vectors over all of ``docs``; the network from a bounded sample of labelled rows that ``learn`` admits."""
    vectors = word_vectors(contexts(docs, text_col))
    ids = sample(labels, label, learn, per_class, id_col)
    rows = sorted(_features(docs.join(F.broadcast(ids), id_col), vectors, id_col, text_col).collect())
    if not rows:
        return None
    return train(np.array([r["x"] for r in rows], dtype=np.float32), np.array([r["y"] for r in rows]), vectors)


def score(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score for each row."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo, m = Tokens(), held.value
        for b in batches:
            p = np.full(b.num_rows, 0.5)
            if m and b.num_rows:
                p = m.scores(np.stack([pool(t.as_py(), m.vectors, memo) for t in b.column(1)]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(p.astype(np.float64))], names=["doc_id", "score"])

    return arrow(docs.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string")), run, "doc_id bigint, score double")
