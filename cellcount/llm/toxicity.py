"""Toxicity: a convolutional text classifier in numpy.

Words (runs of digits, letters and characters beyond ASCII; A-Z lower-cased) become the sum of the hashed embeddings
of the word, its first four bytes and its last three. Filters of widths 1, 2 and 3 slide over the whole text, each
keeps its largest response, and a logistic layer turns these into a score, calibrated by a temperature. Embedding
rows exist for the hashed features of at least two training documents; their first dimension starts at the signed
root of the feature's log-likelihood ratio between the classes. Thresholds for a verdict are chosen by language on
rows kept apart from training; the language is never an input of the score.

The model learns from at most ``PER_CLASS`` labelled rows of each class. Defined results: null and empty texts get the
score of a text without words; very long texts are read whole; without labelled rows of both classes each score is
0.5; repeated rows are scored one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow

from .decontam import words
from .labelled import Adam, sample, sigmoid, temperature

#: Labelled rows of a class that training reads at most.
PER_CLASS = 1500
HASH_BITS, DIM, FILTERS, WIDTHS = 22, 8, 8, (1, 2, 3)
EPOCHS, BATCH = 6, 64
#: Zero rows after each text, so that no window spans two.
PAD = max(WIDTHS)
#: Words of the documents that are scored at once.
CHUNK = 50_000
#: Words of which a worker keeps the embeddings, about.
MEMO = 100_000


def features(w: bytes) -> tuple[int, int, int]:
    """Hashed features of a word: itself, its first four bytes, its last three."""
    shift = 64 - HASH_BITS
    return tuple(xxhash.xxh64_intdigest(x) >> shift for x in (b"w" + w, b"^" + w[:4], b"$" + w[-3:]))


@dataclass
class Model:
    rows: dict[int, int]  # hashed feature -> embedding row; row 0 is zero
    emb: np.ndarray
    filters: list[np.ndarray]  # for each width: (width, DIM, FILTERS)
    bias: np.ndarray
    out: np.ndarray
    out_bias: float = 0.0
    temperature: float = 1.0
    thresholds: dict[str, float] = field(default_factory=dict)
    default_threshold: float = 0.7

    def embed(self, ids: np.ndarray) -> np.ndarray:
        return self.emb[ids].sum(axis=1)

    def pool(self, x: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Largest response of each filter in each text; its windows begin at rows ``starts`` to ``ends`` of ``x``."""
        at = np.stack([starts, ends], axis=1).ravel()
        return np.concatenate([np.maximum.reduceat(a, at, axis=0)[::2] for a in self.responses(x)], axis=1)

    def responses(self, x: np.ndarray) -> list[np.ndarray]:
        out = []
        for k, f in enumerate(self.filters):
            a = x @ f[0] + self.bias[k * FILTERS : (k + 1) * FILTERS]
            for j in range(1, len(f)):
                a[:-j] += x[j:] @ f[j]
            out.append(a)
        return out

    def logits(self, pooled: np.ndarray) -> np.ndarray:
        return np.maximum(pooled, 0) @ self.out + self.out_bias


def _lookup(model: Model):
    """word -> its row in a growing table of summed embeddings."""

    class Memo(dict):
        table = np.zeros((1 << 16, DIM), dtype=np.float32)
        used = 1

        def __missing__(self, w: bytes) -> int:
            ids = [model.rows.get(f, 0) for f in features(w)]
            if not any(ids):
                self[w] = 0
                return 0
            if self.used == len(self.table):
                self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.table[self.used] = model.emb[ids].sum(axis=0)
            self[w] = self.used
            self.used += 1
            return self.used - 1

    return Memo()


def _pool_long(model: Model, w: list[bytes], memo) -> np.ndarray:
    """``pool`` of one text of any length, in pieces that share the words of a filter: one row."""
    reach = max(len(f) for f in model.filters) - 1
    best = None
    for s in range(0, len(w), CHUNK):
        some = w[s : s + CHUNK + reach]
        ids = np.fromiter(map(memo.__getitem__, some), dtype=np.int64, count=len(some))
        last = s + CHUNK >= len(w)
        x = memo.table[np.r_[ids, np.zeros(PAD, dtype=np.int64)] if last else ids]
        top = np.concatenate([a[: min(len(some), CHUNK)].max(axis=0) for a in model.responses(x)])
        best = top if best is None else np.maximum(best, top)
        if len(memo) > MEMO:
            memo.clear()
            memo.used = 1
    return best[None]


def _scores(model: Model, texts: list[str | None], memo) -> np.ndarray:
    """The score of each text. ``memo`` is emptied between chunks only: a chunk's rows stay valid to its end."""
    out: list[np.ndarray] = []
    at: list[int] = []
    ends: list[int] = []
    part: list[np.ndarray] = []
    n = 0
    pad = np.zeros(PAD, dtype=np.int64)

    def flush() -> None:
        nonlocal n
        if at:
            x = memo.table[np.concatenate(part)]
            out.append(sigmoid(model.logits(model.pool(x, np.array(at), np.array(ends))) / model.temperature))
        at.clear()
        ends.clear()
        part.clear()
        n = 0
        if len(memo) > MEMO:
            memo.clear()
            memo.used = 1

    for t in texts:
        w = words(t)
        if n + len(w) > CHUNK:
            flush()
        if len(w) > CHUNK:
            out.append(sigmoid(model.logits(_pool_long(model, w, memo)) / model.temperature))
            continue
        at.append(n)
        ends.append(n + max(1, len(w)))
        part.extend((np.fromiter(map(memo.__getitem__, w), dtype=np.int64, count=len(w)), pad))
        n += len(w) + PAD
    flush()
    return np.concatenate(out) if out else np.zeros(0)


def train(texts: list[str], y: np.ndarray, langs: list[str], epochs: int = EPOCHS, seed: int = 3) -> Model | None:
    """Calibrate the temperature and the thresholds by language on a fifth of the rows, then fit on all of them."""
    y = np.asarray(y, dtype=np.float32)
    if not (y > 0).any() or not (y == 0).any():
        return None
    rng = np.random.default_rng(seed)
    apart = np.zeros(len(y), dtype=bool)
    for c in (0, 1):
        own = np.flatnonzero(y == c)
        apart[rng.permutation(own)[: len(own) // 5]] = True
    # The hashed features of the words of each text.
    memo: dict[bytes, tuple[int, int, int]] = {}
    docs = []
    for t in texts:
        w = words(t)
        for x in set(w):
            if x not in memo:
                memo[x] = features(x)
        docs.append(np.array([memo[x] for x in w], dtype=np.int32).reshape(-1, 3))
        if len(memo) > MEMO:
            memo.clear()
    model, _ = _fit(docs, y, np.arange(len(y)), epochs, seed)
    test = np.flatnonzero(apart)
    if (y[test] > 0).any():
        first, ids = _fit(docs, y, np.flatnonzero(~apart), epochs, seed)
        starts, ends, x = _stack(first, [ids[i] for i in test])
        z = first.logits(first.pool(x, starts, ends))
        model.temperature = min(4.0, max(0.25, temperature(z, y[test])))
        p = sigmoid(z / model.temperature)
        model.default_threshold = _threshold(p, y[test])
        for lang in sorted({langs[i] for i in test}):
            own = np.array([langs[i] == lang for i in test])
            if (y[test][own] > 0).sum() >= 5:
                model.thresholds[lang] = _threshold(p[own], y[test][own])
    return model


def _fit(docs: list[np.ndarray], y: np.ndarray, fit: np.ndarray, epochs: int, seed: int) -> tuple[Model, list[np.ndarray]]:
    """The network after training on the rows ``fit``, and the embedding rows of every text's words."""
    rng = np.random.default_rng(seed + 1)
    sets = [np.unique(docs[i]) for i in fit]
    seen, inverse = np.unique(np.concatenate(sets), return_inverse=True)
    each = np.repeat(y[fit], [len(s) for s in sets])
    pos, total = np.bincount(inverse, weights=each, minlength=len(seen)), np.bincount(inverse, minlength=len(seen))
    keep = total >= 2
    seen, pos, total = seen[keep], pos[keep], total[keep]
    n1, n = float(y[fit].sum()), float(len(fit))
    rows = dict(zip(seen.tolist(), range(1, len(seen) + 1), strict=True))
    emb = np.concatenate([np.zeros((1, DIM)), rng.normal(0, 0.05, (len(seen), DIM))]).astype(np.float32)
    emb[1:, 0] = _signed_root(pos, total, n1, n) / 4
    filters = [rng.normal(0, 0.3, (w, DIM, FILTERS)).astype(np.float32) for w in WIDTHS]
    for f in filters:
        f[:, 0, : FILTERS // 2] = 0.5
    model = Model(rows, emb, filters, np.zeros(FILTERS * len(WIDTHS), dtype=np.float32), np.full(FILTERS * len(WIDTHS), 0.1, dtype=np.float32))
    table = np.zeros(1 << HASH_BITS, dtype=np.int32)
    table[seen] = np.arange(1, len(seen) + 1)
    ids = [table[d] for d in docs]
    weight = np.where(y > 0, n / (2 * n1), n / (2 * max(1, n - n1))).astype(np.float32)
    out_bias = np.zeros(1, dtype=np.float32)
    adam, emb_adam = Adam([*model.filters, model.bias, model.out, out_bias], 0.01, 1e-4), Adam([model.emb], 0.002)
    # Small samples take more rounds, so that about 120 steps are made at least.
    for _ in range(max(epochs, int(np.ceil(120 * BATCH / len(fit))))):
        order = rng.permutation(fit)
        for s in range(0, len(fit), BATCH):
            part = order[s : s + BATCH]
            _step(model, [ids[i] for i in part], y[part], weight[part], out_bias, adam, emb_adam)
    model.out_bias = float(out_bias[0])
    return model, ids


def _signed_root(pos, total, n1: float, n: float) -> np.ndarray:
    """Signed root of the log-likelihood ratio of a feature's documents between the classes."""
    with np.errstate(divide="ignore", invalid="ignore"):
        term = lambda o, e: np.where(o > 0, o * np.log(o / e), 0.0)
        neg = total - pos
        g = 2 * (term(pos, total * n1 / n) + term(neg, total * (n - n1) / n) + term(n1 - pos, (n - total) * n1 / n) + term(n - n1 - neg, (n - total) * (n - n1) / n))
    return np.sign(pos / n1 - neg / (n - n1)) * np.sqrt(np.maximum(g, 0))


def _threshold(p: np.ndarray, y: np.ndarray) -> float:
    """The threshold in [0.3, 0.9] with the best F1; the middle of the best ones, so that both sides have room."""
    grid = np.linspace(0.3, 0.9, 61)
    f1 = np.array([2 * ((p >= t) & (y > 0)).sum() / max(1, (p >= t).sum() + (y > 0).sum()) for t in grid])
    return float(np.median(grid[f1 >= f1.max() - 1e-12]))


def _stack(model: Model, ids: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where the windows of each text begin, from and to, and the embeddings of all words; zeros keep texts apart."""
    pad = np.zeros((PAD, 3), dtype=np.int32)
    starts = np.cumsum([0, *[len(d) + PAD for d in ids[:-1]]])
    return starts, starts + np.array([max(1, len(d)) for d in ids]), model.embed(np.concatenate([x for d in ids for x in (d, pad)]))


def _step(model: Model, ids: list[np.ndarray], y, weight, out_bias, adam: Adam, emb_adam: Adam) -> None:
    """One step of Adam. Gradients of a maximum reach only the window that gave it."""
    model.out_bias = float(out_bias[0])
    pad = np.zeros((PAD, 3), dtype=np.int32)
    all_ids = np.concatenate([x for d in ids for x in (d, pad)])
    starts, ends, x = _stack(model, ids)
    where, pooled = [], []
    for a in model.responses(x):
        at = np.stack([s + a[s:e].argmax(axis=0) for s, e in zip(starts, ends, strict=True)])
        where.append(at)
        pooled.append(np.take_along_axis(a, at, axis=0))
    where, pooled = np.concatenate(where, axis=1), np.concatenate(pooled, axis=1)
    act = np.maximum(pooled, 0)
    g = (sigmoid(model.logits(pooled)) - y) * weight / len(y)
    g_pool = (g[:, None] * model.out) * (pooled > 0)
    grads, g_x = [], np.zeros((len(x) + PAD, DIM), dtype=np.float32)
    x = np.concatenate([x, np.zeros((PAD, DIM), dtype=np.float32)])
    for k, f in enumerate(model.filters):
        cols = slice(k * FILTERS, (k + 1) * FILTERS)
        at, gp, gf = where[:, cols], g_pool[:, cols], np.zeros_like(f)
        for j in range(len(f)):
            gf[j] = np.einsum("bfd,bf->df", x[at + j], gp)
            np.add.at(g_x, at + j, gp[:, :, None] * f[j].T[None])
        grads.append(gf)
    hot = np.flatnonzero(np.abs(g_x[: len(all_ids)]).sum(axis=1))
    g_emb = np.zeros_like(model.emb)
    for j in range(3):
        np.add.at(g_emb, all_ids[hot, j], g_x[hot])
    g_emb[0] = 0
    adam.step([*grads, g_pool.sum(axis=0), act.T @ g, np.array([g.sum()], dtype=np.float32)])
    emb_adam.step([g_emb])
    model.emb[0] = 0


def fit(docs: DataFrame, labels: DataFrame, learn: Column, label: str = "toxic", per_class: int = PER_CLASS, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model | None:
    """Train on a bounded sample of labelled rows that ``learn`` (over ``labels``) admits."""
    ids = sample(labels, label, learn, per_class, id_col)
    rows = docs.select(id_col, text_col, lang_col).join(F.broadcast(ids), id_col).select(F.col(text_col).alias("t"), F.col("y"), F.col(lang_col).alias("l"), F.col(id_col).alias("i")).toPandas().sort_values("i")
    return train(["" if t is None else t for t in rows["t"]], rows["y"].to_numpy(), [str(x) for x in rows["l"]])


def score(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text", lang_col: str | None = "lang") -> DataFrame:
    """id, score, flagged for each row. ``flagged``: score at or over its language's threshold."""
    spark = docs.sparkSession
    held = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        memo = _lookup(m) if m else None
        for b in batches:
            texts, langs = b.column(1).to_pylist(), b.column(2).to_pylist()
            p = _scores(m, texts, memo) if m else np.full(len(texts), 0.5)
            limit = np.array([m.thresholds.get(x, m.default_threshold) for x in langs]) if m else np.ones(len(texts))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(p.astype(np.float64)), pa.array(p >= limit, pa.bool_())], names=["doc_id", "score", "flagged"])

    lang = F.col(lang_col).cast("string") if lang_col else F.lit(None).cast("string")
    return arrow(docs.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string"), lang), run, "doc_id bigint, score double, flagged boolean")


def keep_clean(docs: DataFrame, model: Model | None, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """``docs`` without the rows that their language's threshold flags; all columns stay."""
    held = docs.sparkSession.sparkContext.broadcast(model)
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        memo = _lookup(m) if m else None
        for b in batches:
            if m:
                p = _scores(m, b.column(names.index(text_col)).to_pylist(), memo)
                limit = np.array([m.thresholds.get(x, m.default_threshold) for x in b.column(names.index(lang_col)).to_pylist()])
                b = b.filter(pa.array(p < limit, pa.bool_()))
            yield b

    return arrow(docs, run, docs.schema)
