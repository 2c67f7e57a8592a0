"""Benchmark decontamination by winnowing.

Words are runs of digits, a-z (after lower-casing A-Z) and characters beyond ASCII. Of each text, the smallest
of every ``WINNOW`` successive ``GRAM``-word hashes is kept (all that tie), on the benchmark's and the documents'
side alike, so two texts that share ``GRAM + WINNOW - 1 = 13`` words in a row share a kept fingerprint. Equal
fingerprints are extended to the left and right word by word; spans of 13 words or more are hits. Items of fewer
words are one window of their own length and are looked up at every position.

Equal benchmark rows count once, and long items are cut into overlapping pieces that hold every window. The pieces are
dealt to blocks of about ``BLOCK_CHARS`` characters; each block's index is broadcast, so what is broadcast has a
bound, and a larger benchmark takes more passes over the documents.

Defined results: null and empty texts have no words, no hits, and the digest of the empty string; very long texts
are processed whole; repeated benchmark rows count once by item_id; repeated documents are judged row by row; an
empty benchmark hits nothing; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow, ngram_hashes, stage

WINDOW, GRAM, WINNOW = 13, 7, 7
BLOCK_CHARS = 16_000_000
#: Everything but digits, letters and bytes beyond ASCII becomes a space; A-Z become a-z.
_WORDS = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_WORDS).split() if text else []


def winnow(hashes: np.ndarray, w: int = WINNOW) -> np.ndarray:
    """Positions that are the smallest of some ``w`` successive hashes; of fewer than ``w`` hashes, none."""
    if len(hashes) < w:
        return np.zeros(0, dtype=np.int64)
    low = np.lib.stride_tricks.sliding_window_view(hashes, w).min(axis=1) if w not in (7,) else _low7(hashes)
    keep = np.zeros(len(hashes), dtype=bool)
    n = len(low)
    for s in range(w):
        keep[s : s + n] |= hashes[s : s + n] == low
    return np.flatnonzero(keep)


def _low7(h: np.ndarray) -> np.ndarray:
    """Minimum of each 7 successive values by doubling."""
    two = np.minimum(h[:-1], h[1:])
    four = np.minimum(two[:-2], two[2:])
    return np.minimum(four[:-3], four[3:])


class Index:
    """Fingerprints of a block of benchmark items."""

    def __init__(self, items: list[tuple[str, str | None]]):
        self.vocab: dict[bytes, int] = {}
        self.items: list[tuple[str, np.ndarray]] = []
        spots = defaultdict(list)
        self.short: dict[int, dict[int, list[int]]] = {}
        for item, text in items:
            w = words(text)
            if not w:
                continue
            a = np.array([self.vocab.setdefault(x, len(self.vocab) + 1) for x in w], dtype=np.uint64)
            k = len(self.items)
            self.items.append((item, a))
            if len(a) < WINDOW:
                self.short.setdefault(len(a), {}).setdefault(int(ngram_hashes(a, len(a))[0]), []).append(k)
                continue
            h = ngram_hashes(a, GRAM)
            for p in winnow(h).tolist():
                spots[int(h[p])].append((k, p))
        self.spots = dict(spots)
        self.prints = np.sort(np.fromiter(self.spots, dtype=np.uint64, count=len(self.spots)))
        self.short_prints = {n: np.sort(np.fromiter(x, dtype=np.uint64, count=len(x))) for n, x in self.short.items()}

    def hits(self, w: list[bytes]) -> tuple[np.ndarray, set[str]]:
        """Which words of a document lie in an occurring window, and the items those windows belong to."""
        get = self.vocab.get
        a = np.fromiter([get(x, 0) for x in w], dtype=np.uint64, count=len(w))
        hit, found = np.zeros(len(a), dtype=bool), set()
        if len(self.prints) and len(a) >= WINDOW:
            h = ngram_hashes(a, GRAM)
            at = winnow(h)
            at = at[_among(h[at], self.prints)]
            ends: dict[tuple[int, int], int] = {}
            for p in at.tolist():
                for k, q in self.spots[int(h[p])]:
                    if ends.get((k, p - q), -1) > p:
                        continue
                    lo, hi = extend(a, p, self.items[k][1], q)
                    ends[k, p - q] = hi
                    if hi - lo >= WINDOW:
                        hit[lo:hi] = True
                        found.add(self.items[k][0])
        for n, prints in self.short_prints.items():
            if len(a) >= n:
                h = ngram_hashes(a, n)
                for p in np.flatnonzero(_among(h, prints)).tolist():
                    for k in self.short[n][int(h[p])]:
                        if np.array_equal(a[p : p + n], self.items[k][1]):
                            hit[p : p + n] = True
                            found.add(self.items[k][0])
        return hit, found


def _among(x: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which of ``x`` are in the sorted, not empty array ``known``."""
    return known[np.minimum(np.searchsorted(known, x), len(known) - 1)] == x


def extend(a: np.ndarray, p: int, b: np.ndarray, q: int) -> tuple[int, int]:
    """The longest span of ``a`` around ``p`` that equals ``b`` around ``q``; empty where they differ there."""
    n = min(len(a) - p, len(b) - q)
    off = np.flatnonzero(a[p : p + n] != b[q : q + n])
    right = int(off[0]) if len(off) else n
    m = min(p, q)
    off = np.flatnonzero(a[p - m : p] != b[q - m : q])
    left = m - 1 - int(off[-1]) if len(off) else m
    return p - left, p + right


#: Words of a piece of a long benchmark item; the next piece repeats the last window's words but one.
PIECE = 4096


def _cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """item, text: each item's words, in pieces that hold every window whole, so that no item outgrows a block."""
    for b in batches:
        rows = []
        for item, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            w = words(text.as_py())
            for s in range(0, max(1, len(w) - WINDOW + 1), PIECE):
                if w:
                    rows.append((item, b" ".join(w[s : s + PIECE + WINDOW - 1]).decode("utf-8", "surrogatepass")))
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string()) for i in (0, 1)], names=["item", "text"])


SCHEMA = "doc_id bigint, n_words bigint, hit_bits binary, items array<string>"


def hits(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", block_chars: int = BLOCK_CHARS) -> DataFrame:
    """doc_id, n_words, hit_bits (a bit for each word, packed), items: the items whose windows occur."""
    spark = docs.sparkSession
    bench = benchmark.select(F.coalesce(F.col(item_col).cast("string"), F.lit("")).alias("item"), F.col(text_col).cast("string").alias("text"))
    bench = stage(arrow(bench.distinct(), _cut, "item string, text string").distinct(), "bench")
    chars = bench.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = -(-chars // block_chars) or 1
    src = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.lit(None).cast("binary").alias("hit_bits"), F.array().cast("array<string>").alias("items"))
    for k in range(blocks):
        part = bench.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == k).collect()
        index = spark.sparkContext.broadcast(Index([(r.item, r.text) for r in part]))
        last = k == blocks - 1

        def run(batches: Iterator[pa.RecordBatch], index=index, last=last) -> Iterator[pa.RecordBatch]:
            for b in batches:
                doc, text, bits, items = b.columns
                n, out, names = [], [], []
                for t, had, old in zip(text, bits, items, strict=True):
                    w = words(t.as_py())
                    hit, found = index.value.hits(w)
                    if had.is_valid:
                        hit |= np.unpackbits(np.frombuffer(had.as_py(), dtype=np.uint8), count=len(w)).astype(bool)
                    n.append(len(w))
                    out.append(np.packbits(hit).tobytes())
                    names.append(sorted({*old.as_py(), *found}))
                cols = [pa.array(out, pa.binary()), pa.array(names, pa.list_(pa.string()))]
                if last:
                    yield pa.RecordBatch.from_arrays([doc, pa.array(n, pa.int64()), *cols], names=["doc_id", "n_words", "hit_bits", "items"])
                else:
                    yield pa.RecordBatch.from_arrays([doc, text, *cols], names=["doc_id", "text", "hit_bits", "items"])

        src = arrow(src, run, SCHEMA if last else "doc_id bigint, text string, hit_bits binary, items array<string>")
        if not last:
            src = stage(src, "decontam")
    return src


def report(found: DataFrame, share: int = 20) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated: a document with a twentieth of its words hit, or more, is contaminated."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n_hit = [int(np.unpackbits(np.frombuffer(x.as_py(), dtype=np.uint8)).sum()) for x in b.column(2)]
            items = b.column(3).to_pylist()
            n = b.column(1).to_pylist()
            cols = [b.column(0), b.column(1), pa.array(n_hit, pa.int64()), pa.array([len(x) for x in items], pa.int64()), pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in items]), pa.array([h > 0 and share * h >= k for h, k in zip(n_hit, n, strict=True)], pa.bool_())]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])

    return arrow(found, run, "doc_id bigint, n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean")
