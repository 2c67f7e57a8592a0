"""Near-duplicates: MinHash bands propose pairs, a sequential Bayesian test prunes them, full sets decide.

1. Each text becomes its set of distinct ``SHINGLE``-word shingles (64-bit hashes), a digest of that set and a
   signature of 16-bit minimum hashes. Texts with one digest are one class; only a class's smallest id goes on.
2. A class's signature is cut into bands; equal bands are a bucket. Buckets with one class are dropped.
3. Round one: inside each bucket (in salted blocks of at most ``BLOCK`` rows) signatures are compared batch by
   batch; a pair is dropped as soon as the posterior probability that its similarity reaches the threshold falls
   below ``MISS``. Each row keeps only its most similar earlier row, so the output is at most the input.
   These pairs are verified on full sets, and linked classes get component labels.
4. Round two is the exact rest: in every bucket that still holds more than one component, each row outside the
   bucket's largest component meets all rows of other components, block by block: first on signatures alone, then
   the rows that the test lets through come with their texts and are verified on full sets, and only the links found
   go out. Pairs inside a component need no test: they cannot change the result.

Nothing is capped: a bucket of any size is compared to the end, over as many blocks as it takes, and pairs that are
not worth testing are skipped only because both ends already are in one component or by the Bayesian bound.
A pair is lost only if no band meets (1e-5 at the threshold with the defaults) or by the bound (``MISS`` a batch).
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow, drop_stage, lower_ascii, mix64, ngram_hashes, stage, WordHashes
from .components import components

SHINGLE = 5
#: Bands and rows of a band; the signature has BANDS * ROWS values.
BANDS, ROWS = 24, 6
#: Rows of a bucket that are compared with each other in one block.
BLOCK = 512
#: Posterior probability of reaching the threshold below which a pair is dropped.
MISS = 1e-6
#: Ids up to this many (8 bytes each) are broadcast to fetch their texts; more are joined by a shuffle.
BROADCAST_IDS = 1_000_000

_MEMO = WordHashes()


def shingles(text: str | None, n: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the word shingles of a text (A-Z lower-cased); empty without words."""
    return np.unique(ngram_hashes(_MEMO.array(lower_ascii(text).split()), n)) if text else np.zeros(0, dtype=np.uint64)


@lru_cache(maxsize=4)
def _multipliers(k: int) -> np.ndarray:
    """Odd 32-bit multipliers, and addends, of the hash functions: from a counter, alike on all executors."""
    x = mix64(np.arange(1, 2 * k + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    return ((x >> np.uint64(32)).astype(np.uint32)).reshape(2, k, 1) | np.array([1, 0], dtype=np.uint32).reshape(2, 1, 1)


def signatures(items: np.ndarray, begins: np.ndarray, ends: np.ndarray, k: int) -> np.ndarray:
    """``signature`` of many short sets at once: a row ``items[begin:end]``; no set is empty."""
    mul, add = (m.reshape(1, k) for m in _multipliers(k))
    low = np.full((len(begins), k), 0xFFFFFFFF, dtype=np.uint32)
    x = ((items >> np.uint64(32)) ^ items).astype(np.uint32)
    i, step = 0, max(1, (1 << 18) // k)
    while i < len(begins):
        # As many whole sets as fit a step, or one long set in steps.
        j = max(i + 1, int(np.searchsorted(np.cumsum(ends[i : i + step] - begins[i : i + step]), step, "right")) + i)
        own = np.concatenate([x[b:e] for b, e in zip(begins[i:j].tolist(), ends[i:j].tolist(), strict=True)])
        at = np.cumsum(ends[i:j] - begins[i:j])[:-1]
        for s in range(0, len(own), step):
            h = own[s : s + step, None] * mul
            h += add
            h ^= h >> np.uint32(15)
            h *= np.uint32(0x2C1B3C6D)
            if j == i + 1:
                np.minimum(low[i], h.min(axis=0), out=low[i])
            else:
                low[i:j] = np.minimum.reduceat(h, np.r_[0, at], axis=0)
        i = j
    return (low ^ (low >> np.uint32(16))).astype(np.uint16)


def signature(items: np.ndarray, k: int) -> np.ndarray:
    """``k`` 16-bit minimum hashes of a set of 64-bit hashes."""
    mul, add = _multipliers(k)
    low = np.full(k, 0xFFFFFFFF, dtype=np.uint32)
    x = ((items >> np.uint64(32)) ^ items).astype(np.uint32)
    for s in range(0, len(x), 4096):
        h = mul * x[None, s : s + 4096]
        h += add
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x2C1B3C6D)
        np.minimum(low, h.min(axis=1), out=low)
    return (low ^ (low >> np.uint32(16))).astype(np.uint16)


@lru_cache(maxsize=16)
def least_matches(n: int, threshold: float, miss: float = MISS) -> int:
    """The fewest of ``n`` equal signature values with which a pair goes on.

    Under a uniform prior of the similarity, ``m`` matches of ``n`` give a Beta(m + 1, n - m + 1) posterior; the
    pair goes on if that puts at least ``miss`` on similarities from the threshold up.
    """
    x = (np.arange(20_000) + 0.5) / 20_000
    for m in range(n + 1):
        log = m * np.log(x) + (n - m) * np.log1p(-x) + math.lgamma(n + 2) - math.lgamma(m + 1) - math.lgamma(n - m + 1)
        p = np.exp(log)
        if p[x >= threshold].sum() / p.sum() >= miss:
            return m
    return n


def similar(a: np.ndarray, b: np.ndarray, threshold: float, batch: int = 36) -> tuple[np.ndarray, np.ndarray]:
    """Rows of two signature matrices that pass the sequential test, and their matches."""
    keep, matches = np.arange(len(a)), np.zeros(len(a), dtype=np.int32)
    k = a.shape[1]
    for s in range(0, k, batch):
        e = min(k, s + batch)
        matches = matches + (a[keep, s:e] == b[keep, s:e]).sum(axis=1, dtype=np.int32)
        ok = matches >= least_matches(e, threshold)
        keep, matches = keep[ok], matches[ok]
        if not len(keep):
            break
    return keep, matches


def sketches(items: DataFrame, threshold_set: int = SHINGLE, k: int = BANDS * ROWS) -> DataFrame:
    """id, n_shingles, digest, sig of (id bigint, text string) rows. No shingles: null digest and signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, digest, sig = [], [], []
            for t in b.column(1):
                s = shingles(t.as_py(), threshold_set)
                n.append(len(s))
                digest.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                sig.append(signature(s, k).tobytes() if len(s) else None)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(sig, pa.binary())], names=["id", "n_shingles", "digest", "sig"])

    return arrow(items.select("id", "text"), run, "id bigint, n_shingles bigint, digest binary, sig binary")


def buckets(sigs: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """id, bucket, m, band: a row for each band whose bucket holds m > 1 ids."""
    width = 2 * rows
    keys = F.array(*[F.xxhash64(F.lit(i), F.substring("sig", i * width + 1, width)) for i in range(bands)])
    each = sigs.select("id", F.posexplode(keys).alias("band", "bucket"))
    # A table, so that the join deals both sides itself and a very full bucket can be split.
    full = stage(each.groupBy("bucket").agg(F.count("*").alias("m")).where("m > 1"), "full")
    return each.join(full, "bucket").select("id", "bucket", "m", "band")


def _matrix(col: pa.Array) -> np.ndarray:
    raw = b"".join(x.as_py() for x in col)
    return np.frombuffer(raw, dtype=np.uint16).reshape(len(col), -1) if len(col) else np.zeros((0, 1), dtype=np.uint16)


def _whole_groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Tables that hold whole groups: rows come sorted by their first ``keys`` columns, groups may span batches."""
    held = None
    for b in batches:
        if not b.num_rows:
            continue
        t = pa.Table.from_batches([b])
        t = t if held is None else pa.concat_tables([held, t])
        cols = [t.column(i).to_numpy() for i in range(keys)]
        at = len(cols[0]) - 1
        same = np.ones(len(cols[0]), dtype=bool)
        for c in cols:
            same &= c == c[at]
        cut = int(np.flatnonzero(~same)[-1]) + 1 if not same.all() else 0
        if cut:
            yield t.slice(0, cut).combine_chunks()
        held = t.slice(cut)
    if held is not None and held.num_rows:
        yield held.combine_chunks()


def _best_pairs(threshold: float):
    """Round one: for each row, its most similar earlier row of the block, if any passes the test."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_groups(batches, 2):
            key, block, ids, sig = t.column(0).to_numpy(), t.column(1).to_numpy(), t.column(2).to_numpy(), _matrix(t.column(3))
            n = len(ids)
            best, most = np.full(n, -1, dtype=np.int64), np.zeros(n, dtype=np.int32)
            lag, i = 1, np.arange(n - 1)
            while True:
                i = i[: max(0, np.searchsorted(i, n - lag))]
                i = i[(key[i] == key[i + lag]) & (block[i] == block[i + lag])]
                if not len(i):
                    break
                for s in range(0, len(i), 65_536):
                    part = i[s : s + 65_536]
                    keep, m = similar(sig[part + lag], sig[part], threshold)
                    at = part[keep] + lag
                    better = m > most[at]
                    most[at[better]], best[at[better]] = m[better], (at - lag)[better]
                lag += 1
            at = np.flatnonzero(best >= 0)
            x, y = ids[at], ids[best[at]]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["a", "b"])

    return run


def _candidates(t: pa.Table, threshold: float, bands: int, label: np.ndarray) -> Iterator[tuple[int, int, int, np.ndarray]]:
    """start and end of a block, a probe of it, and the block's rows of other components that it has to be compared
    with, most similar first. A pair that shares several bands comes in the first of them only. ``label``: the
    components; the caller may join some on the way."""
    key, block, band, out = t.column(0).to_numpy(), t.column(1).to_numpy(), t.column(2).to_numpy(), t.column(5).to_numpy()
    sig = _matrix(t.column(6))
    new = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]) | (block[1:] != block[:-1]), True])
    for s, e in zip(new[:-1].tolist(), new[1:].tolist(), strict=True):
        own = label[s:e]
        probe, rest = np.flatnonzero(out[s:e]) + s, np.flatnonzero(~out[s:e]) + s
        for p in probe.tolist():
            q = rest[own[rest - s] != own[p - s]]
            if not len(q):
                continue
            keep, matches = similar(np.broadcast_to(sig[p], (len(q), sig.shape[1])), sig[q], threshold)
            q = q[keep]
            if not len(q):
                continue
            first = (sig[q].reshape(len(q), bands, -1) == sig[p].reshape(1, bands, -1)).all(axis=2).argmax(axis=1) == band[p]
            if first.any():
                yield s, e, p, q[first][np.argsort(-matches[first], kind="stable")]


def _survivors(threshold: float, bands: int):
    """Round two, on signatures: the rows of each block that stand in a pair which the test lets through."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_groups(batches, 2):
            hit = np.zeros(t.num_rows, dtype=bool)
            for _, _, p, q in _candidates(t, threshold, bands, t.column(4).to_numpy()):
                hit[p] = True
                hit[q] = True
            yield from t.select([0, 1, 2, 3, 4, 5]).filter(pa.array(hit)).to_batches()

    return run


def _cross_links(threshold: float, numerator: int, denominator: int, n: int, bands: int, accept):
    """Round two, on full sets: links between components, verified inside the block.

    A row outside the bucket's largest component meets the block's rows of other components, most similar first,
    and skips those that a link found on the way has joined to it. The output is a forest: fewer links than rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_groups(batches, 2):
            ids, label, texts = t.column(3).to_numpy(), t.column(4).to_numpy().copy(), t.column(7)
            links, held, at = [], {}, -1
            for s, e, p, found in _candidates(t, threshold, bands, label):
                own = label[s:e]
                if s != at:
                    held, at = {}, s
                for r in found.tolist():
                    if own[r - s] == own[p - s]:
                        continue
                    for x in (p, r):
                        if ids[x] not in held:
                            held[ids[x]] = shingles(texts[x].as_py(), n)
                    if linked(held[ids[p]], held[ids[r]], numerator, denominator) or accept and accept(texts[p].as_py(), texts[r].as_py()):
                        links.append((ids[p], ids[r]))
                        own[own == own[r - s]] = own[p - s]
            x, y = np.array(links, dtype=np.int64).reshape(-1, 2).T
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["a", "b"])

    return run


def linked(p: np.ndarray, q: np.ndarray, numerator: int, denominator: int) -> bool:
    """Whether the Jaccard similarity of two sorted sets is numerator / denominator or more."""
    if denominator * min(len(p), len(q)) < numerator * max(len(p), len(q)):
        return False
    both = len(np.intersect1d(p, q, assume_unique=True))
    return denominator * both >= numerator * (len(p) + len(q) - both)


def texts_of(ids: DataFrame, items: DataFrame, copies: bool, most: int) -> DataFrame:
    """id, text of the given ids (``most`` at most), as a table in the shared folder. ``copies``: ``items`` may repeat an id, with equal texts."""
    ids = ids.distinct()
    texts = items.select("id", "text").join(F.broadcast(ids) if most <= BROADCAST_IDS else ids, "id", "left_semi")
    return stage(texts.groupBy("id").agg(F.min("text").alias("text")) if copies else texts, "texts")


def verify(pairs: DataFrame, items: DataFrame, numerator: int, denominator: int, n: int = SHINGLE, accept=None, copies: bool = False) -> DataFrame:
    """a, b of the pairs that are linked on their full shingle sets, as a table in the shared folder."""
    texts = texts_of(pairs.select(F.explode(F.array("a", "b")).alias("id")), items, copies, 2 * pairs.count())
    left = texts.select(F.col("id").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("id").alias("b"), F.col("text").alias("tb"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keep, held = [], {}
            for x, tx, ty in zip(b.column(0).to_pylist(), b.column(2), b.column(3), strict=True):
                if x not in held:
                    if len(held) > 256:
                        held.clear()
                    held[x] = shingles(tx.as_py(), n)
                keep.append(linked(held[x], shingles(ty.as_py(), n), numerator, denominator) or bool(accept and accept(tx.as_py(), ty.as_py())))
            yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    wide = pairs.join(right, "b").join(left, "a").select("a", "b", "ta", "tb")
    out = stage(arrow(wide, run, "a bigint, b bigint"), "links")
    drop_stage(texts)
    return out


def near_components(reps: DataFrame, items: DataFrame, numerator: int, denominator: int, n: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, block: int = BLOCK, accept=None, copies: bool = False) -> DataFrame:
    """node, component of the links among ``reps`` (id, sig); ``items`` (id, text) holds their texts, copies allowed."""
    threshold = numerator / denominator
    b = stage(buckets(reps, bands, rows), "buckets")
    # Round one.
    blocks = F.ceil(F.col("m") / F.lit(block))
    inside = F.when(F.col("m") <= block, F.lit(0).cast("bigint")).otherwise(F.pmod(F.xxhash64("bucket", "id"), blocks))
    one = b.select("bucket", inside.alias("block"), "id").join(reps, "id").select("bucket", "block", "id", "sig")
    one = one.repartition("bucket", "block").sortWithinPartitions("bucket", "block", "id")
    pairs1 = stage(arrow(one, _best_pairs(threshold), "a bigint, b bigint").distinct(), "pairs", b.count())
    links = verify(pairs1, items, numerator, denominator, n, accept, copies)
    drop_stage(pairs1)
    comp = components(links)
    # Round two.
    lab = b.join(comp.withColumnRenamed("node", "id"), "id", "left").select("bucket", "band", "id", "m", F.coalesce("component", "id").alias("comp"))
    open_ = lab.groupBy("bucket").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1")).where("c0 < c1").select("bucket")
    lab = stage(lab.join(open_, "bucket", "left_semi"), "open", b.count())
    drop_stage(b)
    if not lab.limit(1).count():
        return comp
    biggest = lab.groupBy("bucket", "comp").agg(F.count("*").alias("c")).groupBy("bucket").agg(F.max(F.struct("c", "comp")).alias("top"))
    marked = lab.join(stage(biggest.select("bucket", F.col("top.comp").alias("top"), F.col("top.c").alias("c")), "biggest"), "bucket")
    # Blocks of probes by blocks of rows, so that no block holds more than about twice ``block`` rows.
    slots = F.greatest(F.ceil((F.col("m") - F.col("c")) / F.lit(block)), F.lit(1).cast("bigint"))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("bigint"), n - 1))
    own = F.pmod(F.xxhash64("bucket", "id", F.lit(1)), slots)
    rest = marked.select("bucket", "band", inside.alias("own"), every(slots).alias("other"), "id", "comp", F.lit(False).alias("out"), F.greatest(blocks, F.lit(1)).alias("width"))
    rest = rest.select("bucket", (F.col("other") * F.col("width") + F.col("own")).alias("block"), "band", "id", "comp", "out")
    probe = marked.where("comp <> top").select("bucket", "band", own.alias("own"), every(F.greatest(blocks, F.lit(1))).alias("other"), "id", "comp", F.lit(True).alias("out"), F.greatest(blocks, F.lit(1)).alias("width"))
    probe = probe.select("bucket", (F.col("own") * F.col("width") + F.col("other")).alias("block"), "band", "id", "comp", "out")
    two = rest.unionByName(probe).join(reps, "id").select("bucket", "block", "band", "id", "comp", "out", "sig")
    two = two.repartition("bucket", "block").sortWithinPartitions("bucket", "block", "id")
    # Texts go only with rows that signatures alone can't settle.
    left = stage(arrow(two, _survivors(threshold, bands), "bucket bigint, block bigint, band int, id bigint, comp bigint, out boolean"), "left")
    texts = texts_of(left.select("id"), items, copies, left.count())
    three = left.join(reps.join(texts, "id"), "id").select("bucket", "block", "band", "id", "comp", "out", "sig", "text")
    three = three.repartition("bucket", "block").sortWithinPartitions("bucket", "block", "id")
    more = stage(arrow(three, _cross_links(threshold, numerator, denominator, n, bands, accept), "a bigint, b bigint"), "links")
    drop_stage(texts)
    drop_stage(left)
    drop_stage(lab)
    if more.limit(1).count():
        first = comp
        comp = components(links.unionByName(more))
        drop_stage(first)
    return comp


def classes(items: DataFrame, numerator: int = 85, denominator: int = 100, n: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, block: int = BLOCK, accept=None) -> DataFrame:
    """id, n_shingles, component for (id bigint, text string) rows.

    Texts are linked at a Jaccard similarity of numerator / denominator or more of their shingle sets (or where
    ``accept(text, text)`` says so for a pair that the bands and the bound propose); ``component`` is the
    smallest id that links reach. Texts without words are linked with nothing; a null id is its own class, without a
    number; each of repeated rows gets its class, and one of them stands for it; texts are read whole, whatever their
    length; no rows give no rows; columns other than the two are ignored.
    """
    sk = stage(sketches(items, n, bands * rows), "sketches")
    # The member of each class with the smallest id stands for it.
    least = sk.where("digest is not null and id is not null").groupBy("digest").agg(F.min(F.struct("id", "sig")).alias("r"))
    cls = stage(least.select("digest", F.col("r.id").alias("rep"), F.col("r.sig").alias("sig")), "classes")
    comp = near_components(cls.select(F.col("rep").alias("id"), "sig"), items, numerator, denominator, n, bands, rows, block, accept)
    # A table, so that the join deals both sides itself and a class with very many members can be split.
    found = stage(cls.select("digest", "rep").join(comp.withColumnRenamed("node", "rep"), "rep", "left").select("digest", F.coalesce("component", "rep").alias("component")), "found")
    drop_stage(cls)
    worded = sk.where("digest is not null").select("id", "n_shingles", "digest").join(found, "digest", "left").select("id", "n_shingles", F.when(F.col("id").isNotNull(), F.coalesce("component", "id")).alias("component"))
    return worded.unionByName(sk.where("digest is null").select("id", "n_shingles", F.col("id").alias("component")))
