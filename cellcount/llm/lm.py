"""Language-model scoring: stupid-backoff scores of bigrams, computed relationally.

Counts come from all documents, and every word has its own. The score of a word after another is c(v, w) / c(v) where
the bigram comes ``min_count`` times or more in *other* documents (``apart``: a document's own occurrences don't vouch
for it; c(v, w) is the number of the others'), else ALPHA * c(w) / N; the first word of a text scores c(w) / N. A document's score is the sum
of the logarithms. So a text that the corpus repeats elsewhere scores apart from one that it does not.
``apart=False`` counts a document's own occurrences too. ``vocab`` is an option that makes all but so many words one
unknown word; without it nothing is merged.

Each document's distinct bigrams are exploded to rows and dealt by a hash of the bigram, once: a hash partition of the
count table and the exploded rows that it joins are the same partition, so the count is a sum over it. Scores are summed per document. The ``LISTED``
most frequent words have their rank as id and their counts are broadcast; any other word has a hash as its key, and
bigrams with such a word are a relation of their own, which joins the table of words once it is known whose count they need. Bigrams of two of
``HOT`` very frequent words, found in a sample, would make hot groups; they are at most HOT^2, so each task counts them
in an array together with the words, the sums are broadcast, and they never enter a shuffle.

Defined results: null and empty texts have no words and a log score of 0; texts are read whole; n-grams don't
cross rows; rows with a repeated doc_id are scored as one document, each row's own occurrences left out by itself; words that tie at the edge of a given ``vocab``
are all left out; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow, mix64, stage, words_in

HOT, ALPHA, MIN_COUNT = 512, 0.4, 1
#: Bits of the id of a listed word. The listed words' ids and counts are broadcast, 20 bytes each; the others' counts are a relation.
BITS = 20
LISTED = (1 << BITS) - 1
#: Keys of words that are not listed start at RARE.
RARE = 1 << 62
#: Rows of a batch that goes back to Spark, about.
CHUNK_ROWS = 1 << 16
#: Documents, about, in which the hot words are looked for; any choice of hot words gives equal scores.
HOT_SAMPLE = 10_000


def frequent_words(docs: DataFrame, hot: int, sample_rows: int = HOT_SAMPLE, text_col: str = "text") -> list[int]:
    """Hashes of the ``hot`` most frequent words of about ``sample_rows`` documents; fewer rows are read whole."""
    every = max(1, docs.count() // sample_rows)
    some = docs.where(F.pmod(F.xxhash64(text_col), F.lit(every)) == 0).select(F.col(text_col).cast("string"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, n = _tally([w.hash.view(np.int64) for w in words_in(b.column(0))])
            top = np.argsort(-n, kind="stable")[: 4 * hot]
            yield pa.RecordBatch.from_arrays([pa.array(ids[top]), pa.array(n[top])], names=["word", "n"])

    rows = arrow(some, run, "word bigint, n bigint").groupBy("word").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "word").limit(hot).collect()
    return [r["word"] for r in rows]


def _tally(parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    ids, n = np.unique(np.concatenate(parts) if parts else np.zeros(0, np.int64), return_counts=True)
    return ids, n.astype(np.int64)


def counts(docs: DataFrame, hot_words: list[int], text_col: str = "text") -> DataFrame:
    """pair, key, n: counts over all documents of each word (``pair`` false, key: its hash) and of the bigrams of two
    of ``hot_words`` (``pair`` true, key: their places in the list)."""
    held = docs.sparkSession.sparkContext.broadcast(hot_words)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = len(held.value)
        place = _Lookup(np.array(held.value, dtype=np.int64), np.arange(m))
        total = np.zeros(m * m, dtype=np.int64)
        for b in batches:
            parts = []
            for x in words_in(b.column(0)):
                parts.append(x.hash.view(np.int64))
                p = place(parts[-1], np.full(len(x.hash), -1, dtype=np.int64))
                both = (p[:-1] >= 0) & (p[1:] >= 0)
                edge = x.at[(x.at > 0) & (x.at < len(p))] - 1  # the last word of a text and the next text's first
                both[edge] = False
                pair, k = _tally([p[:-1][both] * m + p[1:][both]])
                total[pair] += k
            ids, n = _tally(parts)
            yield pa.RecordBatch.from_arrays([pa.array(np.zeros(len(ids), dtype=bool)), pa.array(ids), pa.array(n)], names=["pair", "key", "n"])
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.ones(len(at), dtype=bool)), pa.array(at), pa.array(total[at])], names=["pair", "key", "n"])

    each = arrow(docs.select(F.col(text_col).cast("string")), run, "pair boolean, key bigint, n bigint")
    return each.groupBy("pair", "key").agg(F.sum("n").alias("n"))


def vocabulary(words: DataFrame, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Words and counts of the words more frequent than the first count that would overfill ``size``, most frequent first.

    The edge comes from the number of words with each count (counts from 2^16 up by their power of two), so that no
    task sends more than it has to. Words that tie at the edge stay out together.
    """
    level = F.when(F.col("n") < 1 << 16, F.col("n")).otherwise((F.lit(1 << 16) + F.floor(F.log2("n"))).cast("long"))
    edge, held = 0, 0
    for r in sorted(words.groupBy(level.alias("l")).agg(F.count("*").alias("words"), F.max("n").alias("n")).collect(), key=lambda r: -r["l"]):
        held += r["words"]
        if held > size:
            edge = r["n"]
            break
    top = words.where(F.col("n") > edge).select("key", "n").toArrow()
    key, n = (np.concatenate([np.zeros(0, np.int64), *[x.to_numpy(zero_copy_only=False) for x in top.column(c).chunks]]).astype(np.int64) for c in ("key", "n"))
    order = np.lexsort((key, -n))
    return key[order], n[order]


def _ids(h: np.ndarray, known: np.ndarray, rank: np.ndarray, merge: bool) -> np.ndarray:
    """The ids of listed words by their hashes; of other words a key, or 0 with ``merge``. ``known`` is sorted."""
    other = np.zeros(len(h), dtype=np.int64) if merge else h & (RARE - 1) | RARE
    if not len(known):
        return other
    at = np.minimum(np.searchsorted(known, h), len(known) - 1)
    return np.where(known[at] == h, rank[at], other)


class _Lookup:
    """Values by 64-bit hashes: sorted hashes, found from where those with equal leading bits begin."""

    def __init__(self, known: np.ndarray, values: np.ndarray):
        u = known.view(np.uint64)
        order = np.argsort(u)
        bits = max(1, int(len(u)).bit_length() + 1)
        self.shift, self.known, self.values = np.uint64(64 - bits), u[order], values[order]
        self.first = np.zeros((1 << bits) + 1, dtype=np.int32)
        np.cumsum(np.bincount((self.known >> self.shift).astype(np.int64), minlength=1 << bits), out=self.first[1:])

    def __call__(self, h: np.ndarray, out: np.ndarray) -> np.ndarray:
        """``out``, with the values of the known ones among the hashes ``h``."""
        u = h.view(np.uint64)
        lead = (u >> self.shift).astype(np.int64)
        at, end = self.first[lead], self.first[lead + 1]
        todo = np.flatnonzero(at < end)
        at, end, u = at[todo], end[todo], u[todo]
        while len(todo):
            hit = self.known[at] == u
            out[todo[hit]] = self.values[at[hit]]
            at += 1
            on = ~hit & (at < end)
            todo, at, end, u = todo[on], at[on], end[on], u[on]
        return out


def _codes(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    """A number for each bigram with a word that is not listed: a hash of the keys."""
    mixed = mix64(mix64(v.astype(np.uint64)) * np.uint64(3) + w.astype(np.uint64))
    return (mixed & np.uint64(RARE // 2 - 1)).astype(np.int64)


def score(docs: DataFrame, vocab: int | None = None, hot: int = HOT, alpha: float = ALPHA, min_count: int = MIN_COUNT, apart: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, log_score, log_per_word for each document."""
    if vocab is not None and vocab >= 1 << BITS:
        raise ValueError(f"ids of words take {BITS} bits")
    spark, merge, least = docs.sparkSession, vocab is not None, max(1, min_count)
    hot_words = frequent_words(docs, hot, text_col=text_col)
    table = stage(counts(docs, hot_words, text_col), "counts")
    words, pairs = table.where("not pair").select("key", "n"), table.where("pair").select("key", "n").collect()
    # The listed words and the number of words: LISTED rows and one, whatever the corpus.
    total = words.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first()["n"]
    top, top_n = vocabulary(words, vocab if merge else LISTED)
    order = np.argsort(top)
    known = spark.sparkContext.broadcast((top[order], (order + 1).astype(np.int32)))
    unigram = np.r_[0, top_n]
    if merge:
        unigram[0] = total - unigram.sum()
    log_n, log_u = math.log(max(total, 1)), np.log(np.maximum(unigram, 1))
    # Of the hot words those that are listed: place in the list by id, and how often their bigrams come.
    m = len(hot_words)
    own = _ids(np.array(hot_words, dtype=np.int64), *known.value, True)
    place = np.full(len(log_u), -1, dtype=np.int32)
    place[own[own > 0]] = np.flatnonzero(own > 0)
    c = np.zeros(m * m, dtype=np.int64)
    for r in pairs:
        c[r["key"]] = r["n"]
    held = spark.sparkContext.broadcast((log_u, c, place, own))
    src = docs.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string"))

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray]]:
        """doc_id and the ids of its words."""
        listed = _Lookup(*known.value)
        for b in batches:
            docs = b.column(0).to_pylist()
            for x in words_in(b.column(1)):
                h = x.hash.view(np.int64)
                a = listed(h, np.zeros(len(h), dtype=np.int64) if merge else h & (RARE - 1) | RARE)
                for d, i, j in zip(docs[x.row :], x.at[:-1].tolist(), x.at[1:].tolist(), strict=False):
                    yield d, a[i:j]

    def flush(names: list[str], ids: list, sizes: list[int], cols: list[list[np.ndarray]]) -> pa.RecordBatch:
        who = pa.array(ids, pa.int64()).take(pa.array(np.repeat(np.arange(len(ids)), sizes)))
        return pa.RecordBatch.from_arrays([who, *[pa.array(np.concatenate(x)) for x in cols]], names=names)

    def pieces(names: list[str], rows: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        """Record batches of about CHUNK_ROWS rows from (doc_id, column arrays)."""
        ids, sizes, cols, n = [], [], [[] for _ in names[1:]], 0
        for d, *arrays in rows:
            ids.append(d)
            sizes.append(len(arrays[0]))
            n += sizes[-1]
            for x, y in zip(cols, arrays, strict=True):
                x.append(y)
            if n >= CHUNK_ROWS:
                yield flush(names, ids, sizes, cols)
                ids, sizes, cols, n = [], [], [[] for _ in names[1:]], 0
        if ids:
            yield flush(names, ids, sizes, cols)

    def listed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """doc_id, code, n, s: bigrams of two listed words; and a row for each text, with a negative code that spreads
        these rows, its number of words, and what needs no table: the first word and hot bigrams."""
        log_u, c, place, own = held.value
        m = len(own)

        def rows():
            for d, a in walk(batches):
                here = a < RARE
                p = place[np.where(here, a, 0)]
                both = (p[:-1] >= 0) & (p[1:] >= 0)
                cold = here[:-1] & here[1:] & ~both
                code, n = np.unique(a[:-1][cold] << BITS | a[1:][cold], return_counts=True)
                pair, k = np.unique(p[:-1][both].astype(np.int64) * m + p[1:][both], return_counts=True)
                left = c[pair] - (k if apart else 0)
                seen = np.log(np.maximum(left, 1)) - log_u[own[pair // max(m, 1)]]
                s = (k * np.where(left >= least, seen, math.log(alpha) + log_u[own[pair % max(m, 1)]] - log_n)).sum()
                s += log_u[a[0]] - log_n if len(a) and a[0] < RARE else 0.0
                none = np.full(len(code), np.nan)
                yield d, np.r_[-1 - (xxhash.xxh32_intdigest(str(d)) & 0x3FFFFFFF), code].astype(np.int64), np.r_[len(a), n].astype(np.int32), np.r_[s, none]

        yield from pieces(["doc_id", "code", "n", "s"], rows())

    def rare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """doc_id, code, n, v, w: bigrams with a word that is not listed; a first word of this kind has a negative code."""

        def rows():
            for d, a in walk(batches):
                far = a >= RARE
                at = np.flatnonzero(far[:-1] | far[1:])
                code, i, n = np.unique(_codes(a[at], a[at + 1]), return_index=True, return_counts=True)
                i, first = at[i], a[:1][far[:1]]
                yield d, np.r_[code, -first], np.r_[n, np.ones(len(first), dtype=np.int64)].astype(np.int32), np.r_[a[i], first], np.r_[a[i + 1], first]

        yield from pieces(["doc_id", "code", "n", "v", "w"], rows())

    def counted(rows: DataFrame) -> DataFrame:
        """The exploded bigrams with ``left``, how often each comes elsewhere. The count table of a hash partition is summed
        where its rows are, so they are dealt once; a join of the two would deal them twice."""
        return rows.withColumn("left", F.sum("n").over(Window.partitionBy("code")) - (F.col("n") if apart else 0))

    logs = F.broadcast(spark.createDataFrame(pa.table({"word": np.arange(len(log_u)), "log_word": log_u})))
    seen, back = F.col("left") >= least, F.lit(math.log(alpha) - log_n)
    value = F.col("n") * F.when(seen, F.log("left") - F.col("log_word")).otherwise(back + F.col("log_word"))
    x = counted(arrow(src, listed, "doc_id bigint, code bigint, n int, s double"))
    text = F.col("code") < 0
    x = x.withColumn("word", F.when(text, F.lit(0).cast("bigint")).when(seen, F.shiftright("code", BITS)).otherwise(F.col("code").bitwiseAND(F.lit((1 << BITS) - 1).cast("bigint"))))
    out = x.join(logs, "word").select("doc_id", F.when(text, F.col("n")).otherwise(0).cast("bigint").alias("n_words"), F.when(text, F.col("s")).otherwise(value).alias("s"))
    if not merge:
        y = counted(arrow(src, rare, "doc_id bigint, code bigint, n int, v bigint, w bigint"))
        y = y.withColumn("word", F.when(seen & ~text, F.col("v")).otherwise(F.col("w")))
        others = words.select(F.col("key").bitwiseAND(F.lit(RARE - 1)).bitwiseOR(F.lit(RARE)).alias("word"), F.log("n").alias("log_word"))
        value = F.when(text, F.col("log_word") - log_n).otherwise(value)
        for z in (y.where(F.col("word") < RARE).join(logs, "word"), y.where(F.col("word") >= RARE).join(others, "word")):
            out = out.unionByName(z.select("doc_id", F.lit(0).cast("bigint").alias("n_words"), value.alias("s")))
    out = out.groupBy("doc_id").agg(F.sum("n_words").alias("n_words"), F.sum("s").alias("log_score"))
    return out.select("doc_id", "n_words", "log_score", F.when(F.col("n_words") > 0, F.col("log_score") / F.col("n_words")).otherwise(0.0).alias("log_per_word"))
