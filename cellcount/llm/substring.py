"""Substring deduplication: paragraphs and passages that repeat across documents, exactly or nearly.

Two units, each with a way of its own to find partners; both keep what the document with the smallest id has.

*Paragraphs* are lines with words. Paragraphs with equal words (A-Z lower-cased, white space aside) are one class.
Distinct paragraphs of ``FUZZY_WORDS`` words or more also get MinHash bands, tuned for high recall at the threshold
(0.99997 at Jaccard 0.8); colliding paragraphs are verified by exact Jaccard similarity or by word edit distance, and
components of links form clusters. A cluster counts if it spans two documents; its first occurrence (smallest
document, then place) stays. The others are removed where they stand in a run of adjacent such paragraphs with at
least ``PASSAGE_WORDS`` words, so that a short common line by itself stays.

*Passages* know no lines. Every window of ``SEED_WORDS`` words is a unit; its band is the least hash of its shorter
windows of half that length, a MinHash with one band of one row, which equal windows always share. Bands that occur in one
document only are dropped first, so just the windows near shared text go on; there windows of several documents are
verified by a hash of all their words. Runs of words that such windows cover, with gaps of at most ``BRIDGE`` words, are
passages; those of ``PASSAGE_WORDS`` words or more count. So no repeated passage of that length is missed, wherever
lines begin and end, and neither is a copy whose changed words have ``SEED_WORDS`` equal words on both sides.

``near_passages`` extends runs that are too short by themselves, word by word, over changed words (see there).

Defined results: null and empty texts have no units; a text without line breaks is one paragraph of any length, and
texts are read whole; repeats inside one document alone don't count; equal rows (doc_id and text) count once and are
treated alike, rows with a repeated doc_id and other texts are one document whose texts are marked and cut each by
itself; a null doc_id is no document: such rows have no repeats and stay as they are; an empty table gives an empty
result; extra columns are kept by ``remove`` and ignored elsewhere.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Words, arrow, drop_stage, hashes_in, lower_ascii, mix64, ngram_hashes, stage, word_hashes, words_in
from .neardup import BROADCAST_IDS, SHINGLE, linked, near_components, signatures

#: Fewest words of a removed run, and of a paragraph that is compared nearly.
PASSAGE_WORDS, FUZZY_WORDS = 50, 32
BANDS, ROWS = 20, 4
#: Words of a window, and the longest gap between covered words inside a passage. Two passages of ``PASSAGE_WORDS``
#: words or more at a Jaccard similarity of 0.8 over five-word shingles differ so little that they share a window.
SEED_WORDS, BRIDGE = 24, 2
#: Words of a batch that are sketched at once.
CHUNK_WORDS = 1 << 17

_WORD = re.compile(r"[^\x20\x09-\x0D]+")


def edit_similarity(a: str, b: str) -> float:
    """1 - word edit distance / words of the longer text."""
    x, y = lower_ascii(a).split(), lower_ascii(b).split()
    if not x or not y:
        return float(x == y)
    ids: dict[bytes, int] = {}
    y_ids = np.array([ids.setdefault(w, len(ids)) for w in y])
    row = np.arange(len(y) + 1)
    steps = np.arange(len(y) + 1)
    for i, w in enumerate(x, 1):
        new = np.empty_like(row)
        new[0] = i
        new[1:] = np.minimum(row[1:] + 1, row[:-1] + (y_ids != ids.get(w, -1)))
        # An insertion costs one for each step to the right of the cheapest cell to the left.
        row = np.minimum.accumulate(new - steps) + steps
    return 1 - int(row[-1]) / max(len(x), len(y))


class Lines:
    """The lines with words of some texts: ``row`` of the text, ``begin`` and ``end`` in bytes of ``Words.data``, ``start`` and
    ``n_chars`` in code points of the text, ``first`` and ``last`` of its words, ``no`` among the text's lines with words."""

    def __init__(self, w: Words):
        points = np.zeros(len(w.data) + 1, dtype=np.int64)
        np.cumsum((w.data & 0xC0) != 0x80, out=points[1:])
        breaks = np.flatnonzero(w.data == 10)
        # A line ends at a line feed or with its text, and begins after a line feed or with its text.
        begin, end = np.r_[w.cuts[:-1], breaks + 1], np.r_[w.cuts[1:], breaks]
        begin.sort()
        end.sort()
        first, last = np.searchsorted(w.begin, begin), np.searchsorted(w.begin, end)
        some = last > first
        self.begin, self.end, self.first, self.last = begin[some], end[some], first[some], last[some]
        text = np.searchsorted(w.cuts, self.begin, "right") - 1
        self.row = w.row + text
        self.start, self.n_chars = points[self.begin] - points[w.cuts[text]], points[self.end] - points[self.begin]
        self.no = np.arange(len(text)) - np.searchsorted(text, text)
        self.n_words = self.last - self.first

    def ids(self, w: Words, some: np.ndarray) -> np.ndarray:
        """Signed 64-bit ids of the words of the chosen lines."""
        return np.fromiter((xxhash.xxh3_64_intdigest(w.hash[i:j]) for i, j in zip(self.first[some].tolist(), self.last[some].tolist(), strict=True)), dtype=np.uint64, count=len(some)).view(np.int64)


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, digest, text of the rows that are documents; ``digest`` tells texts of one doc_id apart."""
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.where("doc_id is not null and text is not null").select("doc_id", F.xxhash64("text").alias("digest"), "text")


def paragraphs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", fuzzy_words: int = FUZZY_WORDS, k: int = BANDS * ROWS) -> DataFrame:
    """doc_id, digest, para_no, start, n_chars, n_words, pid, sig: a row for each paragraph; sig only for long ones."""
    names = ["doc_id", "digest", "para_no", "start", "n_chars", "n_words", "pid", "sig"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for w in words_in(b.column(2)):
                x = Lines(w)
                sigs: list[bytes | None] = [None] * len(x.row)
                long = np.flatnonzero(x.n_words >= fuzzy_words)
                if len(long):
                    # One pass for all; the windows across two paragraphs belong to none.
                    items = ngram_hashes(np.r_[w.hash, np.zeros(SHINGLE, dtype=np.uint64)], SHINGLE)
                    for i, sig in zip(long.tolist(), signatures(items, x.first[long], x.last[long] - SHINGLE + 1, k), strict=True):
                        sigs[i] = sig.tobytes()
                own = pa.array(x.row)
                cols = [b.column(0).take(own), b.column(1).take(own), *map(pa.array, (x.no, x.start, x.n_chars, x.n_words, x.ids(w, np.arange(len(x.row))))), pa.array(sigs, pa.binary())]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    if fuzzy_words < SHINGLE:
        raise ValueError(f"paragraphs under {SHINGLE} words have no shingles to compare")
    return arrow(_keyed(docs, id_col, text_col), run, "doc_id bigint, digest bigint, para_no bigint, start bigint, n_chars bigint, n_words bigint, pid bigint, sig binary")


def _texts(docs: DataFrame, text_col: str, fuzzy_words: int) -> DataFrame:
    """id, text of the long paragraphs, copies included."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for w in words_in(b.column(0)):
                x = Lines(w)
                long = np.flatnonzero(x.n_words >= fuzzy_words)
                # The lines' bytes, lower-cased, which have the same words.
                texts = [w.data[i:j].tobytes().decode() for i, j in zip(x.begin[long].tolist(), x.end[long].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(x.ids(w, long)), pa.array(texts, pa.string())], names=["id", "text"])

    return arrow(docs.select(F.col(text_col).cast("string")), run, "id bigint, text string")


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", numerator: int = 80, denominator: int = 100, measure: str = "jaccard", passage_words: int = PASSAGE_WORDS, fuzzy_words: int = FUZZY_WORDS, near: bool = False) -> DataFrame:
    """unit, doc_id, digest, place, start, n_chars, n_words, first_doc_id, removed: repeated units by document.

    ``removed`` rows go; a row with ``removed`` false is the first occurrence that stays for them. ``place`` counts
    paragraphs or words of the text from 0; ``start`` and ``n_chars`` are code points, of paragraphs only.
    ``measure``: "jaccard", or "edit" to accept a proposed pair of paragraphs by its word edit similarity as well.
    ``near``: passages that are shorter than ``passage_words`` go on over changed words (see ``near_passages``).
    """
    lines = repeated_paragraphs(docs, id_col, text_col, numerator, denominator, measure, passage_words, fuzzy_words)
    places = shared_windows(docs, id_col, text_col)
    runs = repeated_passages(docs, places, id_col, text_col, passage_words)
    if near:
        runs = runs.unionByName(near_passages(docs, places, id_col, text_col, numerator, denominator, passage_words))
    none = F.lit(None).cast("bigint")
    return lines.drop("first_para_no").withColumnRenamed("para_no", "place").withColumn("unit", F.lit("paragraph")).unionByName(runs.withColumns({"unit": F.lit("passage"), "start": none, "n_chars": none}))


def repeated_paragraphs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", numerator: int = 80, denominator: int = 100, measure: str = "jaccard", passage_words: int = PASSAGE_WORDS, fuzzy_words: int = FUZZY_WORDS) -> DataFrame:
    """doc_id, digest, para_no, start, n_chars, n_words, first_doc_id, first_para_no, removed; see ``repeats``."""
    par = stage(paragraphs(docs, id_col, text_col, fuzzy_words), "paragraphs")
    reps = stage(par.where("sig is not null").groupBy(F.col("pid").alias("id")).agg(F.min("sig").alias("sig")), "reps")
    share = numerator / denominator
    accept = (lambda a, b: edit_similarity(a, b) >= share) if measure == "edit" else None
    comp = near_components(reps, _texts(docs, text_col, fuzzy_words), numerator, denominator, bands=BANDS, rows=ROWS, accept=accept, copies=True)
    drop_stage(reps)
    # Classes come first, so that the paragraphs themselves are dealt once, and only those that repeat go on.
    per = par.groupBy("pid").agg(F.min("doc_id").alias("d0"), F.max("doc_id").alias("d1"), F.min(F.struct("doc_id", "para_no", "digest")).alias("first"))
    per = per.join(comp.withColumnRenamed("node", "pid"), "pid", "left").where("d0 < d1 or component is not null")
    per = stage(per.withColumn("cluster", F.coalesce("component", "pid")).drop("component"), "classes")
    drop_stage(comp)
    groups = per.groupBy("cluster").agg(F.min("d0").alias("d0"), F.max("d1").alias("d1"), F.min("first").alias("first")).where("d0 < d1").select("cluster", "first")
    hit = stage(per.select("pid", "cluster").join(groups, "cluster"), "hit")
    drop_stage(per)
    own = ["doc_id", "digest", "para_no"]
    many = par.drop("sig").join(hit, "pid").groupBy(*own).agg(*[F.first(c).alias(c) for c in ("start", "n_chars", "n_words", "cluster", "first")])
    many = stage(many.withColumn("keeps", F.struct("doc_id", "para_no", "digest") == F.col("first")), "occurrences")
    drop_stage(par)
    drop_stage(hit)
    row = ["doc_id", "digest"]
    gone = many.where("not keeps").withColumn("run", F.col("para_no") - F.row_number().over(Window.partitionBy(*row).orderBy("para_no")))
    gone = gone.withColumn("run_words", F.sum("n_words").over(Window.partitionBy(*row, "run"))).where(F.col("run_words") >= passage_words)
    cols = [*own, "start", "n_chars", "n_words", F.col("first.doc_id").alias("first_doc_id"), F.col("first.para_no").alias("first_para_no")]
    gone = stage(gone.select("cluster", *cols), "gone")
    kept = many.where("keeps").join(gone.select("cluster").distinct(), "cluster", "left_semi").select(*cols, F.lit(False).alias("removed"))
    return gone.drop("cluster").withColumn("removed", F.lit(True)).unionByName(kept)


def _windows(a: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Anchor and hash of each window of ``words`` words, by the place of its first word; ``a``: the words' hashes."""
    if len(a) < words:
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)

    def widen(h: np.ndarray, width: int, to: int) -> np.ndarray:
        """Hashes of windows of ``to`` words from those of ``width`` words, which cover them twice at most."""
        return mix64(h[: len(a) - to + 1] * np.uint64(3) + h[to - width : len(a) - width + 1])

    half, width, h = words // 2, 1, a
    while width < half:
        to = min(2 * width, half)
        h, width = widen(h, width, to), to
    # An anchor is the least hash of the halves that lie in the window: equal windows have equal anchors.
    low, span, need = h, 1, words - half + 1
    while span < need:
        to = min(2 * span, need)
        low, span = np.minimum(low[: len(h) - to + 1], low[to - span : len(h) - span + 1]), to
    whole = h
    while width < words:
        to = min(2 * width, words)
        whole, width = widen(whole, width, to), to
    return low.view(np.int64), whole.view(np.int64)


def _grouped(texts: DataFrame) -> DataFrame:
    """digest, d0, d1: the least and the greatest id of the documents with one text, where there are several."""
    return texts.groupBy("digest").agg(F.min("doc_id").alias("d0"), F.max("doc_id").alias("d1")).where("d0 < d1")


def shared_windows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = SEED_WORDS) -> DataFrame:
    """doc_id, digest, at, first_doc_id: places of the windows that several documents have, as a table in the shared
    folder. ``first_doc_id``: the least of them. Of documents with one text only the one with the least id appears."""
    src = _keyed(docs, id_col, text_col)
    same = stage(_grouped(src.select("doc_id", "digest")), "same")
    few = same.count() <= BROADCAST_IDS
    src = src.join(F.broadcast(same) if few else same, "digest", "left").where("d0 is null or doc_id = d0").select("doc_id", "digest", F.coalesce("d1", "doc_id").alias("last"), "text")

    def anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [np.unique(_windows(a, words)[0]) for a in hashes_in(b.column(3))]
            lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum([len(g) for g in got])], pa.int32()), pa.array(np.concatenate(got) if got else np.zeros(0, np.int64)))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), lists], names=["doc_id", "digest", "last", "anchors"])

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            own, places, hashes, held = [], [], [], 0

            def pack() -> pa.RecordBatch:
                each = pa.array(np.repeat(np.array(own, dtype=np.int64), [len(p) for p in places]))
                rows = [b.column(i).take(each) for i in range(3)]
                return pa.RecordBatch.from_arrays([*rows, pa.array(np.concatenate(places).astype(np.int32)), pa.array(np.concatenate(hashes))], names=["doc_id", "digest", "last", "at", "hash"])

            for i, (doc, last, a, keys) in enumerate(zip(b.column(0).to_pylist(), b.column(2).to_pylist(), hashes_in(b.column(3)), b.column(4), strict=True)):
                low, whole = _windows(a, words)
                at = np.flatnonzero(np.isin(low, keys.values.to_numpy())) if doc == last else np.arange(len(whole))
                own.append(i)
                places.append(at)
                hashes.append(whole[at])
                held += len(at)
                if held > CHUNK_WORDS:
                    yield pack()
                    own, places, hashes, held = [], [], [], 0
            if own:
                yield pack()

    key = ["doc_id", "digest", "last"]
    held = stage(arrow(src, anchors, "doc_id bigint, digest bigint, last bigint, anchors array<bigint>"), "anchors")
    each = held.select("doc_id", "digest", F.explode("anchors").alias("anchor"))
    many = stage(each.groupBy("anchor").agg(F.min("doc_id").alias("d0"), F.max("doc_id").alias("d1")).where("d0 < d1").select("anchor"), "shared")
    near = each.join(many, "anchor").groupBy("doc_id", "digest").agg(F.collect_list("anchor").alias("anchors"))
    # A text that several documents have is of interest as a whole.
    whole = held.where("doc_id < last").select("doc_id", "digest", F.array().cast("array<bigint>").alias("anchors"))
    near = stage(near.unionByName(whole).groupBy("doc_id", "digest").agg(F.flatten(F.collect_list("anchors")).alias("anchors")), "near")
    ids = near.select("digest").distinct()
    found = src.join(F.broadcast(ids) if near.count() <= BROADCAST_IDS else ids, "digest", "left_semi").dropDuplicates(["doc_id", "digest"])
    each = stage(arrow(found.join(near, ["doc_id", "digest"]).select(*key, "text", "anchors"), windows, "doc_id bigint, digest bigint, last bigint, at int, hash bigint"), "windows")
    for t in (held, many, near):
        drop_stage(t)
    # Tables, so that the join deals both sides itself and a window that very many documents have can be split.
    first = stage(each.groupBy("hash").agg(F.min("doc_id").alias("first_doc_id"), F.max("last").alias("d1")).where("first_doc_id < d1").select("hash", "first_doc_id"), "first")
    out = stage(each.join(first, "hash").select("doc_id", "digest", "at", "first_doc_id"), "places")
    drop_stage(each)
    drop_stage(first)
    return out


def _runs(at: DataFrame, words: int, bridge: int) -> DataFrame:
    """doc_id, digest, place, n_words, first_doc_id, removed: runs of words that shared windows cover."""
    own = ["doc_id", "digest", "removed"]
    at = at.withColumn("removed", F.col("first_doc_id") < F.col("doc_id"))
    before = F.lag("at").over(Window.partitionBy(*own).orderBy("at"))
    runs = at.withColumn("new", F.when(F.col("at") - before <= words + bridge, 0).otherwise(1))
    runs = runs.withColumn("run", F.sum("new").over(Window.partitionBy(*own).orderBy("at")))
    runs = runs.groupBy(*own, "run").agg(F.min("at").cast("bigint").alias("place"), (F.max("at") - F.min("at") + words).cast("bigint").alias("n_words"), F.min("first_doc_id").alias("first_doc_id"))
    return runs.select("doc_id", "digest", "place", "n_words", "first_doc_id", "removed")


def repeated_passages(docs: DataFrame, places: DataFrame, id_col: str = "doc_id", text_col: str = "text", passage_words: int = PASSAGE_WORDS, words: int = SEED_WORDS, bridge: int = BRIDGE) -> DataFrame:
    """doc_id, digest, place, n_words, first_doc_id, removed: the runs among ``shared_windows`` that are long enough."""
    runs = _runs(places, words, bridge).where(F.col("n_words") >= passage_words)
    # Documents with the text of an earlier one repeat all of it.
    texts = _keyed(docs, id_col, text_col).select("doc_id", "digest")
    same = stage(_grouped(texts).join(places.groupBy("digest").agg((F.max("at") + words).cast("bigint").alias("n_words"), F.min("first_doc_id").alias("first_doc_id")), "digest"), "same")
    copies = texts.join(same.where(F.col("n_words") >= passage_words), "digest").where("doc_id > d0").select("doc_id", "digest", F.lit(0).cast("bigint").alias("place"), "n_words", "first_doc_id", F.lit(True).alias("removed"))
    return runs.unionByName(copies.distinct())


#: Words that must agree again after a change, and the most words that one change takes away on a side.
RESUME, STEP = 3, 2


def _stretches(a: np.ndarray, b: np.ndarray, i: int, j: int, changes: int) -> list[tuple[int, int]]:
    """How far two sequences agree from ``i`` and ``j``, after 0, 1, ... ``changes`` changes of up to STEP words."""
    steps = sorted(((x, y) for x in range(STEP + 1) for y in range(STEP + 1) if x or y), key=lambda s: (max(s), sum(s)))
    out = []
    while True:
        n = min(len(a) - i, len(b) - j)
        differ = np.flatnonzero(a[i : i + n] != b[j : j + n])
        n = int(differ[0]) if len(differ) else n
        i, j = i + n, j + n
        out.append((i, j))
        near = [s for s in steps if len(a) >= i + s[0] + RESUME and len(b) >= j + s[1] + RESUME and (a[i + s[0] :][:RESUME] == b[j + s[1] :][:RESUME]).all()]
        if len(out) > changes or not near:
            return out
        i, j = i + near[0][0], j + near[0][1]


def _extended(a: np.ndarray, b: np.ndarray, i: int, j: int, numerator: int, denominator: int, least: int, words: int) -> tuple[int, int] | None:
    """The longest span of ``a`` around an equal window that nearly equals the span of ``b`` around it, if any is long enough."""
    rate = 5 * (denominator + numerator) // (denominator - numerator)  # words for each change at the threshold
    changes = 1 + max(len(a), len(b)) // rate
    ends = _stretches(a, b, i, j, min(changes, 8))
    begins = [(len(a) - x, len(b) - y) for x, y in _stretches(a[::-1], b[::-1], len(a) - i - words, len(b) - j - words, min(changes, 8))]
    spans = sorted(((p, q) for p in begins for q in ends if min(q[0] - p[0], q[1] - p[1]) >= least), key=lambda s: s[0][0] - s[1][0])
    for p, q in spans:
        if linked(np.unique(ngram_hashes(a[p[0] : q[0]], SHINGLE)), np.unique(ngram_hashes(b[p[1] : q[1]], SHINGLE)), numerator, denominator):
            return p[0], q[0] - p[0]
    return None


def near_passages(docs: DataFrame, places: DataFrame, id_col: str = "doc_id", text_col: str = "text", numerator: int = 80, denominator: int = 100, passage_words: int = PASSAGE_WORDS, words: int = SEED_WORDS, bridge: int = BRIDGE) -> DataFrame:
    """doc_id, digest, place, n_words, first_doc_id, removed: passages that nearly equal one of an earlier document.

    A run under ``passage_words`` words is laid over the text of the earliest document that has its first window, and
    goes on in both directions over changed words; the longest span with ``passage_words`` words whose shingles agree with the
    other's (Jaccard) is a passage. Eight changes a side at most are tried, which bounds the work for one run; longer
    passages have a run that is long enough by itself. A pair of texts is one row, whatever its number of runs.
    """
    short = _runs(places, words, bridge).where(F.col("removed") & (F.col("n_words") < passage_words))
    pairs = stage(short.groupBy("doc_id", "digest", "first_doc_id").agg(F.sort_array(F.collect_set("place")).alias("at")), "short")
    need = pairs.select("doc_id").union(pairs.select("first_doc_id")).distinct()
    texts = _keyed(docs, id_col, text_col).join(F.broadcast(need) if 2 * pairs.count() <= BROADCAST_IDS else need, "doc_id", "left_semi")
    texts = stage(texts.dropDuplicates(["doc_id", "digest"]), "texts")
    first = texts.select(F.col("doc_id").alias("first_doc_id"), F.col("text").alias("other"))
    wide = pairs.join(texts, ["doc_id", "digest"]).join(first, "first_doc_id").select("doc_id", "digest", "first_doc_id", "at", "text", "other")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "digest", "first_doc_id", "place", "n_words"]
        for b in batches:
            got = set()
            for doc, digest, partner, at, text, other in zip(*[b.column(i).to_pylist() for i in range(4)], b.column(4), b.column(5), strict=True):
                x, y = word_hashes(text.as_py()), word_hashes(other.as_py())
                mine, theirs = _windows(x, words)[1], _windows(y, words)[1]
                order = np.argsort(theirs, kind="stable")
                for i in at:
                    k = int(np.searchsorted(theirs, mine[i], sorter=order))
                    if k < len(order) and theirs[order[k]] == mine[i]:
                        span = _extended(x, y, i, int(order[k]), numerator, denominator, passage_words, words)
                        if span:
                            got.add((doc, digest, partner, *span))
            yield pa.RecordBatch.from_arrays([pa.array([g[i] for g in got], pa.int64()) for i in range(len(names))], names=names)

    return arrow(wide, run, "doc_id bigint, digest bigint, first_doc_id bigint, place bigint, n_words bigint").distinct().withColumn("removed", F.lit(True))


def remove(docs: DataFrame, found: DataFrame, id_col: str = "doc_id", text_col: str = "text", chars_col: str | None = "n_chars") -> DataFrame:
    """``docs`` without the removed units that ``repeats`` found; a document that has no words left goes.

    Units belong to the rows with their doc_id and text, so equal rows are cut alike and others not at all.
    """
    spans = found.where("removed").groupBy(F.col("doc_id").alias("_d"), F.col("digest").alias("_h")).agg(F.collect_set(F.struct("unit", "place", "n_words", "start", "n_chars")).alias("_spans"))
    spans = stage(spans, "spans")
    # Rows without spans are not dealt where the others' ids may be broadcast.
    ids, few = spans.select("_d", "_h"), spans.count() <= BROADCAST_IDS
    ids = F.broadcast(ids) if few else ids
    same = (F.col(id_col).cast("bigint") == F.col("_d")) & (F.xxhash64(F.col(text_col).cast("string")) == F.col("_h"))
    cut = (docs.join(ids, same, "left_semi") if few else docs).join(spans, same, "inner" if few else "left").select(*[docs[c] for c in docs.columns], "_spans")
    names, kinds = docs.columns, docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            col = b.schema.get_field_index(text_col)
            texts, keep = [], []
            for t, cut in zip(b.column(col), b.column(len(names)).to_pylist(), strict=True):
                text = t.as_py()
                if cut:
                    text = _without(text, cut)
                texts.append(text)
                keep.append(not cut or bool(_WORD.search(text)))
            cols = [pa.array(texts, b.schema.field(i).type) if i == col else pa.array([None if v is None else len(v) for v in texts], b.schema.field(i).type) if n == chars_col else b.column(i) for i, n in enumerate(names)]
            yield pa.RecordBatch.from_arrays(cols, names=names).filter(pa.array(keep, pa.bool_()))

    left = arrow(cut, run, kinds)
    return docs.join(ids, same, "left_anti").unionByName(left) if few else left


def _without(text: str, cut: list[dict]) -> str:
    """A text without its paragraphs (with their line's end) and runs of words (with the white space after them)."""
    begins: list[int] = []
    if any(c["unit"] == "passage" for c in cut):
        begins = [m.start() for m in _WORD.finditer(text)] + [len(text)]
    spans = sorted((begins[c["place"]], begins[c["place"] + c["n_words"]]) if c["unit"] == "passage" else (c["start"], c["start"] + c["n_chars"] + 1) for c in cut)
    parts, last = [], 0
    for s, e in spans:
        parts.append(text[last:s])  # nothing where spans overlap
        last = max(last, min(e, len(text)))
    return "".join([*parts, text[last:]])
