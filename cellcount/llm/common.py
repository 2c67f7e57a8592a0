"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Iterator
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession

from ..cluster import ship

#: ASCII white space, the separators of "words" in several contracts.
SPACES = b" \t\n\x0b\x0c\r"
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; only Spark's reader touches the path."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    Where it is unset (local tests) a folder of the local machine is set once.
    """
    own = spark.conf.get("spark.checkpoint.dir", None)
    if own:
        return own.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return str(held.get()).rstrip("/")
    own = tempfile.mkdtemp(prefix="cellcount-")
    spark.sparkContext.setCheckpointDir(f"file://{own}")
    return f"file://{own}"


#: Rows of a batch that goes to Python at most: texts may be long, and both sides hold whole batches.
BATCH_ROWS = 1000
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def arrow(df: DataFrame, run, schema) -> DataFrame:
    """``mapInArrow`` whose function the executors can import, in batches of at most ``BATCH_ROWS`` rows."""
    spark = df.sparkSession
    ship(spark)
    if not 0 < int(spark.conf.get(_BATCH)) <= BATCH_ROWS:
        spark.conf.set(_BATCH, str(BATCH_ROWS))
    return df.mapInArrow(_tidy(run), schema)


def _tidy(run):
    """``run``, after which a task's free memory goes back to the system: workers live on, and hold their largest task's otherwise."""

    def tidied(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return tidied


def give_back() -> None:
    """Empty the memos of this process and return the free memory of its allocators."""
    for memo in WordHashes.all:
        memo.clear()
    pa.default_memory_pool().release_unused()
    trim = _trim()
    if trim:
        trim(0)


@lru_cache(maxsize=1)
def _trim():
    """glibc's malloc_trim; None with another C library."""
    try:
        return ctypes.CDLL(None).malloc_trim
    except (AttributeError, OSError, TypeError):
        return None


#: Rows of a file where a bound of the rows is known.
FILE_ROWS = 250_000


def stage(df: DataFrame, name: str, most: int | None = None) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: cuts the lineage, survives lost executors.

    ``most``: a bound of the rows, where one is known; the last tasks then are as few as the rows need.
    """
    spark = df.sparkSession
    if most is not None:
        df = df.coalesce(max(1, -(-most // FILE_ROWS)))
    ship(spark)
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_stage(df: DataFrame) -> None:
    """Delete the folder behind a table that ``stage`` wrote, once nothing reads it any more."""
    spark = df.sparkSession
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for root in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(root)
        path.getFileSystem(conf).delete(path, True)


def lower_ascii(text: str) -> bytes:
    """UTF-8 bytes with A-Z, and nothing else, lower-cased."""
    return text.encode("utf-8", "surrogatepass").translate(_LOWER)


class WordHashes(dict):
    """Memo of 64-bit word hashes of one Python worker; emptied when it holds ``limit`` words."""

    limit = 100_000
    all: list[WordHashes] = []

    def __init__(self):
        super().__init__()
        WordHashes.all.append(self)

    def __missing__(self, word) -> int:
        if len(self) >= self.limit:
            self.clear()
        value = self[word] = xxhash.xxh64_intdigest(word)
        return value

    def array(self, words: list) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


def mix64(x: np.ndarray) -> np.ndarray:
    """Avalanche of 64-bit values (the finaliser of splitmix64)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: A random value for each byte, and the odd base of the polynomial that hashes a word's bytes.
_BYTES = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BASE = 0xD6E8FEB86659FD95
#: Longer words, in bytes, are hashed by themselves.
LONG_WORD = 48
#: Bytes of the texts whose words are found at once; a longer text is a piece by itself.
PIECE_BYTES = 1 << 16
_GAP = np.isin(np.arange(256), list(SPACES))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """``n`` powers of the base, or more, and their inverses."""
    return _held_powers() if n <= PIECE_BYTES else _made_powers(n)


@lru_cache(maxsize=1)
def _held_powers() -> tuple[np.ndarray, np.ndarray]:
    return _made_powers(PIECE_BYTES)


def _made_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    both = []
    for base in (_BASE, pow(_BASE, -1, 1 << 64)):
        p = np.full(n, base, dtype=np.uint64)
        p[0] = 1
        both.append(np.cumprod(p, out=p))
    return both[0], both[1]


class Words(NamedTuple):
    """The words of some successive texts: ``row``, the first one's number; ``data``, the texts' bytes with A-Z lower-cased, and
    ``cuts``, where each begins and the last ends; ``begin`` and ``end`` of each word there, and its 64-bit ``hash``; ``at``,
    the number of words before each text, and of all."""

    row: int
    data: np.ndarray
    cuts: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    hash: np.ndarray
    at: np.ndarray


def _words(row: int, raw: bytes, cuts: np.ndarray) -> Words:
    data = np.frombuffer(raw.translate(_LOWER), dtype=np.uint8)
    n = len(data)
    gap = np.ones(n + 2, dtype=bool)
    gap[1:-1] = _GAP[data]
    first, last = gap[:-2].copy(), gap[2:].copy()
    first[cuts[cuts < n]] = True
    last[cuts[cuts > 0] - 1] = True
    begin, end = np.flatnonzero(first & ~gap[1:-1]), np.flatnonzero(last & ~gap[1:-1]) + 1
    up, down = _powers(n)
    total = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum(_BYTES[data] * up[:n], out=total[1:])
    size = end - begin
    h = mix64((total[end] - total[begin]) * down[begin] + size.astype(np.uint64))
    for i in np.flatnonzero(size > LONG_WORD).tolist():
        h[i] = xxhash.xxh64_intdigest(data[begin[i] : end[i]])
    return Words(row, data, cuts, begin, end, h, np.searchsorted(begin, cuts))


def words_in(texts: pa.Array) -> Iterator[Words]:
    """The words of a string column, in pieces of about ``PIECE_BYTES``; nulls are empty texts."""
    texts = texts.cast(pa.large_string())
    if texts.null_count:
        texts = texts.fill_null("")
    if not len(texts):
        return
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data, row = memoryview(texts.buffers()[2] or b""), 0
    while row < len(texts):
        to = max(row + 1, int(np.searchsorted(offsets, offsets[row] + PIECE_BYTES, "right")) - 1)
        yield _words(row, bytes(data[offsets[row] : offsets[to]]), offsets[row : to + 1] - offsets[row])
        row = to


def hashes_in(texts: pa.Array) -> Iterator[np.ndarray]:
    """The hashes of the words of each text."""
    for w in words_in(texts):
        for i, j in zip(w.at[:-1].tolist(), w.at[1:].tolist(), strict=True):
            yield w.hash[i:j]


def word_hashes(text: str | None) -> np.ndarray:
    """The hashes of the words of one text."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return _words(0, raw, np.array([0, len(raw)])).hash


def ngram_hashes(ids: np.ndarray, n: int) -> np.ndarray:
    """A 64-bit hash for each window of ``n`` successive ids; a shorter sequence is one window, none gives none."""
    if len(ids) == 0:
        return np.zeros(0, dtype=np.uint64)
    n = min(n, len(ids))
    out = np.full(len(ids) - n + 1, n, dtype=np.uint64)
    for j in range(n):
        out = out * np.uint64(0x9E3779B97F4A7C15) + ids[j : len(ids) - n + 1 + j]
        out ^= out >> np.uint64(29)
    return mix64(out)
