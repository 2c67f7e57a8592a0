"""Packing: first-fit decreasing over a tournament tree of bin capacities, in randomised groups of pieces.

A document becomes its token ids and an end id, cut into pieces of at most ``limit`` ids. Pieces are dealt by a
hash into groups of about ``group`` pieces, and each group is packed alone: descending sizes, each into the first
open bin with room, found by one descent of a tree whose inner nodes hold the largest free room below them.

Defined results: a null or empty text is one piece of the end id alone; a very long text gives many pieces, each
in some sequence; repeated rows are packed as often as they come; equal sizes go in order of document and start;
an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow, stage

#: Longest sequence and the id that ends a document.
LIMIT, END = 2048, 1
_SPECIAL = "<|endoftext|>"
_ENCODERS: dict = {}


def encoder(name: str):
    """text -> little-endian 32-bit ids, as the tokenizer file ``<name>.json`` gives them without special tokens.

    The ranks file of the same vocabulary is several times faster; texts that spell out the vocabulary's one
    special string go to the tokenizer itself. Both give equal ids (see the tests).
    """
    if name not in _ENCODERS:
        import base64

        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        fast = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        slow = []

        def encode(text: str) -> np.ndarray:
            if _SPECIAL in text:
                if not slow:
                    slow.append(Tokenizer.from_file(public_tokenizers.path(f"{name}.json")))
                return np.array(slow[0].encode(text, add_special_tokens=False).ids, dtype="<u4")
            return np.array(fast.encode_ordinary(text), dtype="<u4")

        _ENCODERS[name] = encode
    return _ENCODERS[name]


def pieces(docs: DataFrame, tokenizer: str = "byte_bpe_50k", limit: int = LIMIT, end: int = END, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens (and the ids as binary) of each piece of each document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer)
        for b in batches:
            doc, start, length, crc, total, ids = [], [], [], [], [], []
            for d, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                a = np.append(encode(text.as_py() or ""), np.uint32(end)).astype("<u4")
                for s in range(0, len(a), limit):
                    part = a[s : s + limit]
                    raw = part.tobytes()
                    doc.append(d)
                    start.append(s)
                    length.append(len(part))
                    crc.append(zlib.crc32(raw))
                    total.append(len(a))
                    if with_ids:
                        ids.append(raw)
            cols = [pa.array(x, pa.int64()) for x in (doc, start, length, crc, total)]
            names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
            yield pa.RecordBatch.from_arrays(cols + [pa.array(ids, pa.binary())] * with_ids, names=names + ["ids"] * with_ids)

    schema = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint" + ", ids binary" * with_ids
    return arrow(docs.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string")), run, schema)


def first_fit(sizes: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each size, in the given order, each into the first bin that has room.

    The bins are the leaves of a complete binary tree; a node holds the largest room below it.
    """
    leaves = 1 << max(0, int(len(sizes) - 1).bit_length())
    tree = [capacity] * (2 * leaves)
    bins, offsets = np.zeros(len(sizes), dtype=np.int64), np.zeros(len(sizes), dtype=np.int64)
    for i, size in enumerate(sizes.tolist()):
        node = 1
        while node < leaves:
            node *= 2
            if tree[node] < size:
                node += 1
        bins[i], offsets[i] = node - leaves, capacity - tree[node]
        tree[node] -= size
        while node > 1:
            node //= 2
            most = max(tree[2 * node], tree[2 * node + 1])
            if tree[node] == most:
                break
            tree[node] = most
    return bins, offsets


def pack(parts: DataFrame, limit: int = LIMIT, group: int = 8192, seed: int = 17) -> DataFrame:
    """``parts`` (of ``pieces``) with sequence_id and offset.

    ``parts`` is written to the shared folder once, since the number of groups follows from its count. A piece's group
    follows from its values; where rows repeat, from its stored place as well, so that they spread over all groups.
    """
    names = parts.columns
    key = F.xxhash64("doc_id", "start", "ids_crc32", F.lit(seed))
    held = stage(parts.withColumn("_at", F.monotonically_increasing_id()).withColumn("_k", key), "pieces")
    n = max(1, round(held.count() / group))
    again = held.groupBy("_k").agg(F.count("*").alias("_c")).where("_c > 1")
    place = F.when(F.col("_c").isNull(), F.col("_k")).otherwise(F.xxhash64("_k", "_at"))
    dealt = held.join(stage(again, "again"), "_k", "left").withColumn("_g", F.pmod(place, F.lit(n))).select(*names, "_g")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["length", "doc_id", "start"], ascending=[False, True, True], kind="stable")
        bins, offsets = first_fit(pdf["length"].to_numpy(), limit)
        pdf["sequence_id"] = pdf["_g"] * (1 << 24) + bins
        pdf["offset"] = offsets
        return pdf.drop(columns="_g")

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in parts.schema.fields)
    return dealt.groupBy("_g").applyInPandas(run, f"{kinds}, sequence_id bigint, offset bigint")


def sequences(packed: DataFrame, limit: int = LIMIT, pad: int = 0) -> DataFrame:
    """sequence_id, n_tokens, ids: the sequences themselves from packed pieces that carry ids.

    A sequence is padded to ``limit``, except where its length is a power of two.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        raw = b"".join(pdf.sort_values("offset")["ids"])
        n = len(raw) // 4
        if n & (n - 1):
            raw += np.full(limit - n, pad, dtype="<u4").tobytes()
        return pd.DataFrame({"sequence_id": [pdf["sequence_id"].iloc[0]], "n_tokens": [n], "ids": [np.frombuffer(raw, dtype="<u4").astype(np.int32).tolist()]})

    return packed.groupBy("sequence_id").applyInPandas(run, "sequence_id bigint, n_tokens bigint, ids array<int>")


def padding(packed: DataFrame, limit: int = LIMIT) -> DataFrame:
    """n_sequences, n_tokens, n_padding of a packing, under the padding rule of ``sequences``."""
    by = packed.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    power = F.col("n").bitwiseAND(F.col("n") - 1) == 0
    return by.agg(F.count("*").alias("n_sequences"), F.coalesce(F.sum("n"), F.lit(0)).alias("n_tokens"), F.coalesce(F.sum(F.when(power, 0).otherwise(limit - F.col("n"))), F.lit(0)).alias("n_padding"))
