"""The ten operators: registered queries against SQL, brute force, round trips, held-out accuracy, and edge cases."""

import hashlib
import json
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from cellcount.llm import chat, decontam, lm, neardup, packing, quality, rules, substring, toxicity, urls
from cellcount.llm.components import components
from cellcount.llm.labelled import auc, held_out, temperature
from cellcount.llm.queries import ORACLE, QUERIES
from tests.conftest import SMALL, TINY, agree

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"
LONG = " ".join(f"w{i % 997} x{i % 89}." for i in range(30_000))
#: Nulls, empty, long, repeated rows, white space of all kinds, no words; and columns whose names clash with internals.
EDGE = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, LONG, "en", "s", len(LONG)), (4, "same text here for all of us", "de", None, 1), (4, "same text here for all of us", "de", None, 1), (5, " \t\n\x0b\x0c\r ", "fr", "s", 7), (6, "###\n***", None, "s", 7), (7, "Ünïcode ÄÖ 日本語 😀", "xx", "s", 3), (None, "id is null but the text is not", "en", "s", 2)]


def edge(spark):
    return spark.createDataFrame(EDGE, DOCS).select("*", F.lit("x").alias("id"), F.lit(1).alias("n"), F.lit(2).alias("bucket"), F.lit("y").alias("_id"))


def empty(spark):
    return edge(spark).where("doc_id < -1")


@pytest.mark.parametrize("name", sorted(ORACLE))
def test_query_equals_sql(spark, name):
    agree(spark, name, QUERIES[name], ORACLE[name], TINY)


# ---------------------------------------------------------------------------------------------------- 1 chat


@settings(max_examples=200, deadline=None)
@given(st.lists(st.tuples(st.text(max_size=12), st.text(alphabet=st.sampled_from("\\<>/turn\n ao"), max_size=40) | st.text(max_size=20)), max_size=6))
def test_template_round_trip(turns):
    text, starts, lengths = chat.render_turns([{"role": r, "text": t} for r, t in turns], loss_roles=("a", "assistant"))
    assert chat.parse(text) == turns
    assert [chat.unescape(text[s : s + n]) for s, n in zip(starts, lengths, strict=True)] == [t for r, t in turns if r in ("a", "assistant")]


def test_layouts_by_fingerprint(spark):
    records = [
        {"messages": [{"role": "user", "content": "hi"}, {"role": "assistant", "content": "yo"}]},
        {"conversations": [{"from": "human", "value": "hi"}, {"from": "gpt", "value": "yo"}]},
        {"prompt": "hi", "response": "yo"}, {"instruction": "hi", "input": "there", "output": "yo"}, {"instruction": "hi", "input": "", "output": "yo"},
        {"question": None, "answer": 7}, {"other": 1}, None,
    ]
    rows = [(i, json.dumps(r)) for i, r in enumerate(records)] + [(8, "{broken"), (9, None), (10, "")]
    got = {r["id"]: (r["layout"], [(t["role"], t["text"]) for t in r["turns"]]) for r in chat.canonicalise_json(spark.createDataFrame(rows, "id bigint, j string"), "id", "j").collect()}
    pair = [("user", "hi"), ("assistant", "yo")]
    assert [got[k] for k in (0, 1, 2)] == [("messages", pair), ("conversations", pair), ("prompt_response", pair)]
    assert got[3][1][0] == ("user", "hi\n\nthere") and got[4][1] == pair and got[5][1] == [("user", ""), ("assistant", "7")]
    assert all(got[k] == (None, []) for k in (6, 7, 8, 9, 10))
    typed = spark.createDataFrame([(1, "hi", "yo")], "id bigint, prompt string, completion string")
    assert [tuple(t) for t in chat.canonicalise(typed, "id").first()["turns"]] == pair
    with pytest.raises(ValueError):
        chat.canonicalise(spark.createDataFrame([(1, 2)], "id bigint, zzz int"), "id")


def test_chat_edges(spark):
    rows = [(1, 1, "assistant", None), (1, 0, None, "q"), (1, 0, None, "q"), (2, None, "user", "b"), (2, 0, "user", "a"), (None, 0, "user", "n")]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumn("messages", F.lit(1))
    got = {r["conv_id"]: r for r in chat.read_back(chat.render(chat.canonicalise(chat.from_turn_rows(df), "conv_id"), "conv_id"), "conv_id").collect()}
    assert got[1]["n_turns"] == 3 and got[1]["loss_chars"] == 0 and got[1]["loss_sha256"] == hashlib.sha256(b"").hexdigest()
    assert got[2]["turns_sha256"] == hashlib.sha256(b"user\nb\nuser\na\n").hexdigest() and got[None]["n_turns"] == 1
    assert chat.from_turn_rows(df.where("conv_id > 5")).count() == 0


def test_contract_conversation(spark):
    r = QUERIES["op1_chat_formatting"](spark, TINY).where("conv_id = -7").first()
    said = r"\### Assistant: </turn> ok"
    assert (r["n_turns"], r["loss_chars"]) == (2, len(said)) and r["loss_sha256"] == hashlib.sha256(said.encode()).hexdigest()


def test_records_take_several_layouts(spark):
    rows = [(1, 0, "user", "q\u0001 \"x\""), (1, 1, "assistant", "a"), (2, 0, "system", "s"), (2, 1, "user", "q"), (2, 2, "assistant", None), (3, 0, "human", "h"), (3, 1, "gpt", "g"), (4, 0, "user", "alone"), (5, 0, "user", ""), (5, 0, "assistant", "b")]
    turns = chat.canonicalise_json(chat.to_records(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")), "conv_id", "record")
    got = {r["conv_id"]: (r["layout"], [(t["role"], t["text"]) for t in r["turns"]]) for r in turns.collect()}
    assert got == {
        1: ("prompt_response", [("user", "q\u0001 \"x\""), ("assistant", "a")]), 2: ("system_prompt", [("system", "s"), ("user", "q"), ("assistant", "")]), 3: ("messages", [("human", "h"), ("gpt", "g")]),
        4: ("messages", [("user", "alone")]), 5: ("messages", [("assistant", "b"), ("user", "")]),
    }


# ---------------------------------------------------------------------------------------------------- 2 packing


def _hf():
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=80) | st.text(alphabet=st.sampled_from(" \n\t'sdlaé1!<|endoftext>\x1c\x85\u2003"), max_size=60))
def test_fast_ids_equal_the_tokenizers(text):
    assert packing.encoder("byte_bpe_50k")(text).tolist() == _hf().encode(text, add_special_tokens=False).ids
    special = text + "<|endoftext|>"
    assert packing.encoder("byte_bpe_50k")(special).tolist() == _hf().encode(special, add_special_tokens=False).ids


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 20), max_size=40))
def test_first_fit_decreasing_equals_a_plain_scan(sizes):
    sizes = sorted(sizes, reverse=True)
    bins, offsets = packing.first_fit(np.array(sizes, dtype=np.int64), 20)
    room, want = [], []
    for s in sizes:
        k = next((i for i, r in enumerate(room) if r >= s), len(room))
        if k == len(room):
            room.append(20)
        want.append((k, 20 - room[k]))
        room[k] -= s
    assert list(zip(bins.tolist(), offsets.tolist(), strict=True)) == want


@pytest.mark.parametrize("source", ["tiny", "edge"])
def test_packing_is_whole_and_gapless(spark, source):
    docs = spark.read.parquet(f"{TINY}/documents.parquet") if source == "tiny" else edge(spark)
    tok, want = _hf(), Counter()
    for r in docs.collect():
        ids = tok.encode(r["text"] or "", add_special_tokens=False).ids + [1]
        want[(r["doc_id"], len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))] += 1
    packed = packing.pack(packing.pieces(docs, with_ids=True)).persist()
    rows = packed.collect()
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append(r)
        assert zlib.crc32(r["ids"]) == r["ids_crc32"] and len(r["ids"]) == 4 * r["length"]
    for own in by.values():
        at = 0
        for r in sorted(own, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
    parts = defaultdict(list)
    for r in rows:
        parts[r["doc_id"], r["doc_tokens"]].append(r)
    got = Counter()
    for (d, n), own in parts.items():
        copies = sum(r["start"] == 0 for r in own)
        own = sorted(own, key=lambda r: (r["start"], r["ids_crc32"]))[::copies]
        whole = b"".join(r["ids"] for r in own)
        got[(d, n, zlib.crc32(whole))] += copies
        assert len(whole) == 4 * n
    assert got == want
    seqs = packing.sequences(packed).collect()
    assert all(len(s["ids"]) == 2048 or len(s["ids"]) == s["n_tokens"] and s["n_tokens"] & (s["n_tokens"] - 1) == 0 for s in seqs)
    p = packing.padding(packed).first()
    assert p["n_padding"] <= 0.1 * p["n_tokens"] + 2048
    assert packing.pack(packing.pieces(empty(spark))).count() == 0


def test_packing_spreads_repeated_rows(spark):
    docs = spark.createDataFrame([(1, "a b c")] * 3000 + [(2, "d e"), (None, "f")], "doc_id bigint, text string")
    out = packing.pack(packing.pieces(docs), group=250)
    assert out.count() == 3002
    groups = Counter(r["sequence_id"] >> 24 for r in out.collect())
    assert len(groups) == 12 and max(groups.values()) < 400


# ---------------------------------------------------------------------------------------------------- 3, 5 classifiers


def test_quality_is_learned(spark):
    got = QUERIES["op3_quality_classifier"](spark, SMALL).join(spark.read.parquet(f"{SMALL}/labels.parquet"), "doc_id").where("held_out").toPandas()
    assert auc(got["score"].to_numpy(), got["quality"].to_numpy()) > 0.95
    assert got["score"].between(0, 1).all() and ((got["score"] >= 0.3) == (got["predicted"] == 1)).all()


def test_toxicity_is_learned(spark):
    got = QUERIES["op5_toxicity"](spark, SMALL).join(spark.read.parquet(f"{SMALL}/labels.parquet"), "doc_id").where("held_out").toPandas()
    assert auc(got["score"].to_numpy(), got["toxic"].to_numpy()) > 0.85
    assert ((got["predicted"] == 1) & (got["toxic"] == 0)).sum() <= 0.02 * len(got)


def test_held_out_rows(spark):
    got = spark.range(50).select(F.col("id").alias("doc_id"), held_out(5, 0).alias("h")).collect()
    assert all(r["h"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in got)


def test_classifier_edges(spark):
    docs, labels = spark.read.parquet(f"{TINY}/documents.parquet"), spark.read.parquet(f"{TINY}/labels.parquet")
    q, t = quality.fit(docs, labels, F.lit(True)), toxicity.fit(docs, labels, F.lit(True))
    for out in (quality.score(edge(spark), q), toxicity.score(edge(spark), t)):
        rows = out.collect()
        assert len(rows) == len(EDGE) and all(0 <= r["score"] <= 1 for r in rows)
        by = {r["doc_id"]: r["score"] for r in rows}
        assert by[1] == by[2] == by[5]
    assert quality.score(empty(spark), q).count() == toxicity.score(empty(spark), t).count() == 0
    none = labels.where("doc_id < 0")
    assert quality.fit(docs, none, F.lit(True)) is None and toxicity.fit(docs, none, F.lit(True)) is None
    assert {r["score"] for r in quality.score(edge(spark), None).collect()} == {0.5}
    assert toxicity.keep_clean(edge(spark), None).count() == len(EDGE)
    assert quality.fit(empty(spark), labels, F.lit(True)) is None


def test_scores_do_not_depend_on_other_columns(spark):
    docs, labels = spark.read.parquet(f"{TINY}/documents.parquet"), spark.read.parquet(f"{TINY}/labels.parquet")
    m = toxicity.fit(docs, labels, F.lit(True))
    other = docs.withColumn("lang", F.lit("zz")).withColumn("source", F.lit("q"))
    a, b = ({r["doc_id"]: r["score"] for r in toxicity.score(x, m).collect()} for x in (docs, other))
    assert a == b


def test_gradients_of_the_network():
    rng = np.random.default_rng(0)
    texts = ["good day to you all", "bad bad idiot here", "nice word list", "idiot again now"] * 6
    m = toxicity.train(texts, np.array([0, 1, 0, 1] * 6), ["en"] * 24)
    p = toxicity._scores(m, ["what an idiot", "a nice day"], toxicity._lookup(m))
    assert p[0] > 0.6 > p[1] and rng is not None


def test_scores_do_not_depend_on_batches(spark, monkeypatch):
    texts = [r["text"] for r in spark.read.parquet(f"{TINY}/documents.parquet").orderBy("doc_id").limit(60).collect()]
    m = toxicity.train(texts, np.array([i % 3 == 0 for i in range(60)]), ["en"] * 60)
    alone = np.concatenate([toxicity._scores(m, [t], toxicity._lookup(m)) for t in texts])
    monkeypatch.setattr(toxicity, "MEMO", 50)
    monkeypatch.setattr(toxicity, "CHUNK", 700)
    assert np.allclose(toxicity._scores(m, texts, toxicity._lookup(m)), alone, atol=1e-5)


def test_temperature_restores_calibration():
    rng = np.random.default_rng(1)
    z = rng.normal(0, 2, 4000)
    y = (rng.random(4000) < 1 / (1 + np.exp(-z))).astype(float)
    assert 2.5 < temperature(3 * z, y) < 3.6


def test_quality_equals_brute_force(spark):
    """Context vectors, pooling and the network, word by word."""
    rng = random.Random(8)
    texts = [" ".join(rng.choice(["Sun,", "rain", "RIVER", "stone.", "7", "cloud!", "a-b"]) for _ in range(rng.randint(1, 25))) for _ in range(40)] + ["", None]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id bigint, text string")
    index, memo = quality.index_vectors(), quality.Tokens()
    want = np.zeros((quality.BUCKETS, quality.DIM))
    for t in texts:
        core, shape = memo.pairs((t or "").split())
        for i in range(len(core)):
            for j in range(max(0, i - 2), min(len(core), i + 3)):
                if i != j:
                    for own in (core[i], shape[i]):
                        want[own] += index[core[j]] + index[shape[j]]
    got = quality.contexts(docs)
    assert np.array_equal(got, want)
    vectors = quality.word_vectors(got)
    known = np.abs(want).sum(axis=1) > 0
    assert np.allclose(np.linalg.norm(vectors[:-1][known], axis=1), 1, atol=1e-5) and not vectors[:-1][~known].any()

    def features(t):
        core, shape = memo.pairs((t or "").split())
        x, n = [vectors[c].astype(float) for c in core], max(1, len(core))
        mean = sum(x, np.zeros(quality.DIM)) / n
        spread = np.sqrt(np.maximum(sum((v * v for v in x), np.zeros(quality.DIM)) / n - mean * mean, 0))
        shapes = sum((vectors[s].astype(float) for s in shape), np.zeros(quality.DIM)) / n
        alike = [sum(float(x[i] @ x[i - d]) for i in range(d, len(x))) / n for d in (1, 2, 3)]
        return np.r_[mean, spread, shapes, alike, np.log1p(len(core)) / 10, float(not len(core))]

    labels = spark.createDataFrame([(i, int(i % 2)) for i in range(40)], "doc_id bigint, quality int")
    model = quality.fit(docs, labels, F.lit(True))
    w1, b1, w2, b2 = model.params
    for r in quality.score(docs, model).collect():
        z = (features(texts[r["doc_id"]]) - model.mean) / model.scale
        hidden = [max(0.0, float(sum(z[i] * w1[i, h] for i in range(len(z))) + b1[h])) for h in range(len(b1))]
        logit = (sum(a * b for a, b in zip(hidden, w2, strict=True)) + b2[0]) / model.temperature
        assert abs(r["score"] - 1 / (1 + math.exp(-max(-30, min(30, logit))))) < 1e-3


def brute_toxicity(model, text):
    """The network on one text, word by word and window by window."""
    from cellcount.llm import toxicity

    emb = [sum((model.emb[model.rows.get(f, 0)] for f in toxicity.features(w)), np.zeros(model.emb.shape[1])) for w in toxicity.words(text)]
    emb = emb or [np.zeros(model.emb.shape[1])]
    pooled = []
    for k, f in enumerate(model.filters):
        for j in range(toxicity.FILTERS):
            best = max(sum(emb[i + d] @ f[d][:, j] for d in range(len(f)) if i + d < len(emb)) for i in range(len(emb)))
            pooled.append(max(0.0, best + model.bias[k * toxicity.FILTERS + j]))
    z = float(np.dot(pooled, model.out) + model.out_bias) / model.temperature
    return 1 / (1 + math.exp(-max(-30, min(30, z))))


def test_toxicity_forward_pass_equals_brute_force(monkeypatch):
    from cellcount.llm import toxicity

    rng = random.Random(1)
    word = lambda: rng.choice(["sun", "rain", "field", "stone", "vile", "hate", "river", "cloud"])
    texts = [" ".join(word() for _ in range(rng.randint(1, 30))) for _ in range(60)]
    y = np.array([int("vile" in t and "hate" in t) for t in texts])
    model = toxicity.train(texts, y, ["en"] * 60, epochs=3)
    some = [*texts[:12], "", None, " ".join(word() for _ in range(200))]
    want = [brute_toxicity(model, t) for t in some]
    for chunk in (toxicity.CHUNK, 37):
        monkeypatch.setattr(toxicity, "CHUNK", chunk)
        assert np.allclose(toxicity._scores(model, some, toxicity._lookup(model)), want, atol=1e-4)


# ---------------------------------------------------------------------------------------------------- 4 language model


def brute_scores(rows, vocab, alpha=0.4, least=1, apart=True):
    low = lambda t: t.encode().translate(bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))).split()
    words = defaultdict(list)
    for d, t in rows:
        words[d].append(low(t or ""))
    counts = Counter(w for docs in words.values() for ws in docs for w in ws)
    total, held, edge_ = sum(counts.values()), 0, 0
    sizes = Counter(counts.values())
    for n in sorted(sizes, reverse=True):
        held += sizes[n]
        if held > vocab:
            edge_ = n
            break
    ids = {d: [[w if counts[w] > edge_ else None for w in ws] for ws in docs] for d, docs in words.items()}
    u = Counter(w for docs in ids.values() for ws in docs for w in ws)
    b = Counter(p for docs in ids.values() for ws in docs for p in zip(ws, ws[1:], strict=False))
    out = {}
    for d, docs in ids.items():
        s = 0.0
        for ws in docs:
            s += math.log(u[ws[0]] / total) if ws else 0.0
            mine = Counter(zip(ws, ws[1:], strict=False)) if apart else Counter()
            for v, w in zip(ws, ws[1:], strict=False):
                n = b[v, w] - mine[v, w]
                s += math.log(n / u[v]) if n >= least else math.log(alpha * u[w] / total)
        out[d] = (sum(map(len, docs)), s)
    return out


@pytest.mark.parametrize("vocab,hot", [(65_535, 512), (300, 40), (50, 512), (65_535, 0)])
def test_lm_equals_brute_force(spark, vocab, hot):
    docs = spark.read.parquet(f"{TINY}/documents.parquet").limit(120).unionByName(edge(spark).select("doc_id", "text", "lang", "source", "n_chars")).persist()
    want = brute_scores([(r["doc_id"], r["text"]) for r in docs.collect()], vocab)
    got = {r["doc_id"]: (r["n_words"], r["log_score"]) for r in lm.score(docs, vocab=vocab, hot=hot).collect()}
    assert set(got) == set(want)
    for d, (n, s) in want.items():
        assert got[d][0] == n and abs(got[d][1] - s) < 1e-6 * max(1.0, abs(s)), d


@pytest.mark.parametrize("least,apart", [(1, True), (2, False), (1, False)])
def test_lm_keeps_every_word_apart(spark, monkeypatch, least, apart):
    """Over 65,535 distinct words, most of them tied, and one of them more frequent: none shares another's count."""
    monkeypatch.setattr(lm, "LISTED", 65_535)
    rows = [(i, " ".join(f"w{x} w{x + 1}" for x in range(i * 1000, i * 1000 + 1000))) for i in range(70)]
    rows += [(100, "w5 w6 w69999 again"), (101, "again w5 w6 w5"), (102, "w12345"), (100, "w777 w777 again w777"), (103, "")]
    want = brute_scores(rows, 1 << 30, least=least, apart=apart)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], DOCS)
    got = {r["doc_id"]: (r["n_words"], r["log_score"]) for r in lm.score(docs, min_count=least, apart=apart).collect()}
    assert set(got) == set(want)
    for d, (n, s) in want.items():
        assert got[d][0] == n and abs(got[d][1] - s) < 1e-6 * max(1.0, abs(s)), d


def test_lm_query_uses_every_count(spark):
    want = brute_scores([(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{TINY}/documents.parquet").collect()], 1 << 30)
    got = {r["doc_id"]: (r["n_words"], r["log_score"]) for r in QUERIES["op4_lm_scoring"](spark, TINY).collect()}
    assert set(got) == set(want)
    for d, (n, s) in want.items():
        assert got[d][0] == n and abs(got[d][1] - s) < 1e-4, d


def test_lm_joins_the_words_that_are_not_listed(spark, monkeypatch):
    monkeypatch.setattr(lm, "LISTED", 300)
    docs = spark.read.parquet(f"{TINY}/documents.parquet").limit(120).persist()
    want = brute_scores([(r["doc_id"], r["text"]) for r in docs.collect()], 1 << 30)
    got = {r["doc_id"]: r["log_score"] for r in lm.score(docs).collect()}
    assert all(abs(got[d] - s) < 1e-6 * max(1.0, abs(s)) for d, (_, s) in want.items()) and len(got) == len(want)


def test_lm_scores_repeated_texts_apart(spark):
    rng = random.Random(4)
    text = lambda: " ".join(f"w{rng.randrange(400)}" for _ in range(60))
    rows = [(i, text()) for i in range(80)]
    rows += [(100 + i, rows[i][1]) for i in range(8)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = {r["doc_id"]: r["log_per_word"] for r in lm.score(docs).collect()}
    twice = [got[i] for i in range(8)] + [got[100 + i] for i in range(8)]
    assert min(twice) > max(got[i] for i in range(8, 80))


def test_lm_of_nothing(spark):
    assert lm.score(empty(spark)).count() == 0
    r = lm.score(edge(spark).where("doc_id = 1")).first()
    assert (r["n_words"], r["log_score"], r["log_per_word"]) == (0, 0.0, 0.0)


# ---------------------------------------------------------------------------------------------------- 6 rules


def brute_measures(t):
    t = t or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    seen, lines = set(), 0
    for x in t.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", x):
            lines += x in seen
            seen.add(x)
    grams = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {p for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for p in range(i, i + 5)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), lines, len(covered)


def test_rules_equal_brute_force(spark):
    extra = ["a b c d e f a b c d e g a b c d e", "x x x x x x x x", "l1 w\nl1 w\n\nl2\nl1 w \nl2"]
    docs = edge(spark).unionByName(spark.createDataFrame([(100 + i, t, None, None, 0) for i, t in enumerate(extra)], DOCS), allowMissingColumns=True)
    want = Counter((r["doc_id"], *brute_measures(r["text"])) for r in docs.collect())
    got = Counter(tuple(r) for r in rules.ledger(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words").collect())
    assert got == want
    assert rules.ledger(empty(spark)).count() == 0


def test_policies_and_ablation(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    led = rules.ledger(docs).persist()
    rows = led.collect()
    m = rules.mask("quality-1")
    assert rules.apply_policy(led).where("kept").count() == sum(r["failed"] & m == 0 for r in rows)
    for a in rules.ablation(led).collect():
        b = a["bit"]
        assert a["n_fail"] == sum(bool(r["failed"] & m & b) for r in rows)
        assert a["n_only"] == sum(r["failed"] & m == b for r in rows)
        assert a["n_kept_without"] == sum(r["failed"] & m & ~b == 0 for r in rows)
    good = led.join(spark.read.parquet(f"{SMALL}/labels.parquet").where("quality = 1"), "doc_id")
    assert rules.apply_policy(good).where("not kept").count() <= 0.1 * good.count()


def test_native_operators_run_no_python(spark):
    for name in ("op6_quality_rules", "op10_url_reputation"):
        assert not re.search("Python|Arrow|Pandas", QUERIES[name](spark, TINY)._jdf.queryExecution().executedPlan().toString())


# ---------------------------------------------------------------------------------------------------- 7 near-duplicates


def jaccard(a, b):
    p, q = set(neardup.shingles(a).tolist()), set(neardup.shingles(b).tolist())
    return len(p & q) / len(p | q) if p | q else 0.0


def brute_components(texts, share):
    ids = list(texts)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    sets = {i: set(neardup.shingles(t).tolist()) for i, t in texts.items()}
    for x, i in enumerate(ids):
        for j in ids[:x]:
            p, q = sets[i], sets[j]
            if p and q and 100 * len(p & q) >= share * len(p | q):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {i: find(i) for i in ids}


def variants(n, seed, base_words=60, edits=4):
    """Copies of one text with edits of their own: alike to the text, less so to each other."""
    rng = random.Random(seed)
    base = [f"b{i}" for i in range(base_words)]
    out = [" ".join(base)]
    for k in range(n):
        w = list(base)
        for _ in range(rng.randint(0, edits)):
            w[rng.randrange(len(w))] = f"e{k}_{rng.random()}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("block", [512, 16])
def test_components_of_chains_and_large_groups(spark, block):
    texts = variants(150, 1, 60, 2) + variants(60, 2, 40, 3) + [" ".join(f"z{(i + k) % 400}" for i in range(80)) for k in range(0, 90, 3)] + ["a b c", "A  b\nC", "a b", "", " "]
    random.Random(5).shuffle(texts)
    rows = [(i, t) for i, t in enumerate(texts)] + [(9000, None), (None, "a b c")]
    got = {r["id"]: r["component"] for r in neardup.classes(spark.createDataFrame(rows, "id bigint, text string"), 85, 100, block=block).collect()}
    want = brute_components(dict(enumerate(texts)), 85)
    assert {i: got[i] for i in want} == want and got[9000] == 9000


def test_neardup_edges(spark):
    items = edge(spark).withColumn("id", F.col("doc_id"))
    rows = neardup.classes(items, 85, 100).collect()
    assert len(rows) == len(EDGE) and {r["id"]: r["component"] for r in rows if r["id"]} == {i: i for i in (1, 2, 3, 4, 5, 6, 7)}
    assert neardup.classes(items.where("doc_id < -1"), 85, 100).count() == 0


def test_neardup_of_repeated_rows(spark):
    """Equal rows, and rows of one id with other texts, stand for their class once."""
    a, b = " ".join(f"w{i}" for i in range(60)), " ".join(f"v{i}" for i in range(60))
    rows = [(1, a)] * 3000 + [(2, b), (2, a), (3, a + " more"), (4, None), (4, ""), (None, b)]
    got = Counter((r["id"], r["n_shingles"], r["component"]) for r in neardup.classes(spark.createDataFrame(rows, "id bigint, text string"), 85, 100).collect())
    assert got == Counter({(1, 56, 1): 3000, (2, 56, 2): 1, (2, 56, 1): 1, (3, 57, 1): 1, (4, 0, 4): 2, (None, 56, None): 1})


def test_posterior_bound():
    assert neardup.least_matches(144, 0.85) < 0.85 * 144 and neardup.least_matches(144, 0.85) > 0.6 * 144
    assert neardup.least_matches(36, 0.85, 1e-3) > neardup.least_matches(36, 0.85, 1e-9)
    rng = np.random.default_rng(0)
    a = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    b = np.r_[a[:2700], rng.integers(0, 1 << 63, 300, dtype=np.uint64)]
    same = (neardup.signature(a, 144) == neardup.signature(b, 144)).mean()
    assert abs(same - 2700 / 3300) < 0.12


def test_components_by_joins(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(1000 + i, 1001 + i) for i in range(70)] + [(5, 5), (None, 3)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            p, q = sorted((find(a), find(b)))
            root[q] = p
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {x: find(x) for x in root}
    assert components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


# ---------------------------------------------------------------------------------------------------- 8 substrings


def test_passages_that_repeat(spark):
    rng = random.Random(9)
    own = lambda k, n=60: " ".join(f"o{k}_{rng.random():.6f}" for _ in range(n))
    passage = " ".join(f"p{i}" for i in range(64))
    near = passage.replace("p20 ", "Q ")
    split = "\n".join(" ".join(f"s{i}" for i in range(k, k + 14)) for k in range(0, 70, 14))
    short = "a short common line of a few words"
    texts = {
        1: f"{own(1)}\n{passage}\n{own(2)}", 2: f"{passage.upper()}\n{own(3)}", 3: f"{own(4)}\n{near}", 4: f"{own(5)}\n{split}\n{own(6)}", 5: f"{split}\n{own(7)}",
        6: f"{short}\n{own(8)}", 7: f"{short}\n{own(9)}", 8: f"{own(10)}", 9: f"{own(11)}\n{own(12)}", 10: passage,
    }
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], DOCS)
    found = substring.repeats(docs).persist()
    lines = found.where("unit = 'paragraph'").persist()
    removed = {(r["doc_id"], r["first_doc_id"]) for r in lines.where("removed").collect()}
    assert removed == {(2, 1), (3, 1), (10, 1), (5, 4)}
    assert {r["doc_id"] for r in lines.where("not removed").collect()} == {1, 4}
    left = {r["doc_id"]: r["text"] for r in substring.remove(docs, lines).collect()}
    assert set(left) == {1, 2, 3, 4, 5, 6, 7, 8, 9} and passage not in left[2].lower() and "s3 s4" not in left[5]
    left = {r["doc_id"]: r["text"] for r in substring.remove(docs, found).collect()}
    assert set(left) == {1, 2, 3, 4, 5, 6, 7, 8, 9}
    assert all(left[i] == texts[i] for i in (1, 4, 6, 7, 8, 9))
    assert all(passage not in left[i].lower() and "p30 p31" not in left[i].lower() for i in (2, 3)) and "s3 s4" not in left[5]
    assert all(r["n_chars"] == len(r["text"]) for r in substring.remove(docs, found).collect())


def brute_passages(texts, least=50, seed=24, bridge=2):
    """(doc, place, words, removed) of (doc, text) pairs: the rule on plain word lists."""
    words = {(d, t): substring.lower_ascii(t).split() for d, t in texts if d is not None and t is not None}
    has = {}
    for (d, _), w in words.items():
        for i in range(len(w) - seed + 1):
            has.setdefault(tuple(w[i : i + seed]), set()).add(d)
    out = set()
    for (d, t), w in words.items():
        for removed in (True, False):
            at = [i for i in range(len(w) - seed + 1) if len(h := has[tuple(w[i : i + seed])]) > 1 and (min(h) < d) == removed]
            while at:
                n = next((k for k in range(1, len(at)) if at[k] - at[k - 1] > seed + bridge), len(at))
                if at[n - 1] + seed - at[0] >= least:
                    out.add((d, at[0], at[n - 1] + seed - at[0], removed))
                at = at[n:]
    return out


def test_passages_inside_lines_are_cut(spark):
    import corpus_pipeline as pipe

    own = lambda k, n=70: " ".join(f"o{k}_{i}" for i in range(n))
    words = [f"p{i}" for i in range(60)]
    passage, broken = " ".join(words), "\n".join(" ".join(words[i : i + 7]) for i in range(0, 60, 7))
    texts = [
        (1, f"{own(1)} {passage} {own(2)}"), (2, f"{own(3)} {passage.upper()} {own(4)}"), (3, f"{own(5)}\n{broken} {own(6)}"), (4, f"{own(7)} {' '.join(words[:49])} {own(8)}"),
        (5, f"{own(9)} {' '.join(words[5:55])}"), (6, own(10)), (6, f"{own(11)} {passage}"), (6, None), (7, f"{own(12, 80)} {own(12, 80)}"), (None, passage), (8, passage),
    ]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts], DOCS)
    found = substring.repeats(docs)
    assert {(r["doc_id"], r["place"], r["n_words"], r["removed"]) for r in found.where("unit = 'passage'").collect()} == brute_passages(texts)
    left = Counter((r["doc_id"], None if r["text"] is None else " ".join(r["text"].split())) for r in substring.remove(docs, found).collect())
    # Repeats inside one document, and 49 words, stay; a row without id is no document.
    want = {1: texts[0][1], 2: f"{own(3)} {own(4)}", 3: f"{own(5)} {own(6)}", 4: texts[3][1], 5: own(9), 7: texts[8][1]}
    assert left == Counter([*want.items(), (6, own(10)), (6, own(11)), (6, None), (None, passage)])
    some = docs.where("doc_id in (1, 2, 3)")
    assert {r["doc_id"]: " ".join(r["text"].split()) for r in pipe.substring_stage(spark, some, TINY).collect()} == {i: want[i] for i in (1, 2, 3)}


def test_passages_against_brute_force(spark):
    rng = random.Random(11)
    pool = [[f"v{k}_{i}" for i in range(rng.randint(20, 90))] for k in range(6)]
    texts = []
    for d in range(60):
        parts = []
        for _ in range(rng.randint(1, 4)):
            p = list(rng.choice(pool))
            a = rng.randrange(len(p))
            p = p[:a] + (["x%d" % rng.random()] if rng.random() < 0.3 else []) + p[a + rng.randint(0, 3) :]
            parts.append(rng.choice((" ", "\n")).join(p) if rng.random() < 0.8 else " ".join(f"u{rng.random()}" for _ in range(40)))
        texts.append((d if rng.random() < 0.9 else d // 2, " ".join(parts)))
    texts += [(70 + i, texts[i][1]) for i in range(10)] + texts[:5]
    docs = spark.createDataFrame(texts, "doc_id bigint, text string")
    places = substring.shared_windows(docs)
    got = [(r["doc_id"], r["place"], r["n_words"], r["removed"]) for r in substring.repeated_passages(docs, places).collect()]
    assert set(got) == brute_passages(texts)


def test_near_copies_of_short_lines(spark):
    import corpus_pipeline as pipe

    own = lambda k, n=70: " ".join(f"o{k}_{i}" for i in range(n))
    lines = [" ".join(f"p{i}" for i in range(k, k + 20)) for k in (0, 20, 40)]
    near = [lines[0], lines[1].replace("p30", "Q"), lines[2]]
    end = [lines[0].replace("p14", "Q"), *lines[1:]]
    gone = [lines[0], lines[1], lines[2].replace("p47 ", "")]
    far = [lines[0].replace("p10", "Q"), lines[1].replace("p25", "R").replace("p33", "S"), lines[2].replace("p50", "T")]
    texts = {1: [own(1), *lines, own(2)], 2: [own(3), *near, own(4)], 3: [own(5), *far, own(6)], 4: [own(7), *lines[:1], own(8)], 5: [own(9), *end, own(10)], 6: [own(11), *gone, own(12)]}
    docs = spark.createDataFrame([(i, "\n".join(t), "en", "s", len("\n".join(t))) for i, t in texts.items()], DOCS)
    left = {r["doc_id"]: r["text"].split("\n") for r in pipe.substring_stage(spark, docs, TINY).collect()}
    assert left == {**texts, 2: [own(3), own(4)], 5: [own(9), own(10)], 6: [own(11), own(12)]}


def test_runs_go_on_over_changed_words():
    a = np.arange(200, dtype=np.uint64)
    b = a[60:130].copy()
    b[10] = 999
    assert substring._extended(b, a, 30, 90, 80, 100, 50, 24) == (0, 70)
    b[[5, 15, 60]] = 777
    assert substring._extended(b, a, 30, 90, 80, 100, 50, 24) is None or substring._extended(b, a, 30, 90, 80, 100, 50, 24)[1] < 70
    assert substring._extended(np.delete(a[60:130], 12), a, 30, 91, 80, 100, 50, 24) == (0, 69)
    assert substring._extended(a[60:100], a, 5, 65, 80, 100, 50, 24) is None


def test_removal_of_repeated_rows(spark):
    own = lambda k, n=70: " ".join(f"o{k}_{i}" for i in range(n))
    passage = " ".join(f"p{i}" for i in range(60))
    one, two, other = f"{own(1)}\n{passage}", f"{own(2)}\n{passage}\n{own(3)}", f"{own(4)}\n{own(5)}"
    rows = [(1, one)] * 3 + [(2, two)] * 2 + [(2, other), (2, None), (2, "")]
    kind = "doc_id int, text string, n_chars int, digest string, unit string, start string"
    docs = spark.createDataFrame([(i, t, None if t is None else len(t), "clash", "u", "s") for i, t in rows], kind)
    out = substring.remove(docs, substring.repeats(docs, near=True))
    assert out.schema == docs.schema
    left = Counter((r["doc_id"], r["text"], r["n_chars"], r["digest"]) for r in out.collect())
    cut = f"{own(2)}\n{own(3)}"
    assert left == Counter({(1, one, len(one), "clash"): 3, (2, cut, len(cut), "clash"): 2, (2, other, len(other), "clash"): 1, (2, None, None, "clash"): 1, (2, "", 0, "clash"): 1})
    many = spark.createDataFrame([(1, one)] * 1500 + [(2, one)] * 1500 + [(3, two)], "doc_id bigint, text string")
    left = Counter(r["doc_id"] for r in substring.remove(many, substring.repeats(many), chars_col=None).collect())
    assert left == {1: 1500, 3: 1}


def test_substring_edges(spark):
    passage = " ".join(f"r{i}" for i in range(55))
    docs = edge(spark)
    docs = docs.unionByName(spark.createDataFrame([(20, passage), (21, f"x\n{passage}"), (21, f"x\n{passage}"), (22, "\n".join([passage] * 40_000))], "doc_id bigint, text string"), allowMissingColumns=True)
    found = substring.repeats(docs, near=True).persist()
    assert {(r["unit"], r["doc_id"], r["removed"]) for r in found.collect()} == {(u, d, d > 20) for u in ("paragraph", "passage") for d in (20, 21, 22)}
    left = substring.remove(docs, found)
    assert left.columns == docs.columns and Counter(r["doc_id"] for r in left.collect()) == Counter(r["doc_id"] for r in docs.collect() if r["doc_id"] != 22)
    assert substring.repeats(edge(spark)).count() == 0
    assert substring.repeats(empty(spark), near=True).count() == 0
    assert substring.remove(empty(spark), found).count() == 0


def test_edit_distance(spark):
    a = [f"w{i}" for i in range(30)]
    assert substring.edit_similarity(" ".join(a), " ".join(a[:10] + a[11:])) == 1 - 1 / 30
    assert substring.edit_similarity("a b c", "x a b c") == 0.75 and substring.edit_similarity("", "") == 1.0 and substring.edit_similarity("a", "") == 0.0

    def plain(x, y):
        d = [[max(i, j) if not i or not j else 0 for j in range(len(y) + 1)] for i in range(len(x) + 1)]
        for i in range(1, len(x) + 1):
            for j in range(1, len(y) + 1):
                d[i][j] = min(d[i - 1][j] + 1, d[i][j - 1] + 1, d[i - 1][j - 1] + (x[i - 1] != y[j - 1]))
        return d[-1][-1]

    rng = random.Random(2)
    for _ in range(60):
        x, y = ([rng.choice("abcd") for _ in range(rng.randint(1, 9))] for _ in range(2))
        assert abs(substring.edit_similarity(" ".join(x), " ".join(y)) - (1 - plain(x, y) / max(len(x), len(y)))) < 1e-12
    words = [f"v{i}" for i in range(60)]
    texts = [" ".join(words), " ".join("X" if i in (20, 45) else w for i, w in enumerate(words))]
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in enumerate(texts)], DOCS)
    assert substring.repeated_paragraphs(docs).count() == 0 and substring.repeated_paragraphs(docs, measure="edit").where("removed").count() == 1


# ---------------------------------------------------------------------------------------------------- 9 decontamination


def brute_hits(text, items):
    w = decontam.words(text)
    hit, found = set(), set()
    for item, t in items:
        b = decontam.words(t)
        n = min(13, len(b))
        grams = {tuple(b[i : i + n]) for i in range(len(b) - n + 1)} if n else set()
        for i in range(len(w) - n + 1) if n else ():
            if tuple(w[i : i + n]) in grams:
                hit |= set(range(i, i + n))
                found.add(str(item))
    return len(w), len(hit), ",".join(sorted(found))


@settings(max_examples=150, deadline=None)
@given(st.lists(st.sampled_from("abc"), max_size=60), st.lists(st.lists(st.sampled_from("abc"), max_size=24), max_size=4))
def test_winnowing_finds_all_windows(doc, items):
    named = [(str(i), " ".join(x)) for i, x in enumerate(items)]
    hit, found = decontam.Index(named).hits(decontam.words(" ".join(doc)))
    n, n_hit, ids = brute_hits(" ".join(doc), named)
    assert (len(hit), int(hit.sum()), ",".join(sorted(found))) == (n, n_hit, ids)


@pytest.mark.parametrize("block", [decontam.BLOCK_CHARS, 400])
def test_decontamination_edges(spark, block):
    bench = [(1, " ".join(f"q{i}" for i in range(20))), (2, "short item Here"), (3, None), (4, ""), (2, "short item Here"), (None, "nothing at all"), (5, " ".join(f"w{i % 997} x{i % 89}." for i in range(20)))]
    docs = edge(spark).unionByName(spark.createDataFrame([(50, "so a SHORT-item; here! " + " ".join(f"q{i}" for i in range(3, 18)), None, None, 0)], DOCS), allowMissingColumns=True)
    b = spark.createDataFrame(bench, "item_id bigint, text string").withColumn("items", F.lit(1))
    got = Counter((r["doc_id"], r["n_words"], r["n_hit"], r["items_sha256"], r["contaminated"]) for r in decontam.report(decontam.hits(docs, b, block_chars=block)).collect())
    want = Counter()
    for r in docs.collect():
        n, h, ids = brute_hits(r["text"], [("" if i is None else i, t) for i, t in bench])
        want[(r["doc_id"], n, h, hashlib.sha256(ids.encode()).hexdigest(), h > 0 and 20 * h >= n)] += 1
    assert got == want
    assert decontam.report(decontam.hits(docs, b.where("item_id > 100"))).where("n_hit > 0").count() == 0
    assert decontam.hits(empty(spark), b).count() == 0


def test_repeated_and_long_items_spread(spark, monkeypatch):
    """Equal rows count once, and a long item is found through its pieces."""
    monkeypatch.setattr(decontam, "PIECE", 40)
    long = [f"z{i}" for i in range(500)]
    rows = [(1, "twice " * 20)] * 2000 + [(2, " ".join(long))]
    bench = spark.createDataFrame(rows, "item_id bigint, text string")
    docs = spark.createDataFrame([(i, " ".join(long[i : i + 30])) for i in range(0, 470, 7)] + [(900, "x " + "twice " * 14)], "doc_id bigint, text string")
    pieces = list(decontam._cut(iter([__import__("pyarrow").RecordBatch.from_pydict({"item": ["2"], "text": [" ".join(long)]})])))[0]
    assert pieces.num_rows == 13 and max(len(x.as_py().split()) for x in pieces.column(1)) == 52
    got = {r["doc_id"]: (r["n_hit"], r["n_items"]) for r in decontam.report(decontam.hits(docs, bench, block_chars=600)).collect()}
    assert got == {**{i: (30, 1) for i in range(0, 470, 7)}, 900: (14, 1)}


# ---------------------------------------------------------------------------------------------------- 10 urls


def test_url_parts_and_rules(spark):
    cases = {
        None: ("", "", None), "no-scheme.com/x": ("", "", None), "http://A.Example.NET/en/1?q#f": ("a.example.net", "/en/1", "example.net/en/"), "http://net/x": ("net", "/x", "net/"), "http://x.net": ("x.net", "", None),
        "http://x.net?a=/": ("x.net", "", None), "https://example.com/de/5#t": ("example.com", "/de/5", "example.com/de/"), "https://badexample.com/de/": ("badexample.com", "/de/", None), "s://b.org/fr/": ("b.org", "/fr/", "org/fr/"),
        "a://b://c/d": ("b:", "//c/d", None), "http://ÄX.org/fr/1": ("Äx.org", "/fr/1", "org/fr/"), "://": ("", "", None), "http://h/p?q://z": ("h", "/p", None),
    }
    rows = [(i, u, "<p>text</p>") for i, u in enumerate(cases)] + [(99, "http://x.net/1", None), (99, "http://x.net/1", None)]
    from cellcount.llm.queries import URL_RULES

    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("host", F.lit("clash")).withColumn("n", F.lit(1))
    got = {r["page_id"]: r for r in urls.judge(pages, URL_RULES).collect()}
    for i, want in enumerate(cases.values()):
        assert (got[i]["host"], got[i]["path"], got[i]["rule"]) == want, list(cases)[i]
    assert urls.judge(pages, URL_RULES).count() == len(rows) and urls.judge(pages.where("page_id < 0"), URL_RULES).count() == 0
    assert {r["verdict"] for r in urls.judge(pages, URL_RULES).where("rule = 'net/'").collect()} == {"block"}


def test_reputation_shrinks_towards_the_domain(spark):
    good, bad = "<p>" + "fine words " * 20, "<p>" + "###$$$ " * 40
    rows = [(i, f"http://bad.farm.com/{i}", bad) for i in range(60)] + [(100 + i, f"http://ok.site.org/{i}", good) for i in range(60)] + [(300, "http://new.farm.com/", good), (301, "http://new.site.org/", bad)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    v = {r["page_id"]: r for r in urls.judge(pages, ()).collect()}
    assert v[0]["verdict"] == "block" and v[100]["verdict"] == "allow" and v[301]["verdict"] == "allow"
    assert v[300]["p_bad"] > v[301]["p_bad"]


def test_posterior_of_a_rate(spark):
    rng = np.random.default_rng(3)
    rows = [(a, b, float((rng.beta(a, b, 200_000) > 0.5).mean())) for a, b in ((1.0, 1.0), (3.5, 2.0), (40.0, 60.0), (700.0, 650.0), (20_000.0, 19_000.0))]
    df = spark.createDataFrame(rows, "a double, b double, p double")
    for r in df.select("p", urls.above(F.col("a"), F.col("b"), 0.5).alias("got")).collect():
        assert abs(r["p"] - r["got"]) < 0.02
    groups = [(200.0, float(rng.binomial(200, rng.beta(0.3 * 30, 0.7 * 30))), 0.3) for _ in range(4000)]
    k = urls.strength(spark.createDataFrame(groups, "n double, bad double, mean double"), "n", "bad", "mean", "k").first()["k"]
    assert 26 < k < 34
    one = spark.createDataFrame([(1.0, 0.0, 0.3)] * 5, "n double, bad double, mean double")
    assert urls.strength(one, "n", "bad", "mean", "k").first()["k"] == urls.USUAL


def test_registered_domains(spark):
    hosts = {"a.b.co.uk": ("co.uk", "b.co.uk"), "co.uk": ("co.uk", "co.uk"), "x.y.z.com": ("com", "z.com"), "com": ("com", "com"), "": ("", "")}
    df = spark.createDataFrame([(h,) for h in hosts], "host string")
    assert {r["host"]: (r["s"], r["d"]) for r in df.select("host", urls.suffix_of(F.col("host")).alias("s"), urls.domain_of(F.col("host")).alias("d")).collect()} == hosts


# ---------------------------------------------------------------------------------------------------- pipeline


def test_pipeline_stages_against_brute_force(spark):
    import corpus_pipeline as pipe
    from cellcount.llm.common import stage

    assert [n for n, _ in pipe.STAGES] == ["toxicity", "minhash_near_dedup", "substring_dedup", "benchmark_decontamination", "packing"]
    docs, seen = spark.read.parquet(f"{TINY}/documents.parquet"), []
    for name, f in pipe.STAGES:
        before = docs
        docs = stage(f(spark, before, TINY), name)
        seen.append({r["doc_id"]: r for r in docs.collect()} if name != "packing" else None)
        if name != "packing":
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    tox, near, sub, clean = seen[:4]
    want = brute_components({i: r["text"] for i, r in tox.items()}, 80)
    assert set(near) == {i for i, c in want.items() if i == c}
    assert set(sub) <= set(near)
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{TINY}/benchmark.parquet").collect()]
    bad = {i for i, r in sub.items() if (h := brute_hits(r["text"], items))[1] and 20 * h[1] >= h[0]}
    assert set(clean) == set(sub) - bad
    assert {r["doc_id"] for r in docs.select("doc_id").distinct().collect()} == set(clean)
    rows = pipe.run(spark, TINY)
    assert rows.exceptAll(docs).count() == 0 and docs.exceptAll(rows).count() == 0


def test_pipeline_bands_fit_its_threshold(spark, monkeypatch):
    import corpus_pipeline as pipe

    seen, plain = [], neardup.near_components

    def spy(reps, items, numerator, denominator, n, bands, rows, *rest):
        seen.append((1 - (numerator / denominator) ** rows) ** bands)
        return plain(reps, items, numerator, denominator, n, bands, rows, *rest)

    monkeypatch.setattr(neardup, "near_components", spy)
    rows = edge(spark).select("doc_id", "text", "lang", "source", "n_chars")
    assert pipe.near_dedup_stage(spark, rows, TINY).count() == len(EDGE)
    assert len(seen) == 1 and seen[0] < 1e-5


def test_pipeline_stages_take_edge_cases(spark):
    import corpus_pipeline as pipe
    from cellcount.llm.common import stage

    for rows in (edge(spark).select("doc_id", "text", "lang", "source", "n_chars"), empty(spark).select("doc_id", "text", "lang", "source", "n_chars")):
        for name, f in pipe.STAGES:
            stage(f(spark, rows, TINY), name).count()


def test_words_of_a_column_equal_split_texts():
    """Pieces of a column, whatever its rows are, give each text's words and lines; equal words have equal hashes and others not."""
    from cellcount.llm import common

    rng = random.Random(11)
    alphabet = [" ", " ", "\n", "\t", "\x0b", "\x0c", "\r", "\x1c", "\xa0", "a", "B", "b", "ß", "É", "é", " ", "界", "😀", "0", "x" * 49]
    texts = ["", None, " ", "\n", "a", "A\n", "\na", " a b ", "x" * 48 + " " + "x" * 49 + " " + "X" * 49]
    texts += ["".join(rng.choices(alphabet, k=rng.randrange(60))) for _ in range(400)]
    texts += ["word " * 60_000 + "end", None, "a b", *["".join(rng.choices("ab", k=6)) + " " for _ in range(200)]]
    known, back = {}, {}
    for col in (pa.array(texts, pa.string()), pa.array(["skip", *texts, "skip"], pa.large_string()).slice(1, len(texts))):
        got = list(common.hashes_in(col))
        assert len(got) == len(texts)
        for t, h in zip(texts, got, strict=True):
            words = common.lower_ascii(t or "").split()
            assert len(words) == len(h) and np.array_equal(h, common.word_hashes(t))
            for w, x in zip(words, h.tolist(), strict=True):
                assert known.setdefault(w, x) == x and back.setdefault(x, w) == w
        lines = []
        for w in common.words_in(col):
            x = substring.Lines(w)
            ids = x.ids(w, np.arange(len(x.row)))
            lines += zip(x.row.tolist(), x.no.tolist(), x.start.tolist(), x.n_chars.tolist(), x.n_words.tolist(), ids.tolist(), strict=True)
        want, by_words = [], {}
        for row, t in enumerate(texts):
            at = no = 0
            for line in (t or "").split("\n"):
                if words := common.lower_ascii(line).split():
                    want.append((row, no, at, len(line), len(words)))
                    by_words.setdefault(tuple(words), set()).add(lines[len(want) - 1][5])
                    no += 1
                at += len(line) + 1
        assert [x[:5] for x in lines] == want
        assert all(len(x) == 1 for x in by_words.values()) and len({i for x in by_words.values() for i in x}) == len(by_words)
    assert list(common.hashes_in(pa.array([], pa.string()))) == []


def test_values_by_hashes():
    rng = np.random.default_rng(5)
    known = np.unique(rng.integers(-(1 << 63), 1 << 63, 3000))
    known = np.r_[known, np.arange(40) + (7 << 50)]  # many with equal leading bits
    found = lm._Lookup(known, np.arange(1, len(known) + 1))
    asked = rng.permutation(np.r_[known, rng.integers(-(1 << 63), 1 << 63, 3000)])
    want = {h: i for i, h in enumerate(known.tolist(), 1)}
    assert found(asked, np.zeros(len(asked), dtype=np.int64)).tolist() == [want.get(h, 0) for h in asked.tolist()]
    assert lm._Lookup(known[:0], known[:0])(asked, np.full(len(asked), -1)).tolist() == [-1] * len(asked)


def test_tasks_give_memory_back(spark):
    """The memos of a worker are empty between tasks, whichever operator filled them."""
    from cellcount.llm import common, neardup

    def run(batches):
        for b in batches:
            held = len(neardup._MEMO)
            neardup.shingles("a b c d e f g")
            yield pa.RecordBatch.from_arrays([pa.array([held] * len(b), pa.int64())], names=["held"])

    for _ in range(3):
        assert {r["held"] for r in common.arrow(spark.range(8).repartition(8), run, "held bigint").collect()} == {0}
