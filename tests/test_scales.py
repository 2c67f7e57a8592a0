"""Scales: values are in a range exactly if their ids are in the range's ids, by every quantizer."""

import random
from datetime import datetime, timedelta

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from pyspark.sql import types as T

from cellcount.functions.scales import Scale, build_scale, quantize, quantize_by_join, register_quantizer
from cellcount.plans.model import Interval, compare

ends = st.one_of(st.none(), st.integers(0, 12))


@st.composite
def intervals(draw):
    lo, hi = draw(ends), draw(ends)
    return Interval(lo, draw(st.booleans()) if lo is not None else False, hi, draw(st.booleans()) if hi is not None else False)


@settings(max_examples=400, deadline=None)
@given(st.lists(intervals(), min_size=1, max_size=8))
def test_quantization_preserves_selections(batch):
    scale = build_scale(batch)
    for x in [v / 2 for v in range(-2, 28)]:
        b = scale.quantize(x)
        for i in batch:
            if not i.empty:
                lo, hi = scale.id_range(i)
                assert i.holds(x) == (lo <= b <= hi)
        assert (b > 0) == any(i.holds(x) for i in batch)


def test_three_buckets():
    scale = build_scale([compare(">=", 3), compare("=", 7)])
    assert scale == Scale((3, 7), (0, 1, 1, 2, 3))
    assert scale.id_range(compare(">=", 3)) == (1, 3) and scale.id_range(compare("=", 7)) == (2, 2)
    assert [scale.quantize(x) for x in (2, 3, 5, 7, 8, None)] == [0, 1, 1, 2, 3, 0]


def _agree(spark, values, kind, batch):
    scale = build_scale(batch)
    df = spark.createDataFrame([(v,) for v in values], T.StructType([T.StructField("v", kind)]))
    got = df.select("v", *[quantize(F.col("v"), scale, i, kind).alias(i) for i in ("case", "arrow", "scan")]).collect()
    for r in got:
        want = 0 if r["v"] is None else scale.quantize(r["v"])
        assert (r["case"], r["arrow"], r["scan"]) == (want,) * 3, r
    for r in quantize_by_join(df, "v", scale, "range_join", "b").collect():
        assert r["b"] == (0 if r["v"] is None else scale.quantize(r["v"]))


def test_quantizers_agree_on_each_type(spark):
    rng = random.Random(1)
    pick = lambda values: [Interval(*sorted(rng.sample(values, 2))[:1], rng.random() < 0.5) if rng.random() < 0.5 else compare("=", rng.choice(values)) for _ in range(6)]
    longs = list(range(-5, 25))
    _agree(spark, [*longs, None], T.LongType(), pick(longs))
    doubles = [x / 4 for x in range(-8, 40)]
    _agree(spark, [*doubles, -0.0, None], T.DoubleType(), [*pick(doubles), compare("<=", 0.0)])
    words = ["", "a", "ab", "b", "ba", "é", "z", "zz"]
    _agree(spark, [*words, "aa", None], T.StringType(), pick(words))
    days = [datetime(2020, 1, 1) + timedelta(hours=7 * k) for k in range(20)]
    _agree(spark, [*days, None], T.TimestampNTZType(), pick(days))


def test_nan_is_above_all_numbers(spark):
    df = spark.createDataFrame([(float("nan"),), (1e300,), (None,)], "v double")
    scale = build_scale([compare(">", 5.0)])
    for impl in ("case", "arrow"):
        assert [r["b"] for r in df.select(quantize(F.col("v"), scale, impl, T.DoubleType()).alias("b")).collect()] == [1, 1, 0]


def test_quantizer_in_sql(spark):
    scale = build_scale([compare(">=", 3), compare("=", 7)])
    register_quantizer(spark, "quantize_demo", scale, T.LongType())
    got = spark.sql("SELECT id, quantize_demo(id) AS b FROM range(10)").collect()
    assert all(r["b"] == scale.quantize(r["id"]) for r in got)


def test_many_cuts_switch_to_binary_search(spark):
    scale = build_scale([compare("<", float(k)) for k in range(600)])
    df = spark.range(0, 700).select(F.col("id").cast("double").alias("v"))
    got = df.select("v", quantize(F.col("v"), scale, "auto", T.DoubleType()).alias("b"))
    assert "ArrowEvalPython" in got._jdf.queryExecution().executedPlan().toString()
    assert all(r["b"] == scale.quantize(r["v"]) for r in got.collect())
