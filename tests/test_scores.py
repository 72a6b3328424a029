"""Decisions, bins, metrics and their invariants, on fixtures worked by hand."""

import math

import duckdb
from pyspark.sql import functions as F

from factbench.functions.scores import bin_index, clip, decide, nearest_anchor, rounded
from factbench.operators import judges, metrics

EDGES = [-1.0, -1 / 3 - 1e-9, -1 / 3, 0.0, 1 / 3, 1 / 3 + 1e-9, 1.0]


def column(spark, values, *columns):
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i int, s double")
    return [tuple(r) if len(columns) > 1 else r[0] for r in df.orderBy("i").select(*columns).collect()]


def test_decisions_at_the_edges(spark):
    assert column(spark, EDGES, decide("s")) == ["negative", "negative", "unknown", "unknown", "unknown", "positive", "positive"]


def test_three_bins_are_the_decisions(spark):
    got = column(spark, EDGES, bin_index("s", 3), decide("s"))
    assert all({-1: "negative", 0: "unknown", 1: "positive"}[b] == d for b, d in got)


def test_seven_bins_fall_toward_zero(spark):
    assert column(spark, [-1.0, 5 / 7, -5 / 7, 3 / 7, -3 / 7, 1 / 7, -1 / 7, 0.0, 1.0], bin_index("s", 7)) == [-3, 2, -2, 1, -1, 0, 0, 0, 3]


def test_bins_are_symmetric_and_rise(spark):
    values = [i / 50 - 1 for i in range(101)]
    bins = column(spark, values, bin_index("s", 7))
    assert bins == sorted(bins) and bins == [-b for b in reversed(bins)]
    anchors = column(spark, values, nearest_anchor("s", 7))
    assert set(anchors) == set(range(-3, 4)) and anchors == sorted(anchors)


def test_clip_keeps_null(spark):
    assert column(spark, [None, 3.0, -3.0, 0.5], clip("s")) == [None, 1.0, -1.0, 0.5]


def measured(spark, pairs):
    df = spark.createDataFrame([(float(p), float(t)) for p, t in pairs], "score double, truth double")
    return metrics.evaluate(df).first().asDict()


def test_one_flip_in_a_hundred(spark):
    m = measured(spark, [(1, 1)] * 99 + [(1, -1)])
    assert (m["mse"], m["mae"], m["acc3"]) == (0.04, 0.02, 99.0)


def test_constant_zero_and_all_flipped(spark):
    assert measured(spark, [(0, 1), (0, -1)])["mse"] == 1.0
    assert measured(spark, [(1, -1), (-1, 1)])["mse"] == 4.0
    assert measured(spark, [(0.5, 0.5)])["acc7"] == 100.0


def test_bounds_and_decomposition(spark):
    pairs = [(math.sin(i), math.cos(3 * i)) for i in range(200)]
    m = measured(spark, pairs)
    assert m["mae"] ** 2 <= m["mse"] <= 2 * m["mae"] + 1e-6
    halves = [measured(spark, [p for p in pairs if (p[1] > 0) == side]) for side in (True, False)]
    assert abs(sum(h["n"] * h["mse"] for h in halves) / 200 - m["mse"]) < 1e-5


def test_confusion_totals(spark):
    df = spark.createDataFrame([(math.sin(i), math.cos(i)) for i in range(100)], "score double, truth double")
    rows = metrics.confusion(df, 3).collect()
    assert len(rows) == 9 and sum(r["count"] for r in rows) == 100
    assert abs(sum(r["count"] for r in rows if r["truth_bin"] == r["pred_bin"]) - metrics.evaluate(df).first()["acc3"]) < 1e-6


def test_unanswered_claims(spark):
    truth = spark.createDataFrame([(1, 1.0), (2, -1.0)], "claim_id long, truth double")
    pred = spark.createDataFrame([("a", 1, 1.0)], "system string, claim_id long, score double")
    assert metrics.evaluate(metrics.align(pred, truth, ["system"], "zero")).first()["mse"] == 0.5
    assert metrics.evaluate(metrics.align(pred, truth, ["system"])).first()["n"] == 1


def test_sanitize(spark):
    df = spark.createDataFrame([(float("nan"),), (7.0,), (None,)], "score double")
    assert [r[0] for r in metrics.sanitize(df).orderBy(F.col("score").desc_nulls_last()).collect()] == [1.0, None, None]


def test_rounding_is_that_of_sql(spark):
    # ties in the scaled double, negative scores that round to zero, and zeros
    values = [0.0, -0.0, -2.2e-16, -0.0003, 0.0003, -0.0005, 0.0005, 0.1115, -0.1115, 0.0235, 1.0, -1.0, 0.3335, 1.0005, 0.1234565, None]
    told = duckdb.sql("SELECT CAST(round(s, 3) AS VARCHAR), CAST(round(round(s, 6), 3) AS VARCHAR), round(s, 6) FROM (SELECT unnest($v)::DOUBLE AS s)", params={"v": values}).fetchall()
    got = column(spark, values, rounded("s", 3).cast("string"), rounded(rounded("s", 6), 3).cast("string"), rounded("s", 6))
    assert [tuple(map(repr, r)) for r in got] == [tuple(map(repr, r)) for r in told]
    assert got[3][0] == "-0.0" and got[4][0] == "0.0"


def test_justification_of_a_score_just_below_zero(spark):
    df = spark.createDataFrame([("J2", -0.0002), ("J3", 0.0002), ("J1", -0.38)], "member string, score double")
    assert [r[0] for r in df.select(judges.justified(F.col("member"), F.col("score"))).collect()] == ["J2 scores -0.0", "J3 scores 0.0", "J1 scores -0.38"]
