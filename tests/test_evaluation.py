"""Evidence, frames, cutoffs, people, updates, streams."""

import datetime
import math

import pytest
from pyspark.sql import functions as F

from factbench.operators import ablate, cutoff, evidence, frames, humaneval, insights, leaderboard
from factbench.plans import evaluation as plan_evaluation
from factbench.plans import streams as plan_streams
from factbench.plans import update
from factbench.sources import derived
from factbench.sources.io import load, write_split
from factbench.streaming import streams

T0 = datetime.datetime(2024, 1, 10)


def test_evidence_never_comes_later(spark):
    c = spark.createDataFrame([(1, 7, T0)], "claim_id long, k long, claim_ts timestamp_ntz")
    e = spark.createDataFrame([(i, 7, T0 + datetime.timedelta(seconds=s)) for i, s in ((1, 0), (2, 1), (3, -1))], "evidence_id long, k long, pub_ts timestamp_ntz")
    assert sorted(r["evidence_id"] for r in evidence.admissible(c, e, "k").collect()) == [1, 3]
    assert [r["evidence_id"] for r in evidence.admissible(c, e, "k", strict=True).collect()] == [3]
    assert evidence.newest(c, e, "k").first()["evidence_id"] == 1
    assert evidence.admissible_within(c.drop("k"), e.drop("k"), 1).count() == 2


def test_search_before_ranking_ignores_the_future(spark):
    c = spark.createDataFrame([(1, "red fox", T0)], "claim_id long, text string, claim_ts timestamp_ntz")
    docs = [(1, "red fox red fox", T0 + datetime.timedelta(1)), (2, "a red hen", T0), (3, "blue sea", T0)]
    d = spark.createDataFrame(docs, "doc_id long, text string, pub_ts timestamp_ntz")
    assert [r["doc_id"] for r in evidence.search(c, d, k=1).collect()] == [1]
    assert [r["doc_id"] for r in evidence.search(c, d, k=1, before=True).collect()] == [2]


def test_bm25_by_hand(spark):
    c = spark.createDataFrame([(1, "fox")], "claim_id long, text string")
    d = spark.createDataFrame([(1, "fox fox"), (2, "hen"), (3, "fox hen hen hen")], "doc_id long, text string")
    got = {r["doc_id"]: r["score"] for r in evidence.search(c, d).collect()}
    idf, mean = math.log(1 + (3 - 2 + 0.5) / 2.5), 7 / 3
    assert got == {k: round(idf * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * n / mean)), 6) for k, tf, n in ((1, 2, 2), (3, 1, 4))}


@pytest.mark.parametrize(("n", "want"), [(0, []), (1, [0]), (3, [0, 1, 2]), (5, [0, 1, 2, 3, 4]), (12, [1, 3, 6, 8, 10])])
def test_even_frames(spark, n, want):
    df = spark.createDataFrame([(1, i) for i in range(n)], "k long, o long")
    assert sorted(r["place"] for r in frames.even(df, "k", ["o"]).collect()) == want


def test_planted_cutoff_is_found(spark, medium):
    p = derived.predictions(spark, medium)
    rows = {r["system"]: r for r in cutoff.inflation(p.filter("not search")).collect()}
    assert all(r["inflation"] > 0 for r in rows.values())
    assert max(rows, key=lambda s: rows[s]["inflation"]) == "V2"
    board = leaderboard.search_gain(p.groupBy("system", "search").agg(F.avg(cutoff.squared()).alias("mse")))
    assert board.filter("system = 'V3'").first()["gain"] > 0


def test_wide_curve_is_the_global_error(spark, small):
    p = derived.predictions(spark, small).filter("not search")
    whole = {r["system"]: r["m"] for r in p.groupBy("system").agg(F.avg(cutoff.squared()).alias("m")).collect()}
    rows = cutoff.curve(p, half_width=100_000).collect()
    assert rows and all(abs(r["mse"] - whole[r["system"]]) < 2e-6 for r in rows)


def test_ablation_rows(spark, medium):
    from factbench.operators.judges import wide_votes

    votes = wide_votes(load(spark, medium, "documents", ["doc_id", "text"]))
    human = humaneval.truth(humaneval.annotations(load(spark, medium, "labels")))
    rows = {r["setting"]: r for r in humaneval.ablations(votes, human).collect()}
    assert rows["filtered"]["n"] < rows["unfiltered"]["n"]
    assert rows["filtered"]["mse"] < rows["unfiltered"]["mse"] < min(rows[f"J{i}"]["mse"] for i in range(1, 5))


def test_kappa_forms_agree(spark):
    pairs = spark.createDataFrame([(i % 3, (i * i) % 3) for i in range(60)], "a int, b int")
    counts = pairs.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))
    assert abs(humaneval.weighted_kappa(pairs, "a", "b").first()[0] - humaneval.kappa_by_counts(counts).first()[0]) < 1e-6


def test_runs_compared_with_themselves(spark):
    a = spark.createDataFrame([(1, 0.5), (2, -0.5)], "claim_id long, score double")
    r = ablate.compare_runs(a, a).first()
    assert (r["mse"], r["same_decision"], r["correlation"]) == (0.0, 1.0, 1.0)


def test_shares_fold_small_values(spark):
    df = spark.createDataFrame([("a",)] * 90 + [("b",)] * 6 + [("c",)] * 4, "v string")
    assert {r["v"]: r["percent"] for r in insights.shares(df, "v", 5.0).collect()} == {"a": 90.0, "b": 6.0, "other": 4.0}


def test_quarterly_append(spark, small, tmp_path):
    feed = derived.claims(spark, small).select("claim_id", "quarter", "veracity")
    q = str(feed.agg(F.min("quarter")).first()[0])
    total = feed.filter(F.col("quarter") == q).count()
    process = lambda df: df.withColumn("label", F.when(F.col("veracity") > 0, "intact").otherwise("compromised"))
    state = str(tmp_path)
    assert update.append_quarter(state, feed, q, process, limit=10) == total - 10
    assert update.append_quarter(state, feed, q, process) == 0
    assert update.append_quarter(state, feed, q, process) == 0
    out = spark.read.parquet(f"{state}/claims")
    assert out.count() == out.select("claim_id").distinct().count() == total
    nxt = str(feed.filter(F.col("quarter") > q).agg(F.min("quarter")).first()[0])
    update.append_quarter(state, feed, nxt, process)
    assert spark.read.parquet(f"{state}/claims").filter(F.col("quarter") == q).count() == total


def test_rewritten_split_replaces_its_quarter_only(spark, tmp_path):
    path = str(tmp_path / "split")
    df = spark.createDataFrame([(1, "a"), (2, "b")], "claim_id long, quarter string")
    write_split(df, path)
    write_split(df.filter("quarter = 'b'"), path)
    assert spark.read.parquet(path).count() == 2


def arrivals(spark, tmp_path, frames_):
    folder = tmp_path / "in"
    for n, rows in enumerate(frames_):
        spark.createDataFrame(rows, "claim_id long, claim_ts timestamp, label string").coalesce(1).write.mode("append").parquet(str(folder))
    return str(folder)


def test_quota_doesnt_depend_on_arrival(spark, tmp_path):
    ts = datetime.datetime(2024, 2, 1)
    rows = [(i, ts + datetime.timedelta(hours=i), "intact" if i % 2 else "compromised") for i in range(60)]
    schema = "claim_id long, claim_ts timestamp, label string"
    folder = arrivals(spark, tmp_path, [rows[40:], rows[:20], rows[20:40]])
    stream = streams.files(spark, folder, schema, files_per_trigger=1)
    streams.quota_sink(stream, str(tmp_path / "out"), str(tmp_path / "c1"), 5)
    stored = {r["claim_id"] for r in spark.read.parquet(str(tmp_path / "out" / "split")).collect()}
    from factbench.operators.splits import ranked

    batch = spark.createDataFrame(rows, schema).withColumn("quarter", F.to_date(F.lit("2024-01-01")))
    assert stored == {r["claim_id"] for r in ranked(batch).filter("rank <= 5").collect()}


def test_stateful_quota(spark, tmp_path):
    ts = datetime.datetime(2024, 2, 1)
    rows = [(i, ts + datetime.timedelta(hours=i), "intact") for i in range(40)]
    schema = "claim_id long, claim_ts timestamp, label string"
    folder = arrivals(spark, tmp_path, [rows[20:], rows[:20]])
    out = streams.quota(streams.files(spark, folder, schema, files_per_trigger=1), 5)
    streams.run_once(out, str(tmp_path / "out"), str(tmp_path / "c2"))
    held = spark.read.parquet(str(tmp_path / "out")).groupBy("claim_id").agg(F.sum(F.when(F.col("added"), 1).otherwise(-1)).alias("n")).filter("n > 0")
    from factbench.operators.splits import ranked

    batch = spark.createDataFrame(rows, schema).withColumn("quarter", F.to_date(F.lit("2024-01-01")))
    assert {r["claim_id"] for r in held.collect()} == {r["claim_id"] for r in ranked(batch).filter("rank <= 5").collect()}


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    base = datetime.datetime(2024, 2, 1)
    folder = str(tmp_path / "in")
    for day in (10, 20, 1):
        df = spark.createDataFrame([(day, base + datetime.timedelta(days=day))], "id long, ts timestamp")
        df.coalesce(1).write.mode("append").parquet(folder)
    import os

    for n, f in enumerate(sorted((f for f in os.listdir(folder) if f.endswith(".parquet")), key=lambda f: os.path.getmtime(f"{folder}/{f}"))):
        os.utime(f"{folder}/{f}", (1_700_000_000 + n * 10,) * 2)
    counted = streams.volume(streams.files(spark, folder, "id long, ts timestamp", 1), "ts", "1 day", "1 day")
    query = streams.run_once(counted, str(tmp_path / "out"), str(tmp_path / "c3"))
    assert streams.late_rows(query) == 1


def test_sources_and_sinks_round_trip(spark, small, tmp_path):
    from factbench.sources import io

    df = load(spark, small, "nation")
    io.write_json(df, str(tmp_path / "j"))
    io.write_csv(df, str(tmp_path / "c"))
    assert io.read_json(spark, str(tmp_path / "j"), df.schema).exceptAll(df).count() == 0
    assert io.read_csv(spark, str(tmp_path / "c"), df.schema).exceptAll(df).count() == 0
    assert io.read_lines(spark, str(tmp_path / "j")).columns == ["raw"]
    with pytest.raises(ValueError, match="no table"):
        load(spark, small, "nothing")


def test_credible_stream(spark, tmp_path):
    spark.createDataFrame([("x.org", 1), ("y.com", 2)], "publisher string, n int").write.parquet(str(tmp_path / "in"))
    listed = spark.createDataFrame([("x.org",)], "publisher string")
    streams.run_once(streams.credible(streams.files(spark, str(tmp_path / "in"), "publisher string, n int"), listed), str(tmp_path / "out"), str(tmp_path / "c4"))
    assert [r["n"] for r in spark.read.parquet(str(tmp_path / "out")).collect()] == [1]


def test_counts_within_are_those_of_pairs(spark):
    at = lambda h, us=0: T0 + datetime.timedelta(hours=h, microseconds=us)
    c = spark.createDataFrame([(1, at(0)), (2, at(24)), (3, at(24, -1)), (4, at(24, 1)), (5, at(500)), (6, None), (7, at(-900)), (2, at(30)), (8, at(12))], "claim_id long, claim_ts timestamp_ntz")
    e = spark.createDataFrame([(i, t) for i, t in enumerate([at(0), at(0), at(0, 1), at(23), at(24), at(36), at(-3), None, at(499), at(-1000)])], "evidence_id long, pub_ts timestamp_ntz")
    for days in (1, 3):
        pairs = evidence.admissible_within(c, e, days).groupBy("claim_id").count().collect()
        got = evidence.count_within(c, e, days)
        assert {r["claim_id"]: r["n"] for r in got.collect()} == {r["claim_id"]: r["count"] for r in pairs} and got.count() == len(pairs)
    assert evidence.count_within(c.limit(0), e, 1).count() == evidence.count_within(c, e.limit(0), 1).count() == 0


def test_counting_within_a_day_makes_no_pairs(spark, small):
    p = plan_evaluation.evidence_within_day(spark, small)._jdf.queryExecution().optimizedPlan().toString()
    # the one join is to a row a day: claims and evidence meet in one sorted pass
    assert p.count("Join ") == 1 and "Window" in p


def test_first_of_equal_events_in_any_order_of_arrival(spark, tmp_path):
    day = lambda n: datetime.datetime(2024, 1, 1) + datetime.timedelta(days=n)
    late = [(1, day(9), 1, "view"), (2, day(4), 2, "view"), (3, None, 3, "view"), (4, day(5), 1, "click"), (9, day(2), 4, "view")]
    early = [(5, day(3), 1, "view"), (6, day(4), 3, "view"), (7, day(800), 2, "view"), (8, day(2), 4, "view")]
    for rows in (late, early):
        spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string").coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    assert {r["event_id"] for r in plan_streams.stream_dedup(spark, str(tmp_path)).collect()} == {5, 2, 6, 4, 8}
