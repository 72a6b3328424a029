"""Verdicts, ensembles, rectification and splits: worked cases and invariants."""

import itertools

import __spark_entry__ as entry
import oracle
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from factbench.operators import ensemble, judges, rectify, splits, verdict
from factbench.sources import derived

CLAIMS = "claim_id long, veracity double, coverage double"
MEDIA = "claim_id long, authenticity double, contextualization double"


def told(spark, ver, cov, media=(), **options):
    c = spark.createDataFrame([(1, ver, cov)], CLAIMS)
    m = spark.createDataFrame([(1, a, x) for a, x in media], MEDIA)
    return verdict.verdicts(c, m, **options).first()


def test_text_only_claim(spark):
    r = told(spark, 0.8, 0.6)
    assert (r["integrity"], r["compromising"], r["contextualization"], r["label"]) == (0.6, "coverage", None, "intact")


def test_bad_media_end_evaluation(spark):
    r = told(spark, -0.9, -0.9, [(0.9, 0.9), (0.9, -0.5)])
    assert (r["integrity"], r["veracity"], r["coverage"]) == (-0.5, None, None)


def test_bad_veracity_ends_evaluation(spark):
    r = told(spark, -0.4, -1.0, [(1.0, 0.9)])
    assert (r["integrity"], r["coverage"], r["compromising"]) == (-0.4, None, "veracity")


def test_cherry_picked(spark):
    r = told(spark, 0.9, -0.8, [(1.0, 0.9)])
    assert (r["integrity"], r["compromising"]) == (-0.8, "coverage")


def test_labelled_generated_media_stay_intact(spark):
    assert told(spark, 0.9, 0.9, [(-1.0, 0.9)])["integrity"] == 0.9


def test_ties_go_to_the_earliest(spark):
    assert told(spark, 0.5, 0.5, [(0.0, 0.5)])["compromising"] == "contextualization"


def test_early_stop_never_changes_labels(spark, small):
    c, m = derived.claims(spark, small), derived.claim_media(spark, small)
    early, full = (verdict.verdicts(c, m, early_stop=e).select("claim_id", F.col("integrity").alias(f"i{e}"), F.col("label").alias(f"l{e}")) for e in (True, False))
    both = early.join(full, "claim_id")
    assert both.filter("lTrue != lFalse").count() == 0
    assert both.filter("iFalse > iTrue or (iFalse < iTrue and not (iTrue < -1.0/3 and iFalse < -1.0/3))").count() == 0


def votes(spark, scores):
    return spark.createDataFrame([(1, f"J{i}", float(s), f"text {i}") for i, s in enumerate(scores, 1)], "claim_id long, member string, score double, justification string")


@pytest.mark.parametrize(("scores", "kept"), [((0, 0, 0, 1), True), ((-0.1, 0, 0, 1), False), ((0.3,) * 4, True)])
def test_spread(spark, scores, kept):
    assert (ensemble.filter_agreement(ensemble.combine(votes(spark, scores), ["claim_id"])).count() == 1) == kept


def test_justification_is_nearest_to_mean(spark):
    assert ensemble.justify(votes(spark, (0.0, 0.4, 0.5, 1.0)), ["claim_id"]).first()["justification"] == "text 3"


def test_mean_of_mins_never_exceeds_min_of_means(spark):
    rows = [(c, f"J{k}", ((c * k * 31) % 21 - 10) / 10.0, ((c * k * 17) % 21 - 10) / 10.0, ((c + k * 7) % 21 - 10) / 10.0) for c in range(50) for k in range(1, 5)]
    df = spark.createDataFrame(rows, "claim_id long, member string, contextualization double, veracity double, coverage double")
    a = ensemble.integrity_votes(df, gate="none").select("claim_id", F.col("integrity").alias("min_of_means"))
    b = ensemble.integrity_votes(df, order="min_then_mean", gate="none").select("claim_id", F.col("integrity").alias("mean_of_mins"))
    assert a.join(b, "claim_id").filter("mean_of_mins > min_of_means + 1e-6").count() == 0


@pytest.mark.parametrize(
    ("consistent", "shareable", "integrity", "spread", "outcome"),
    [(True, True, 0.34, 0.5, "accepted"), (True, True, 1 / 3, 0.5, "not intact"), (True, True, 0.9, 1.2, "low agreement"), (False, True, 0.9, 0.1, "inconsistent"), (True, False, 0.9, 0.1, "not shareable"), (True, True, None, None, "not intact")],
)
def test_twins(spark, consistent, shareable, integrity, spread, outcome):
    df = spark.createDataFrame([(1, consistent, shareable, integrity, spread)], "claim_id long, consistent boolean, shareable boolean, twin_integrity double, twin_spread double")
    assert rectify.decided(df).first()["outcome"] == outcome


def test_replacement_keeps_every_claim_once(spark, small):
    from factbench.plans.construction import _final, _twins

    twins, out = _twins(spark, small).persist(), _final(spark, small, half=False).persist()
    assert out.count() == out.select("claim_id").distinct().count() == 1500
    assert out.filter("rectified and not (integrity > 1.0/3)").count() == 0
    assert out.filter("rectified").count() == twins.filter("outcome = 'accepted'").count() > 100
    assert {r[0] for r in twins.select("outcome").distinct().collect()} == {"accepted", "not intact", "low agreement", "inconsistent", "not shareable"}
    assert twins.filter("outcome in ('inconsistent', 'not shareable') and twin_integrity is not null").count() == 0  # never scored


def test_twins_follow_the_justification(spark):
    rows = [(1, "It rained\nIt rained\n#### $$$$", "coverage", "forgot the sun"), (2, "It rained", "veracity", "no"), (3, "It rained", "contextualization", None)]
    df = spark.createDataFrame(rows, "claim_id long, text string, compromising string, justification string")
    assert {r["claim_id"]: r["twin_text"] for r in rectify.generate(df).collect()} == {1: "With what was left out: It rained (forgot the sun)", 2: "In fact: It rained", 3: "Seen in its context: It rained"}


def test_justification_of_integrity(spark):
    names = ("contextualization", "veracity", "coverage")
    given = {"J1": (0.9, -0.1, 0.5), "J2": (0.8, -0.6, 0.5), "J3": (0.9, -0.5, None), "J4": (0.9, -0.9, 0.7)}
    rows = [(1, m, p, s, f"{m} on {p}") for m, scores in given.items() for p, s in zip(names, scores, strict=True)]
    long = spark.createDataFrame(rows, "claim_id long, member string, property string, score double, justification string")
    wide = spark.createDataFrame([(1, m, *s) for m, s in given.items()], "claim_id long, member string, contextualization double, veracity double, coverage double")
    row = ensemble.justify_integrity(ensemble.standardize(wide), ensemble.justify_properties(long)).first()
    assert (row["compromising"], row["label"], row["integrity"], row["spread"], row["coverage"]) == ("veracity", "compromised", -0.525, 0.8, None)
    assert row["justification"] == row["veracity_justification"] == "J3 on veracity" and row["contextualization_justification"] == "J1 on contextualization"
    summed = ensemble.justify_properties(long, lambda texts, scores: F.concat_ws("; ", F.array_join(texts, ","), F.size(scores).cast("string"))).first()
    assert summed["coverage_justification"] == "J1 on coverage,J2 on coverage,J4 on coverage; 3"


def test_wide_votes_are_the_long_ones(spark, small):
    from factbench.sources.io import load

    docs = load(spark, small, "documents", ["doc_id", "text"])
    wide = judges.wide_votes(docs)
    a = ensemble.combine_wide(wide, ["J1", "J2", "J3", "J4"]).select("claim_id", "mean", "low", "high", "n_votes", "spread", "complete")
    b = ensemble.combine(judges.local_votes(docs), ["claim_id"]).select("claim_id", "mean", "low", "high", "n_votes", "spread", "complete")
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    some = spark.createDataFrame([(1, 0.5, None), (2, None, None)], "claim_id long, J1 double, J2 double")
    got = {r["claim_id"]: (r["mean"], r["n_votes"], r["complete"]) for r in ensemble.combine_wide(some, ["J1", "J2"]).collect()}
    assert got == {1: (0.5, 1, False), 2: (None, 0, False)}


def labelled(spark, n=400):
    rows = [(i, f"20{20 + i % 2}-0{1 + 3 * (i % 3)}-01", "intact" if i % 5 == 0 else "compromised") for i in range(n)]
    return spark.createDataFrame(rows, "claim_id long, quarter string, label string").withColumn("quarter", F.to_date("quarter"))


def test_balanced_split(spark):
    df = labelled(spark)
    out = splits.balanced(df, 20)
    counts = {(r["quarter"], r["label"]): r["count"] for r in out.groupBy("quarter", "label").count().collect()}
    assert set(counts.values()) == {10} and len(counts) == 12
    again = splits.balanced(df.repartition(7), 20)
    assert out.select("claim_id").exceptAll(again.select("claim_id")).count() == 0
    assert splits.longitudinal(df, 4).select("claim_id").exceptAll(out.select("claim_id")).count() == 0


def test_scarce_quarters_are_left_out(spark):
    df = labelled(spark).filter("label != 'intact' or quarter > date'2020-01-01' or claim_id < 90")
    scarce = df.filter("quarter = date'2020-01-01' and label = 'intact'").count()
    assert scarce < 10
    assert splits.balanced(df, 20).select("quarter").distinct().count() == 5
    assert splits.eligible(df, 10).filter("not eligible").count() == 1


def test_staged_scorers_see_survivors_only(spark):
    df = spark.createDataFrame([(i, i / 10 - 0.5) for i in range(10)], "claim_id long, x double").coalesce(1)
    calls = spark.sparkContext.accumulator(0)
    scorer = lambda frame: frame.assign(score=frame["x"], justification="")
    out = judges.staged(df, [("veracity", scorer), ("coverage", scorer)], "claim_id", lambda d: d.persist(), calls=calls)
    rows = {r["claim_id"]: r for r in out.collect()}
    assert calls.value == 10 + 8
    assert rows[0]["coverage"] is None and rows[9]["coverage"] == 0.4


def test_failing_scorer_is_a_result(spark):
    df = spark.createDataFrame([(1,)], "claim_id long")

    def broken(frame):
        raise RuntimeError("no model")

    row = judges.scored(df, broken, "J1").first()
    assert row["score"] is None and "no model" in row["failure"]


@pytest.mark.parametrize(
    ("out", "told"),
    [
        ({"claim": "string"}, {"claim": "A B"}), ({"reasons": "array<string>"}, {"reasons": ["too long"]}), ({"summary": "string"}, {"summary": "in short"}), ({"relevant": "boolean"}, {"relevant": True}),
        ({"start": "long", "end": "long"}, {"start": 1, "end": 2}), ({"urls": "array<string>"}, {"urls": ["u", "v"]}), ({"score": "double", "justification": "string"}, {"score": 0.5, "justification": "so"}),
    ],
)
def test_every_interface_binds_in_batches(spark, out, told):
    df = spark.createDataFrame([(i, f"text {i}", "spare") for i in range(5)], "claim_id long, text string, other string")

    def model(frame):
        assert list(frame.columns) == ["claim_id", "text"]
        result = frame[["claim_id"]].copy()
        for name, value in told.items():
            result[name] = [value] * len(frame)
        return result

    rows = judges.in_batches(df, model, out, ["text"]).collect()
    assert len(rows) == 5 and all({**told, "failure": None} == {k: r[k] for k in (*told, "failure")} for r in rows)

    def broken(frame):
        raise RuntimeError("no model")

    rows = judges.in_batches(df, broken, out, ["text"], attempts=3).collect()
    assert all(r["failure"] == "attempt 3: no model" and all(r[k] is None for k in told) for r in rows)


def test_a_batch_judge_keeps_relevant_media(spark):
    df = spark.createDataFrame([(1, "cat"), (2, "dog"), (3, "cat")], "media_id long, what string")
    kept, failed = judges.judged(df, lambda frame: frame.assign(relevant=frame["what"] == "cat"), ["what"])
    assert sorted(r["media_id"] for r in kept.collect()) == [1, 3] and failed.count() == 0


def test_mean_over_media_adds_in_the_given_order(spark):
    """Sums of the same scores in all orders differ in the last bit; each claim gets that of its own order, however its rows are dealt."""
    scores = {i: xs for i, xs in enumerate(itertools.permutations([-0.4, 0.2, 0.4, 0.6, 0.8, 0.4]))} | {-1: (None, 0.2, None), -2: (None, None)}
    rows = [(claim, x, x, n) for claim, xs in scores.items() for n, x in enumerate(xs)]
    df = spark.createDataFrame(rows, MEDIA + ", n long").repartition(7, "contextualization")
    got = {r["claim_id"]: (r["authenticity"], r["contextualization"], r["n_media"]) for r in verdict.over_media(df, "mean", ["n"]).collect()}
    want = {}
    for claim, xs in scores.items():
        total, known = 0.0, [x for x in xs if x is not None]
        for x in known:
            total += x
        mean = total / len(known) if known else None
        want[claim] = (mean, mean, len(xs))
    assert got == want and len({m for m, _, _ in want.values()}) > 3


def test_mean_over_media_of_several_files_follows_their_rows(spark, medium, tmp_path):
    """The query gives what its SQL gives on one thread, where the claims' rows lie in files of unlike sizes."""
    name = "verdict_mean_over_media"
    rows, cuts = pq.read_table(f"{medium}/lineitem.parquet"), (0, 4_000, 11_000, 25_000, 26_000, 41_000, 60_000)
    (tmp_path / "lineitem.parquet").mkdir()
    for n, (a, b) in enumerate(zip(cuts, cuts[1:])):
        pq.write_table(rows.slice(a, b - a), tmp_path / "lineitem.parquet" / f"part-{n}.parquet")
    (tmp_path / "orders.parquet").symlink_to(f"{medium}/orders.parquet")
    duck = oracle.connect(medium)
    duck.execute("SET threads = 1")
    duck.execute(f"CREATE OR REPLACE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    theirs = duck.execute(entry.oracle_sql()[name]).df()
    assert oracle.rows(entry.queries()[name](spark, str(tmp_path)).toPandas()) == oracle.rows(theirs)
