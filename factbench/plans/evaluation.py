"""Workloads of the evaluation layer over the given tables; SQL beside each that SQL can express."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from factbench.functions import text
from factbench.functions.scores import band, bin_index, coarse_label, flip_equivalent, nearest_anchor
from factbench.operators import ablate, baselines, cutoff, evidence, frames, funnel, humaneval, insights, judges, leaderboard, metrics, splits
from factbench.operators.ensemble import combine_wide
from factbench.plans.construction import ARTICLE, HOSTS, SCORERS, VERDICTS, _documents, _ensemble, _verdicts, _wide
from factbench.sources import derived
from factbench.sources.io import load, small

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


def _b(c: str, n: int) -> str:
    """SQL of the bin index."""
    edges = [f"({2 * k - 1}::DOUBLE / {n})" for k in range(1, (n - 1) // 2 + 1)]
    return "(" + " + ".join(f"(({c} > {e})::INT - ({c} < -{e})::INT)" for e in edges) + ")"


def _m(p: str = "score", t: str = "truth") -> str:
    """SQL of the measures."""
    return f"""count({p} - {t}) AS n, round(avg(({p} - {t}) * ({p} - {t})), 6) AS mse, round(avg(abs({p} - {t})), 6) AS mae,
round(100.0::DOUBLE * avg(({_b(p, 7)} = {_b(t, 7)})::INT::DOUBLE), 6) AS acc7, round(100.0::DOUBLE * avg(({_b(p, 3)} = {_b(t, 3)})::INT::DOUBLE), 6) AS acc3"""


# people

HUMAN = """ann AS (SELECT doc_id AS claim_id, unnest(['H1', 'H2']) AS annotator, unnest([2.0::DOUBLE * quality - 1, 1 - 2.0::DOUBLE * toxic]) AS score FROM labels),
human AS (SELECT claim_id, avg(score) AS truth FROM ann GROUP BY 1 HAVING count(DISTINCT annotator) >= 2)"""
SETTINGS = f"""{SCORERS}, {HUMAN}, mean_ AS (SELECT doc_id AS claim_id, ("J1" + "J2" + "J3" + "J4") / 4 AS mean, round(greatest("J1", "J2", "J3", "J4") - least("J1", "J2", "J3", "J4"), 6) AS spread, "J1", "J2", "J3", "J4" FROM wide),
settings AS (SELECT claim_id, 'filtered' AS setting, mean AS score FROM mean_ WHERE spread <= 1 UNION ALL SELECT claim_id, 'unfiltered', mean FROM mean_ UNION ALL SELECT claim_id, 'J1', "J1" FROM mean_
UNION ALL SELECT claim_id, 'J2', "J2" FROM mean_ UNION ALL SELECT claim_id, 'J3', "J3" FROM mean_ UNION ALL SELECT claim_id, 'J4', "J4" FROM mean_)"""


def _annotations(spark: SparkSession, d: str):
    return humaneval.annotations(load(spark, d, "labels"))


def _human(spark, d, **options):
    return humaneval.truth(_annotations(spark, d), **options)


def _ensemble_truth(spark, d):
    """Unfiltered ensemble scores beside human truths."""
    return _ensemble(spark, d).select("claim_id", F.col("mean").alias("score")).join(_human(spark, d), "claim_id")


@query(f"WITH {SETTINGS} SELECT setting, {_m()} FROM settings JOIN human USING (claim_id) GROUP BY setting")
def human_eval_ablations(spark, d):
    return humaneval.ablations(_wide(spark, d), _human(spark, d))


@query(f"WITH {SETTINGS}, least_ AS (SELECT claim_id, min(score) AS truth FROM ann GROUP BY 1) SELECT setting, {_m()} FROM settings JOIN least_ USING (claim_id) GROUP BY setting")
def human_eval_min_truth(spark, d):
    return humaneval.ablations(_wide(spark, d), _human(spark, d, how="min"))


def _confusion_sql(n: int) -> str:
    half = (n - 1) // 2
    return f"""WITH {SCORERS}, {HUMAN}, e AS (SELECT mean AS score, truth FROM ens JOIN human USING (claim_id)), c AS (SELECT {_b('truth', n)} AS t, {_b('score', n)} AS p, count(*) AS k FROM e GROUP BY 1, 2),
d AS (SELECT t.i AS truth_bin, p.i AS pred_bin, coalesce(k, 0) AS count FROM range({-half}, {half + 1}) t(i) CROSS JOIN range({-half}, {half + 1}) p(i) LEFT JOIN c ON c.t = t.i AND c.p = p.i)
SELECT CAST(truth_bin AS INTEGER) AS truth_bin, CAST(pred_bin AS INTEGER) AS pred_bin, count, CASE WHEN sum(count) OVER (PARTITION BY truth_bin) > 0 THEN round(100.0::DOUBLE * count / sum(count) OVER (PARTITION BY truth_bin), 6) END AS row_percent FROM d"""


@query(_confusion_sql(3))
def human_confusion3(spark, d):
    return metrics.confusion(_ensemble_truth(spark, d), 3)


@query(_confusion_sql(7))
def human_confusion7(spark, d):
    return metrics.confusion(_ensemble_truth(spark, d), 7)


@query(f"""WITH {SCORERS}, {HUMAN}, e AS (SELECT {_b('truth', 3)} AS truth_bin, {_b('mean', 3)} AS p FROM ens JOIN human USING (claim_id))
SELECT truth_bin, sum((p = -1)::INT)::BIGINT AS "-1", sum((p = 0)::INT)::BIGINT AS "0", sum((p = 1)::INT)::BIGINT AS "1" FROM e GROUP BY 1 UNION ALL SELECT i, 0, 0, 0 FROM (VALUES (-1), (0), (1)) v(i) WHERE i NOT IN (SELECT truth_bin FROM e)""")
def human_confusion_wide(spark, d):
    return metrics.confusion_wide(_ensemble_truth(spark, d), 3)


@query(f"WITH {SCORERS}, {HUMAN} SELECT CASE annotator WHEN 'H1' THEN 'quality' ELSE 'toxicity' END AS property, {_m('mean', 'a.score')} FROM ens JOIN ann a USING (claim_id) GROUP BY 1")
def human_properties(spark, d):
    votes = _ensemble(spark, d).select("claim_id", F.col("mean").alias("score"))
    return metrics.by_property(votes.join(_annotations(spark, d).select("claim_id", "property", F.col("score").alias("truth")), "claim_id"))


@query(f"WITH {HUMAN} SELECT a.annotator AS first, b.annotator AS second, {_m('a.score', 'b.score')} FROM ann a JOIN ann b ON a.claim_id = b.claim_id AND a.annotator < b.annotator GROUP BY 1, 2")
def human_pair_agreement(spark, d):
    return humaneval.pair_agreement(_annotations(spark, d))


@query("""WITH p AS (SELECT quality AS a, 1 - toxic AS b, count(*) AS n FROM labels GROUP BY 1, 2), r AS (SELECT a AS ra, sum(n) AS rn FROM p GROUP BY 1), c AS (SELECT b AS cb, sum(n) AS cn FROM p GROUP BY 1)
SELECT round(1 - (SELECT sum(n * (a - b) * (a - b)) * sum(n) FROM p)::DOUBLE / (SELECT sum(rn * cn * (ra - cb) * (ra - cb)) FROM r, c)::DOUBLE, 6) AS kappa""")
def human_kappa(spark, d):
    counts = load(spark, d, "labels").groupBy(F.col("quality").alias("a"), (1 - F.col("toxic")).alias("b")).agg(F.count(F.lit(1)).alias("n"))
    return humaneval.kappa_by_counts(counts, n=2)


@query("""WITH p AS (SELECT quality AS a, 1 - toxic AS b, count(*) AS n FROM labels GROUP BY 1, 2), r AS (SELECT a AS ra, sum(n) AS rn FROM p GROUP BY 1), c AS (SELECT b AS cb, sum(n) AS cn FROM p GROUP BY 1)
SELECT round(1 - (SELECT sum(n * (a - b) * (a - b)) * sum(n) FROM p)::DOUBLE / (SELECT sum(rn * cn * (ra - cb) * (ra - cb)) FROM r, c)::DOUBLE, 6) AS kappa""")
def human_kappa_udaf(spark, d):
    pairs = load(spark, d, "labels").select(F.col("quality").alias("a"), (1 - F.col("toxic")).alias("b"))
    return humaneval.weighted_kappa(pairs, "a", "b", n=2).select(F.round("kappa", 6).alias("kappa"))


@query(f"""WITH {SCORERS}, {HUMAN}, e AS (SELECT mean AS score, spread, truth FROM ens JOIN human USING (claim_id)), t AS (SELECT unnest([0.25::DOUBLE, 0.5, 0.75, 1.0, 1.25, 1.5, 1.75, 2.0]) AS threshold)
SELECT threshold, round(avg((spread <= threshold)::INT::DOUBLE), 6) AS kept_share, round(avg(CASE WHEN spread <= threshold THEN (score - truth) * (score - truth) END), 6) AS mse FROM e, t GROUP BY 1""")
def human_spread_sweep(spark, d):
    return humaneval.sweep(_wide(spark, d), _human(spark, d))


@query("SELECT round(100.0::DOUBLE * avg(toxic), 6) AS flagged_percent, count(*) AS n FROM labels")
def human_flag_rate(spark, d):
    return humaneval.flag_rate(load(spark, d, "labels"), "toxic")


@query(f"WITH {SCORERS} SELECT quantile_disc(spread, 0.25) AS q25, quantile_disc(spread, 0.5) AS q50, quantile_disc(spread, 0.75) AS q75 FROM ens")
def ensemble_spread_quantiles(spark, d):
    return insights.spread_quantiles(_ensemble(spark, d))


# systems

_VALUES = ", ".join(f"('{s}', {n}, {a}::DOUBLE, {b}::DOUBLE, {c}::DOUBLE, {e}::DOUBLE, TIMESTAMP '{t}')" for s, n, a, b, c, e, t in derived.SYSTEMS)
PRED = f"""systems(system, number, before_, after_, searched, noise, cutoff) AS (VALUES {_VALUES}),
pred0 AS (SELECT s.system, a.search, o_orderkey AS claim_id, o_orderdate AS claim_ts, CAST(date_trunc('quarter', o_orderdate) AS DATE) AS quarter, CASE WHEN (o_orderkey * 104729) % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS truth, o_custkey % 5 < 2 AS english, s.cutoff,
  CASE WHEN a.search THEN searched WHEN o_orderdate < cutoff THEN before_ ELSE after_ END AS fit, (((o_orderkey + number * 31 + CASE WHEN a.search THEN 17 ELSE 0 END) * 7919) % 2001 - 1000) / 997.0::DOUBLE * noise AS dev
  FROM orders, systems s, (VALUES (false), (true)) a(search)),
pred AS (SELECT system, search, claim_id, claim_ts, quarter, truth, english, cutoff, round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, truth * fit + dev - 0.05::DOUBLE)), 9) AS score FROM pred0)"""
_AGENTS = ", ".join(f"('{s}', {n}, {f}::DOUBLE, {e}::DOUBLE, {b}::DOUBLE)" for s, n, f, e, b in derived.AGENTS)
ALL = f"""{PRED}, agents(system, number, fit, noise, lean) AS (VALUES {_AGENTS}),
every AS (SELECT *, CASE WHEN search THEN 'search' ELSE 'parametric' END AS block FROM (SELECT system, search, claim_id, quarter, truth, english, score FROM pred)
UNION ALL SELECT a.system, true, o_orderkey, CAST(date_trunc('quarter', o_orderdate) AS DATE), CASE WHEN (o_orderkey * 104729) % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS t, o_custkey % 5 < 2,
  round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, t * fit + (((o_orderkey + number * 31 + 17) * 7919) % 2001 - 1000) / 997.0::DOUBLE * noise - lean)), 9), 'agent' FROM orders, agents a),
late_all AS (SELECT * FROM every WHERE quarter = (SELECT max(quarter) FROM every)), full_board AS (SELECT system, block, {_m()} FROM late_all GROUP BY 1, 2)"""
LATEST = f"{PRED}, late AS (SELECT * FROM pred WHERE quarter = (SELECT max(quarter) FROM pred)), board AS (SELECT system, search, {_m()} FROM late GROUP BY 1, 2)"


def _late(spark, d):
    return splits.latest(derived.predictions(spark, d))


def _board(spark, d):
    return metrics.evaluate(_late(spark, d), ["system", "search"])


def _late_all(spark, d):
    """All 22 rows of the system table: eight systems without and with search, two kinds of agents with three backbones."""
    kinds = [derived.predictions(spark, d).drop("cutoff").withColumn("block", F.when(F.col("search"), "search").otherwise("parametric")), derived.agent_predictions(spark, d).withColumn("block", F.lit("agent"))]
    return splits.latest(kinds[0].unionByName(kinds[1]))


@query(f"WITH {ALL}, r AS (SELECT *, CAST(dense_rank() OVER (PARTITION BY block ORDER BY mse) AS INTEGER) AS rank FROM full_board) SELECT *, CASE rank WHEN 1 THEN 'best' WHEN 2 THEN 'second' ELSE '' END AS mark FROM r")
def leaderboard_rank(spark, d):
    """The system table in three blocks: parametric, with search, agents."""
    return leaderboard.rank(metrics.evaluate(_late_all(spark, d), ["system", "block"]), block="block")


_SUB = " UNION ALL ".join(
    f"SELECT system, block, '{name}' AS subset, score, truth FROM j WHERE {where}"
    for name, where in (("images", "has_image"), ("videos", "has_video"), ("text_only", "NOT has_image AND NOT has_video"), ("english", "english"), ("other_language", "NOT english"), ("intact", "truth > 1.0::DOUBLE/3"), ("compromised", "truth <= 1.0::DOUBLE/3"), ("all", "true"))
)
MEMBERS = "mem AS (SELECT l_orderkey AS claim_id, bool_or(l_returnflag <> 'R') AS has_image, bool_or(l_returnflag = 'R') AS has_video FROM lineitem GROUP BY 1)"


def _with_media(spark, d, rows):
    joined = rows.join(derived.memberships(spark, d), "claim_id", "left")
    return joined.withColumns({c: F.coalesce(c, F.lit(False)) for c in ("has_image", "has_video")})


@query(f"WITH {ALL}, {MEMBERS}, j AS (SELECT late_all.*, coalesce(has_image, false) AS has_image, coalesce(has_video, false) AS has_video FROM late_all LEFT JOIN mem USING (claim_id)), s AS ({_SUB}) SELECT system, block, subset, count(*) AS n, round(avg((score - truth) * (score - truth)), 6) AS mse FROM s GROUP BY ALL")
def leaderboard_subsets(spark, d):
    return metrics.subsets(_with_media(spark, d, _late_all(spark, d)), ["system", "block"])


@query(f"WITH {LATEST} SELECT system, english, truth, count(*) AS n, round(avg((score - truth) * (score - truth)), 6) AS mse, CAST(grouping(system, english, truth) AS BIGINT) AS level FROM late GROUP BY CUBE (system, english, truth)")
def leaderboard_cube(spark, d):
    return metrics.subset_cube(_late(spark, d), ["system", "english", "truth"])


@query(f"WITH {PRED} SELECT quarter, system, count(*) AS n, round(avg((score - truth) * (score - truth)), 6) AS mse, CAST(grouping(quarter, system) AS BIGINT) AS level FROM pred GROUP BY ROLLUP (quarter, system)")
def error_rollup(spark, d):
    """Errors of all predictions by quarter and system, with totals by quarter and overall."""
    return metrics.subset_rollup(derived.predictions(spark, d), ["quarter", "system"])


@query(f"WITH {LATEST}, r AS (SELECT *, dense_rank() OVER (PARTITION BY search ORDER BY mse) AS r FROM board), g AS (SELECT *, min(mse) OVER (PARTITION BY search) AS best, min(CASE WHEN r = 2 THEN mse END) OVER (PARTITION BY search) AS second FROM r) SELECT system, search, mse, round(mse - best, 6) AS gap, round(second - best, 6) AS lead FROM g")
def leaderboard_gaps(spark, d):
    return leaderboard.gaps(_board(spark, d))


@query(f'WITH {LATEST} SELECT system, max(mse) FILTER (NOT search) AS without, max(mse) FILTER (search) AS "with", round(max(mse) FILTER (NOT search) - max(mse) FILTER (search), 6) AS gain FROM board GROUP BY 1')
def search_gain(spark, d):
    return leaderboard.search_gain(_board(spark, d))


@query(f"""WITH {LATEST}, e AS (SELECT *, (score - truth) * (score - truth) AS e FROM late) SELECT system, search, round(avg(e) FILTER (truth > 1.0::DOUBLE/3), 6) AS mse_intact, round(avg(e) FILTER (truth <= 1.0::DOUBLE/3), 6) AS mse_compromised,
round(avg(e) FILTER (truth > 1.0::DOUBLE/3) - avg(e) FILTER (truth <= 1.0::DOUBLE/3), 6) AS difference, round(avg(score - truth), 6) AS signed_error, round(avg((score < -1.0::DOUBLE/3)::INT::DOUBLE), 6) AS negative_share FROM e GROUP BY 1, 2""")
def class_bias(spark, d):
    return metrics.class_bias(_late(spark, d), ["system", "search"])


@query(f"WITH {LATEST} SELECT system, search, mse, round(4.0::DOUBLE / mse, 6) AS flips, CASE WHEN mse <= 0.04::DOUBLE THEN 'very high agreement' WHEN mse <= 0.1::DOUBLE THEN 'acceptable' ELSE 'above acceptable' END AS band FROM board")
def flip_bands(spark, d):
    return _board(spark, d).select("system", "search", "mse", F.round(flip_equivalent("mse"), 6).alias("flips"), band("mse").alias("band"))


@query(f"WITH {LATEST}, a AS (SELECT late.* REPLACE (CASE WHEN claim_id % 10 = 3 THEN 0.0::DOUBLE ELSE score END AS score), claim_id % 10 <> 3 AS covered FROM late) SELECT system, search, {_m()}, round(avg(covered::INT::DOUBLE), 6) AS coverage FROM a GROUP BY 1, 2")
def missing_as_uncertain(spark, d):
    late = _late(spark, d)
    truth = late.select("claim_id", "truth").distinct()
    given = late.filter("claim_id % 10 <> 3").select("system", "search", "claim_id", "score")
    rows = metrics.align(given, truth, ["system", "search"], missing="zero")
    return rows.groupBy("system", "search").agg(*metrics.measures(), F.round(F.avg(F.col("covered").cast("double")), 6).alias("coverage"))


@query(f"WITH {LATEST}, a AS (SELECT * FROM late WHERE claim_id % 10 <> 3) SELECT system, search, {_m()} FROM a GROUP BY 1, 2")
def missing_excluded(spark, d):
    late = _late(spark, d)
    rows = metrics.align(late.filter("claim_id % 10 <> 3").select("system", "search", "claim_id", "score"), late.select("claim_id", "truth").distinct(), ["system", "search"])
    return metrics.evaluate(rows, ["system", "search"])


@query(f"WITH {LATEST}, s AS (SELECT system, search, CASE WHEN claim_id % 50 = 0 THEN NULL ELSE greatest(-1.0::DOUBLE, least(1.0::DOUBLE, score * 3)) END AS score FROM late) SELECT system, search, count(score) AS n, round(min(score), 6) AS low, round(max(score), 6) AS high FROM s GROUP BY 1, 2")
def predictions_sanitized(spark, d):
    wild = _late(spark, d).withColumn("score", F.when(F.col("claim_id") % 50 == 0, F.lit(float("nan"))).otherwise(F.col("score") * 3))
    return metrics.sanitize(wild).groupBy("system", "search").agg(F.count("score").alias("n"), F.round(F.min("score"), 6).alias("low"), F.round(F.max("score"), 6).alias("high"))


@query("SELECT l_orderkey, l_linenumber, count(*) AS n FROM lineitem GROUP BY 1, 2 HAVING count(*) > 1")
def quality_repeated_keys(spark, d):
    """A quality gate as a table of violations."""
    return metrics.repeated_predictions(load(spark, d, "lineitem", ["l_orderkey", "l_linenumber"]), ["l_orderkey", "l_linenumber"])


@query(f"WITH {LATEST} SELECT system, search, CAST(round(sign(score) * ceil(abs(score * 3) - 0.5::DOUBLE)) AS INTEGER) AS anchor, count(*) AS n FROM late GROUP BY ALL")
def bins_by_anchor(spark, d):
    return _late(spark, d).groupBy("system", "search", nearest_anchor("score", 7).alias("anchor")).agg(F.count(F.lit(1)).alias("n"))


# cutoffs

PARAM = f"{PRED}, par AS (SELECT *, (score - truth) * (score - truth) AS e FROM pred WHERE NOT search)"


def _parametric(spark, d):
    return derived.predictions(spark, d).filter("not search")


@query(f"WITH {PARAM} SELECT system, round(avg(e) FILTER (claim_ts < cutoff), 6) AS mse_before, round(avg(e) FILTER (claim_ts >= cutoff), 6) AS mse_after, round(avg(e) FILTER (claim_ts >= cutoff) - avg(e) FILTER (claim_ts < cutoff), 6) AS inflation FROM par GROUP BY 1")
def cutoff_inflation(spark, d):
    return cutoff.inflation(_parametric(spark, d))


def _curve_sql(source: str) -> str:
    return f"""{source}, days AS (SELECT system, cutoff, CAST(claim_ts AS DATE) AS day, count(e) AS n, sum(e) AS sse FROM rows_ GROUP BY ALL)
SELECT system, day, round(sum(sse) OVER w / sum(n) OVER w, 6) AS mse, day >= CAST(cutoff AS DATE) AS after FROM days WINDOW w AS (PARTITION BY system ORDER BY day RANGE BETWEEN INTERVAL 45 DAYS PRECEDING AND INTERVAL 45 DAYS FOLLOWING)"""


@query(_curve_sql(f"WITH {PARAM}, rows_ AS (SELECT * FROM par)"))
def cutoff_curve(spark, d):
    return cutoff.curve(_parametric(spark, d))


@query(_curve_sql(f"WITH {PARAM}, rows_ AS (SELECT * FROM par WHERE claim_id NOT IN (SELECT l_orderkey FROM lineitem))"))
def cutoff_text_only(spark, d):
    return cutoff.curve(_with_media(spark, d, _parametric(spark, d)), where="not has_image and not has_video")


@query(f"""WITH {PARAM}, days AS (SELECT system, CAST(claim_ts AS DATE) AS day, count(e) AS n, sum(e) AS sse FROM par GROUP BY ALL)
SELECT system, day, round(sum(sse) OVER w / sum(n) OVER w, 6) AS mse FROM days WINDOW w AS (PARTITION BY system ORDER BY day RANGE BETWEEN INTERVAL 90 DAYS PRECEDING AND CURRENT ROW)""")
def cutoff_curve_trailing(spark, d):
    return cutoff.curve(_parametric(spark, d), mode="trailing").drop("after")


@query(f"WITH {PARAM} SELECT system, round(avg(truth * truth - e) FILTER (claim_ts < cutoff), 6) AS margin_before, round(avg(truth * truth - e) FILTER (claim_ts >= cutoff), 6) AS margin_after FROM par GROUP BY 1")
def cutoff_margin(spark, d):
    return cutoff.margin(_parametric(spark, d))


@query(f"WITH {PARAM} SELECT system, CAST(claim_ts AS DATE) AS day, count(e) AS n, round(sum(e), 9) AS sse FROM par GROUP BY ALL")
def cutoff_daily_partials(spark, d):
    return cutoff.daily(_parametric(spark, d)).withColumn("sse", F.round("sse", 9))


@query(f"WITH {PARAM} SELECT CASE WHEN quarter = (SELECT max(quarter) FROM par) THEN 'newest' ELSE 'frozen' END AS split, {_m()} FROM par WHERE quarter = (SELECT max(quarter) FROM par) OR claim_ts < TIMESTAMP '1998-01-01' GROUP BY 1")
def static_vs_latest(spark, d):
    """A frozen benchmark against the newest quarter: what leakage hides."""
    p = _parametric(spark, d)
    rows = splits.static(p, "1998-01-01").withColumn("split", F.lit("frozen")).unionByName(splits.latest(p).withColumn("split", F.lit("newest")))
    return metrics.evaluate(rows, ["split"])


# baselines

TRUTHS = "truths AS (SELECT o_orderkey AS claim_id, CASE WHEN (o_orderkey * 104729) % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS truth FROM orders)"


def _truths(spark, d):
    return load(spark, d, "orders", ["o_orderkey"]).select(F.col("o_orderkey").alias("claim_id"), F.when((F.col("o_orderkey") * 104729) % 2 == 0, 1.0).otherwise(-1.0).alias("truth"))


@query(f"WITH {TRUTHS}, s AS (SELECT truth, unnest(['always -1', 'always 0', 'always 1']) AS system, unnest([-1.0::DOUBLE, 0.0, 1.0]) AS score FROM truths) SELECT system, {_m()} FROM s GROUP BY 1")
def constant_baseline(spark, d):
    t = _truths(spark, d)
    rows = [baselines.constant(t, v, f"always {v}") for v in (-1, 0, 1)]
    return metrics.evaluate(rows[0].unionByName(rows[1]).unionByName(rows[2]), ["system"])


@query(f"WITH {TRUTHS}, s AS (SELECT truth, avg(truth) OVER () AS score FROM truths) SELECT {_m()} FROM s")
def prior_mean_baseline(spark, d):
    return metrics.evaluate(baselines.prior_mean(_truths(spark, d)))


@query(f"WITH {SCORERS}, {HUMAN} SELECT member AS system, {_m()} FROM votes JOIN human USING (claim_id) GROUP BY 1")
def parametric_baselines(spark, d):
    return metrics.evaluate(baselines.parametric(_documents(spark, d)).join(_human(spark, d), "claim_id"), ["system"])


@query(f"WITH {LATEST} SELECT system, search, CASE WHEN truth > 1.0::DOUBLE/3 THEN 'true' ELSE 'false' END AS truth_label, CASE WHEN score > 1.0::DOUBLE/3 THEN 'true' WHEN score < -1.0::DOUBLE/3 THEN 'false' ELSE 'not enough information' END AS label, count(*) AS n, round(avg((score - truth) * (score - truth)), 6) AS mse FROM late GROUP BY ALL")
def coarse_labels(spark, d):
    """The single-label scheme: near and severe confusions count alike there; the squared error keeps them apart."""
    rows = _late(spark, d).withColumn("truth_label", coarse_label("truth")).withColumn("label", coarse_label("score"))
    return rows.groupBy("system", "search", "truth_label", "label").agg(F.count(F.lit(1)).alias("n"), F.round(metrics.mse("score", "truth"), 6).alias("mse"))


# evidence

DATED = """cl AS (SELECT event_id AS claim_id, user_id, ts AS claim_ts FROM events WHERE event_type = 'purchase'), ev AS (SELECT event_id AS evidence_id, user_id, ts AS pub_ts FROM events WHERE event_type IN ('view', 'click'))"""


def _dated(spark, d):
    e = load(spark, d, "events", ["event_id", "ts", "user_id", "event_type"])
    c = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("claim_id"), "user_id", F.col("ts").alias("claim_ts"))
    return c, e.filter("event_type in ('view', 'click')").select(F.col("event_id").alias("evidence_id"), "user_id", F.col("ts").alias("pub_ts"))


@query(f"WITH {DATED} SELECT claim_id, evidence_id FROM cl JOIN ev USING (user_id) WHERE pub_ts <= claim_ts")
def evidence_admissible(spark, d):
    return evidence.admissible(*_dated(spark, d), "user_id").select("claim_id", "evidence_id")


@query(f"WITH {DATED} SELECT claim_id, evidence_id FROM cl JOIN ev USING (user_id) WHERE pub_ts < claim_ts - INTERVAL 2 DAYS")
def evidence_lagged(spark, d):
    return evidence.admissible(*_dated(spark, d), "user_id", lag_days=2, strict=True).select("claim_id", "evidence_id")


@query(f"WITH {DATED} SELECT claim_id, count(*) AS n FROM cl JOIN ev ON pub_ts <= claim_ts AND pub_ts > claim_ts - INTERVAL 1 DAY GROUP BY 1")
def evidence_within_day(spark, d):
    return evidence.count_within(*[x.drop("user_id") for x in _dated(spark, d)], days=1)


@query(f"WITH {DATED} SELECT claim_id, cl.user_id, claim_ts, arg_max(evidence_id, (pub_ts, evidence_id)) AS evidence_id, max(pub_ts) AS pub_ts FROM cl LEFT JOIN ev ON cl.user_id = ev.user_id AND pub_ts <= claim_ts GROUP BY 1, 2, 3")
def evidence_latest(spark, d):
    return evidence.newest(*_dated(spark, d), "user_id")


def _tokens_sql(table: str, key: str) -> str:
    return rf"SELECT {key}, token, count(*) AS tf FROM (SELECT {key}, unnest(list_filter(regexp_split_to_array(lower(text), '[^\p{{L}}\p{{N}}]+'), lambda t: t <> '')) AS token FROM {table}) GROUP BY ALL"


BM25 = f"""q AS (SELECT DISTINCT item_id AS claim_id, token FROM ({_tokens_sql('benchmark', 'item_id')})), p AS ({_tokens_sql('documents', 'doc_id')}), l AS (SELECT doc_id, sum(tf) AS len FROM p GROUP BY 1), c AS (SELECT count(*) AS n, avg(len) AS mean FROM l),
f AS (SELECT token, count(*) AS df FROM p GROUP BY 1), s AS (SELECT q.claim_id, p.doc_id, round(sum(ln(1 + (c.n - f.df + 0.5::DOUBLE) / (f.df + 0.5::DOUBLE)) * p.tf * 2.2::DOUBLE / (p.tf + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * l.len / c.mean))), 6) AS score
FROM q JOIN p USING (token) JOIN f USING (token) JOIN l ON l.doc_id = p.doc_id, c GROUP BY 1, 2)"""


def _claims_as_queries(spark, d):
    return load(spark, d, "benchmark").select(F.col("item_id").alias("claim_id"), "text")


@query(f"WITH {BM25} SELECT claim_id, doc_id, score, CAST(row_number() OVER (PARTITION BY claim_id ORDER BY score DESC, doc_id) AS INTEGER) AS rank FROM s QUALIFY rank <= 3")
def evidence_search(spark, d):
    return evidence.search(_claims_as_queries(spark, d), load(spark, d, "documents", ["doc_id", "text"]))


_DAY = "TIMESTAMP '2024-01-01' + to_days(CAST({0} % 100 AS INTEGER))"


@query(f"WITH {BM25}, t AS (SELECT * FROM s WHERE {_DAY.format('doc_id')} <= {_DAY.format('claim_id * 2')}) SELECT claim_id, doc_id, score, CAST(row_number() OVER (PARTITION BY claim_id ORDER BY score DESC, doc_id) AS INTEGER) AS rank FROM t QUALIFY rank <= 3")
def evidence_search_before(spark, d):
    """Search with the time cut before ranking; days come from ids."""
    day = lambda c: (F.lit("2024-01-01").cast("timestamp_ntz") + F.make_dt_interval((c % 100).cast("int")))
    claims = _claims_as_queries(spark, d).withColumn("claim_ts", day(F.col("claim_id") * 2))
    docs = load(spark, d, "documents", ["doc_id", "text"]).withColumn("pub_ts", day(F.col("doc_id")))
    return evidence.search(claims, docs, before=True)


# claims against a collection of evidence: documents are the claims, the benchmark's items the evidence

_CUT = r"list_filter(regexp_split_to_array(lower({0}), '[^\p{{L}}\p{{N}}]+'), lambda t: t <> '')"


def _backed(queries: str, name: str = "back") -> str:
    """SQL of the support of (id, text) queries in the benchmark."""
    return rf"""{name}_q AS (SELECT DISTINCT id, unnest({_CUT.format('text')}) AS token FROM ({queries})), {name}_p AS ({_tokens_sql('benchmark', 'item_id')}), {name}_l AS (SELECT item_id, sum(tf) AS len FROM {name}_p GROUP BY 1), {name}_c AS (SELECT count(*) AS n, avg(len) AS mean FROM {name}_l),
{name}_f AS (SELECT token, count(*) AS df FROM {name}_p GROUP BY 1), {name}_s AS (SELECT q.id, p.item_id, round(sum(ln(1 + (c.n - f.df + 0.5::DOUBLE) / (f.df + 0.5::DOUBLE)) * p.tf * 2.2::DOUBLE / (p.tf + 1.2::DOUBLE * (0.25::DOUBLE + 0.75::DOUBLE * l.len / c.mean))), 6) AS score
FROM {name}_q q JOIN {name}_p p USING (token) JOIN {name}_f f USING (token) JOIN {name}_l l ON l.item_id = p.item_id, {name}_c c GROUP BY 1, 2), {name} AS (SELECT id, least(1.0::DOUBLE, max(score) / 100) AS support FROM {name}_s GROUP BY 1)"""


def _moved(score: str) -> str:
    return f"greatest(-1.0::DOUBLE, least(1.0::DOUBLE, 0.5::DOUBLE * ({score}) + 0.5::DOUBLE * (2 * coalesce(support, 0.0::DOUBLE) - 1) * abs({score})))"


def _found(spark, d):
    """Support of claims in the benchmark's items, which are sent to where the claims are."""
    items = load(spark, d, "benchmark").select(F.col("item_id").alias("doc_id"), "text")
    return lambda claims: evidence.support(claims, items, side="docs")


WHOLE = "SELECT doc_id AS id, text FROM documents"


@query(f"WITH {_backed(WHOLE)}, {SCORERS}, {HUMAN}, m AS (SELECT claim_id, member AS system, round({_moved('score')}, 6) AS score FROM votes LEFT JOIN back ON id = claim_id) SELECT system, {_m()} FROM m JOIN human USING (claim_id) GROUP BY 1")
def evidence_augmented_baselines(spark, d):
    docs = _documents(spark, d)
    support = _found(spark, d)(docs.select(F.col("doc_id").alias("claim_id"), "text"))
    return metrics.evaluate(baselines.with_evidence(baselines.parametric(docs), support).join(_human(spark, d), "claim_id"), ["system"])


def _backbones_sql(table: str) -> str:
    return f"""SELECT *, unnest(['b1', 'b2', 'b3']) AS b, unnest([("J1" + "J2" + "J3" + "J4") / 4, "J4", least("J4", "J3")]) AS own FROM {table}"""


MULTI_CHECK = f"""{_backed(WHOLE)}, {SCORERS}, mc AS ({_backbones_sql('wide LEFT JOIN back ON id = doc_id')}),
multi AS (SELECT doc_id AS claim_id, 'multi_check_' || b AS system, round((own + ({_moved('"J1"')} + {_moved('"J2"')} + {_moved('"J3"')} + {_moved('"J4"')}) / 4 + least({_moved('"J1"')}, {_moved('"J2"')}, {_moved('"J3"')}, {_moved('"J4"')})) / 3, 6) AS score FROM mc)"""


@query(f"WITH {MULTI_CHECK}, {HUMAN} SELECT system, {_m()} FROM multi JOIN human USING (claim_id) GROUP BY 1")
def multi_check_baseline(spark, d):
    return metrics.evaluate(baselines.multi_check(_documents(spark, d), _found(spark, d)).join(_human(spark, d), "claim_id"), ["system"])


PARTS = rf"""cuts AS (SELECT doc_id, regexp_extract_all(text, '{baselines.SENTENCE}') AS ps FROM documents), each_part AS (SELECT doc_id, unnest(ps) AS text, generate_subscripts(ps, 1) - 1 AS place FROM cuts),
sents AS (SELECT doc_id AS claim, doc_id || ':' || place AS doc_id, text FROM each_part WHERE trim(translate(text, chr(10) || chr(9) || chr(13), '   ')) <> '')"""
STEPWISE = f"""{PARTS}, {_backed('SELECT doc_id AS id, text FROM sents', 'sb')}, {SCORERS.replace('FROM documents', 'FROM sents')}, st AS ({_backbones_sql('wide LEFT JOIN sb ON id = doc_id')}),
stepwise AS (SELECT claim AS claim_id, 'stepwise_' || b AS system, round(min({_moved('own')}), 6) AS score FROM st JOIN sents USING (doc_id) GROUP BY 1, 2)"""


@query(f"WITH {STEPWISE}, {HUMAN} SELECT system, {_m()} FROM stepwise JOIN human USING (claim_id) GROUP BY 1")
def stepwise_baseline(spark, d):
    return metrics.evaluate(baselines.stepwise(_documents(spark, d), _found(spark, d)).join(_human(spark, d), "claim_id"), ["system"])


# frames and transcripts

_EVEN = "SELECT *, row_number() OVER (PARTITION BY {k} ORDER BY {o}) - 1 AS place, count(*) OVER (PARTITION BY {k}) AS length FROM {t}"
_WANTED = "list_contains([" + ", ".join(f"CAST(floor({2 * i + 1} * length / 10) AS BIGINT)" for i in range(5)) + "], place)"


@query(f"WITH p AS ({_EVEN.format(k='user_id', o='ts, event_id', t='events')}) SELECT user_id, event_id, CAST(place AS INTEGER) AS place, length FROM p WHERE {_WANTED}")
def frames_even5(spark, d):
    return frames.even(load(spark, d, "events", ["event_id", "user_id", "ts"]), "user_id", ["ts", "event_id"]).select("user_id", "event_id", "place", "length")


@query(f"WITH p AS ({_EVEN.format(k='conv_id', o='turn', t='conversations')}) SELECT conv_id, turn, CAST(place AS INTEGER) AS place, length FROM p WHERE {_WANTED}")
def frames_conversations(spark, d):
    return frames.even(load(spark, d, "conversations"), "conv_id", ["turn"]).select("conv_id", "turn", "place", "length")


@query("SELECT conv_id, count(*) AS n, string_agg(role || ': ' || text, chr(10) ORDER BY turn, role, text) AS transcript FROM conversations GROUP BY 1")
def transcripts(spark, d):
    return frames.transcript(load(spark, d, "conversations"), "conv_id", "turn")


def _scored_as(table: str, of: str) -> str:
    """SQL of the ensemble over another table of (doc_id, text), as a subquery."""
    return f"(WITH documents AS ({table}), {SCORERS} SELECT claim_id, mean AS {of} FROM ens)"


_NATIVE = "SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn, text) AS text FROM conversations GROUP BY 1"
_FIVE = f"SELECT conv_id AS doc_id, string_agg(text, chr(10) ORDER BY turn, text) AS text FROM ({_EVEN.format(k='conv_id', o='turn', t='conversations')}) WHERE {_WANTED} GROUP BY 1"


def _compared(b3) -> str:
    return f"SELECT count(*) AS n, round(avg((sa - sb) * (sa - sb)), 6) AS mse, round(avg(abs(sa - sb)), 6) AS mae, round(corr(sa, sb), 6) AS correlation, round(avg(({b3('sa', 3)} = {b3('sb', 3)})::INT::DOUBLE), 6) AS same_decision"


@query(f"{_compared(_b)} FROM {_scored_as(_NATIVE, 'sa')} JOIN {_scored_as(_FIVE, 'sb')} USING (claim_id)")
def frames_vs_native(spark, d):
    """Scores of the same systems from five sampled turns and a transcript of them, against the whole dialogue."""
    c = load(spark, d, "conversations")
    joined = lambda rows: rows.groupBy(F.col("conv_id").alias("doc_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), "\n").alias("text"))
    scored = lambda docs: combine_wide(judges.wide_votes(docs), list(text.raw_scorers())).select("claim_id", F.col("mean").alias("score"))
    return ablate.compare_runs(scored(joined(c)), scored(joined(frames.even(c, "conv_id", ["turn"]))))


# statistics and trends


def _shares_sql(col: str, table: str, least: float) -> str:
    return f"WITH c AS (SELECT {col} AS v, count(*) AS n FROM {table} GROUP BY 1), t AS (SELECT v, n, sum(n) OVER () AS total FROM c) SELECT CASE WHEN 100.0::DOUBLE * n / total >= {least}::DOUBLE THEN v ELSE 'other' END AS {col}, CAST(sum(n) AS BIGINT) AS n, round(100.0::DOUBLE * sum(n) / max(total), 6) AS percent FROM t GROUP BY 1"


@query(_shares_sql("lang", "documents", 0.0))
def stats_languages(spark, d):
    return insights.shares(load(spark, d, "documents", ["lang"]), "lang")


@query(f"WITH {HOSTS}, c AS (SELECT host AS v, count(*) AS n FROM pubs GROUP BY 1), t AS (SELECT v, n, sum(n) OVER () AS total FROM c) SELECT CASE WHEN 100.0::DOUBLE * n / total >= 5 THEN v ELSE 'other' END AS host, CAST(sum(n) AS BIGINT) AS n, round(100.0::DOUBLE * sum(n) / max(total), 6) AS percent FROM t GROUP BY 1")
def stats_hosts(spark, d):
    from factbench.operators.publishers import with_publisher

    return insights.shares(with_publisher(load(spark, d, "pages", ["url"])), "host", 5)


@query("SELECT count(DISTINCT c_nationkey) AS n_distinct, (SELECT count(DISTINCT c_mktsegment) FROM customer) AS n_groups FROM customer")
def stats_distinct_sketch(spark, d):
    """Distinct nations over all market segments, out of one stored sketch a segment."""
    return insights.merged_distinct(insights.distinct_sketches(load(spark, d, "customer"), "c_mktsegment", "c_nationkey"))


@query(_shares_sql("source", "documents", 0.0))
def stats_shares(spark, d):
    return insights.shares(load(spark, d, "documents", ["source"]), "source")


@query("SELECT count(*) AS n_values, CAST(sum((n >= 50)::INT) AS BIGINT) AS n_frequent FROM (SELECT source, count(*) AS n FROM documents GROUP BY 1)")
def stats_frequent(spark, d):
    return insights.frequent(load(spark, d, "documents", ["source"]), "source", 50)


@query("""WITH c AS (SELECT CAST(date_trunc('quarter', o_orderdate) AS DATE) AS quarter, o_orderpriority AS category, count(*) AS n FROM orders GROUP BY 1, 2), s AS (SELECT *, round(100.0::DOUBLE * n / sum(n) OVER (PARTITION BY quarter), 6) AS percent FROM c)
SELECT *, round(percent - lag(percent) OVER (PARTITION BY category ORDER BY quarter), 6) AS change FROM s""")
def trend_share(spark, d):
    o = load(spark, d, "orders", ["o_orderdate", "o_orderpriority"]).withColumnRenamed("o_orderpriority", "category")
    return insights.trend(o, "o_orderdate", "category")


@query("WITH c AS (SELECT CAST(date_trunc('quarter', o_orderdate) AS DATE) AS quarter, count(*) AS n FROM orders GROUP BY 1) SELECT quarter, n, n - lag(n) OVER (ORDER BY quarter) AS change, n = max(n) OVER () AS peak FROM c")
def trend_volume(spark, d):
    return insights.volume(load(spark, d, "orders", ["o_orderdate"]), "o_orderdate")


@query(f"WITH {MEMBERS} SELECT CAST(date_trunc('quarter', o_orderdate) AS DATE) AS quarter, count(*) AS n, round(100.0::DOUBLE * avg((claim_id IS NOT NULL)::INT), 6) AS with_media, round(100.0::DOUBLE * avg(coalesce(has_video, false)::INT), 6) AS with_video FROM orders LEFT JOIN mem ON claim_id = o_orderkey GROUP BY 1")
def trend_media(spark, d):
    o = load(spark, d, "orders", ["o_orderkey", "o_orderdate"]).select(F.col("o_orderkey").alias("claim_id"), F.trunc("o_orderdate", "quarter").alias("quarter"))
    m = derived.memberships(spark, d)
    rows = o.join(m, "claim_id", "left")
    share = lambda c: F.round(100.0 * F.avg(F.coalesce(c, F.lit(False)).cast("int")), 6)
    return rows.groupBy("quarter").agg(F.count(F.lit(1)).alias("n"), share(F.col("has_video").isNotNull()).alias("with_media"), share(F.col("has_video")).alias("with_video"))


@query(f"WITH {VERDICTS} SELECT round(100.0::DOUBLE * avg((label = 'intact')::INT), 6) AS percent, count(*) AS n FROM verdicts")
def class_share(spark, d):
    return insights.class_share(_verdicts(spark, d), F.col("label") == "intact")


# runs against each other, leaks, yields

SECOND = SCORERS.replace('round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, r4)), 6) AS "J4"', "round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, 1 - abs(length(regexp_replace(text, '[ \\t\\n\\r]', '', 'g')) / len(ws)::DOUBLE - 5.0::DOUBLE) / 4)), 6) AS \"J4\"")


@query(f"""WITH a AS (WITH {SCORERS} SELECT claim_id, mean AS sa FROM ens), b AS (WITH {SECOND} SELECT claim_id, mean AS sb FROM ens)
SELECT count(*) AS n, round(avg((sa - sb) * (sa - sb)), 6) AS mse, round(avg(abs(sa - sb)), 6) AS mae, round(corr(sa, sb), 6) AS correlation, round(avg(({_b('sa', 3)} = {_b('sb', 3)})::INT::DOUBLE), 6) AS same_decision FROM a JOIN b USING (claim_id)""")
def backbone_compare(spark, d):
    run = lambda family: combine_wide(judges.wide_votes(_documents(spark, d), family), list(family())).select("claim_id", F.col("mean").alias("score"))
    return ablate.compare_runs(run(text.raw_scorers), run(text.second_raw_scorers))


_QUARTER = "SELECT doc_id, text FROM documents WHERE date_trunc('quarter', DATE '2023-01-01' + CAST(doc_id % 800 AS INTEGER)) = DATE '2024-01-01'"


@query(f"{_compared(_b)} FROM {_scored_as(_QUARTER, 'sa')} JOIN {_scored_as(_QUARTER, 'sb').replace(SCORERS, SECOND)} USING (claim_id)")
def backbone_quarter(spark, d):
    """One quarter made again with another backbone: are scores and verdicts the same?"""
    dated = _documents(spark, d).filter(F.trunc(F.date_add(F.lit("2023-01-01").cast("date"), (F.col("doc_id") % 800).cast("int")), "quarter") == F.lit("2024-01-01").cast("date"))
    run = lambda family: combine_wide(judges.wide_votes(dated, family), list(family())).select("claim_id", F.col("mean").alias("score"))
    return ablate.compare_runs(run(text.raw_scorers), run(text.second_raw_scorers))


@query(r"""WITH c AS (SELECT item_id, text, regexp_replace(text, '\.', ' !', 'g') AS other FROM benchmark), w AS (SELECT item_id, list_distinct(regexp_split_to_array(text, '[ \t\n\r]+')) AS a, list_distinct(regexp_split_to_array(other, '[ \t\n\r]+')) AS b, text, other FROM c)
SELECT item_id AS claim_id, round(len(list_intersect(a, b)) / len(list_distinct(list_concat(a, b)))::DOUBLE, 6) AS jaccard, CAST(levenshtein(text, other) AS INTEGER) AS distance FROM w""")
def backbone_texts(spark, d):
    b = load(spark, d, "benchmark").select(F.col("item_id").alias("claim_id"), "text")
    return ablate.compare_texts(b, b.withColumn("text", F.regexp_replace("text", r"\.", " !")))


@query(r"""WITH g AS (SELECT item_id, list_distinct(list_transform(range(1, len(ws) - 6), lambda i: array_to_string(ws[i:i + 7], ' '))) AS grams FROM (SELECT item_id, string_split(trim(text), ' ') AS ws FROM benchmark)),
h AS (SELECT DISTINCT unnest(list_transform(range(1, greatest(1, len(ws) - 6)), lambda i: array_to_string(ws[i:i + 7], ' '))) AS gram FROM (SELECT string_split(trim(text), ' ') AS ws FROM documents)),
e AS (SELECT item_id, unnest(grams) AS gram FROM g) SELECT item_id, count(*) AS n_grams, count(h.gram) AS n_leaked FROM e LEFT JOIN h USING (gram) GROUP BY 1""")
def leak_overlap(spark, d):
    """Eight-word runs of benchmark claims that occur in documents."""
    def grams(df, key):
        # the words are bound to a variable, or each run would split the text again
        of = lambda ws: F.when(F.size(ws) >= 8, F.transform(F.sequence(F.lit(1), F.size(ws) - 7), lambda i: F.array_join(F.slice(ws, i, F.lit(8)), " ")))
        runs = F.element_at(F.transform(F.array(F.split(F.trim("text"), " ")), of), 1)
        return df.select(key, F.explode(F.array_distinct(runs)).alias("gram"))

    own = grams(load(spark, d, "benchmark"), "item_id")
    seen = grams(_documents(spark, d), "doc_id").join(small(own.select("gram").distinct()), "gram", "left_semi").select("gram", F.lit(1).alias("hit")).distinct()
    return own.join(seen, "gram", "left").groupBy("item_id").agg(F.count(F.lit(1)).alias("n_grams"), F.count("hit").alias("n_leaked"))


@query(rf"""WITH {HOSTS}, {ARTICLE}, s AS (SELECT 1 AS step, 'publisher' AS stage, count(*) AS entered, sum((publisher IN ('example.com', 'example.org'))::INT) AS kept FROM pubs
UNION ALL SELECT 2, 'article', count(*), sum((length(article) >= 300)::INT) FROM article JOIN pubs USING (page_id) WHERE publisher IN ('example.com', 'example.org')
UNION ALL SELECT 3, 'long', count(*), sum((length(article) >= 2000)::INT) FROM article JOIN pubs USING (page_id) WHERE publisher IN ('example.com', 'example.org') AND length(article) >= 300)
SELECT CAST(step AS INTEGER) AS step, stage, entered, CAST(kept AS BIGINT) AS kept, round(kept / entered::DOUBLE, 6) AS stage_yield, round(exp(sum(ln(kept / entered::DOUBLE)) OVER (ORDER BY step)), 6) AS total_yield,
CAST(entered * CASE stage WHEN 'article' THEN 1 WHEN 'long' THEN 2 ELSE 0 END AS BIGINT) AS calls, CAST(first_value(entered) OVER (ORDER BY step) * CASE stage WHEN 'article' THEN 1 WHEN 'long' THEN 2 ELSE 0 END AS BIGINT) AS calls_unfiltered FROM s""")
def funnel_cumulative(spark, d):
    from factbench.operators.articles import with_article
    from factbench.operators.publishers import with_publisher
    from factbench.plans.construction import CREDIBLE

    rows = with_article(with_publisher(load(spark, d, "pages"))).select(F.col("publisher").isin(*CREDIBLE).alias("ok"), F.length("article").alias("chars"))
    long, longer = F.col("ok") & (F.col("chars") >= 300), F.col("ok") & (F.col("chars") >= 2000)
    n = lambda c: F.sum(c.cast("long"))
    sums = rows.agg(F.count(F.lit(1)).alias("a"), n(F.col("ok")).alias("b"), n(long).alias("c"), n(longer).alias("e"))
    table = sums.select(F.inline(F.array(*[F.struct(F.lit(i).alias("step"), F.lit(s).alias("stage"), F.col(x).alias("entered"), F.col(y).alias("kept")) for i, s, x, y in ((1, "publisher", "a", "b"), (2, "article", "b", "c"), (3, "long", "c", "e"))])))
    return funnel.calls(funnel.cumulative(table), {"article": 1, "long": 2})


@query(f"WITH {SCORERS} SELECT CAST({_b('mean', 7)} AS INTEGER) AS bin, count(*) AS n FROM ens GROUP BY 1")
def ensemble_bins7(spark, d):
    return _ensemble(spark, d).groupBy(bin_index("mean", 7).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
