"""The construction pipeline as one run: one set of reviews through stages 1 to 7, each stage on what the one before kept.

Reviews are the given documents, their articles the given pages (four documents a page or so), their media the given
vectors. What hosted models, downloads and feeds would decide is planted by integer hashes and by hashes of URLs. Every
stage gives what it keeps and a narrow row (stage, status, reason) for every record that entered it.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factbench.functions import url
from factbench.functions.scores import clip
from factbench.functions.text import raw_scorers, with_scores
from factbench.operators import appearances, articles, claims, discovery, ensemble, funnel, judges, media, publishers, rectify, splits, verdict
from factbench.plans.construction import ARTICLE, CREDIBLE, HOSTS, LANGUAGE, LINKS, MEDIA, NEAR, SAYS, SCORERS, STANDARD, TWINS_OF
from factbench.sources import derived
from factbench.sources.io import checkpointed, load, small, spread

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


@dataclass
class Stage:
    """What a stage keeps, and a row (stage, status, reason) per record that entered it."""

    kept: DataFrame
    marks: DataFrame


def decided(df: DataFrame, stage: str, reason, pending=None) -> Stage:
    """Records without a reason against them stay; those that wait are neither kept nor dropped yet. The decisions are computed once."""
    waits = pending if pending is not None else F.lit(False)
    told = checkpointed(df.withColumns({"_waits": waits, "_reason": F.when(~waits, reason)}))
    status = F.when(F.col("_waits"), "pending").when(F.col("_reason").isNull(), "kept").otherwise("dropped")
    return Stage(told.filter("not _waits and _reason is null").drop("_waits", "_reason"), funnel.marked(told, stage, status, F.col("_reason")))


# stage 1

FEED = """count_ AS (SELECT count(*) AS pages, (SELECT count(*) // 10 FROM embeddings) AS sets FROM pages),
feed AS (SELECT doc_id AS claim_id, text AS raw, source AS claimant, CASE WHEN doc_id % 3 = 0 THEN detected ELSE lang END AS lang, doc_id % pages AS page_id, doc_id % sets AS media_set, doc_id % 97 = 0 AS malformed, DATE '2023-01-01' + CAST(doc_id % 800 AS INTEGER) AS date FROM guess, count_),
s1 AS (SELECT *, CASE WHEN malformed THEN 'malformed' WHEN row_number() OVER (PARTITION BY malformed, raw ORDER BY claim_id) > 1 THEN 'repeated' END AS r1 FROM feed)"""


def feed(spark: SparkSession, d: str) -> DataFrame:
    """(raw) review markup of all documents; one in 97 is malformed, one in 8 names its appearances, one in 3 no language."""
    docs = spread(load(spark, d, "documents", ["doc_id", "text", "lang", "source"]))
    pages = load(spark, d, "pages", ["page_id", "url"])
    n = pages.agg(F.count(F.lit(1)).alias("pages"))
    rows = docs.crossJoin(F.broadcast(n)).withColumn("page_id", F.col("doc_id") % F.col("pages")).join(small(pages), "page_id")
    given = F.when(F.col("doc_id") % 8 == 0, F.array(*[F.struct(F.concat(F.lit(f"https://given.example/{p}/"), F.col("doc_id").cast("string")).alias("url")) for p in "pq"]))
    markup = F.struct(
        F.col("text").alias("claimReviewed"), F.when(F.col("doc_id") % 3 != 0, F.col("lang")).alias("inLanguage"), F.date_add(F.lit("2023-01-01").cast("date"), (F.col("doc_id") % 800).cast("int")).alias("datePublished"),
        F.concat("url", F.lit("#r"), F.col("doc_id").cast("string"), F.lit("p"), F.col("page_id").cast("string")).alias("url"),
        F.struct(F.col("source").alias("name")).alias("author"), F.struct(given.alias("appearance")).alias("itemReviewed"),
    )
    return rows.select(F.when(F.col("doc_id") % 97 != 0, F.to_json(markup)).otherwise(F.lit("{broken")).alias("raw"))


def discovery_stage(raw: DataFrame) -> Stage:
    parsed = discovery.parse_reviews(raw).withColumnRenamed("claim", "raw")
    number = lambda mark: F.regexp_extract("url", rf"#r([0-9]+)p([0-9]+)$", mark).cast("long")
    rows = parsed.withColumns({"claim_id": F.when(~F.col("malformed"), number(1)), "page_id": F.when(~F.col("malformed"), number(2))})
    good = discovery.fill_language(rows.filter("not malformed"), "raw")
    first = discovery.dedup_reviews(good.select("claim_id", "raw"), ["raw"], ["claim_id"]).select("claim_id", F.lit(True).alias("_first"))
    told = good.join(first, "claim_id", "left").unionByName(rows.filter("malformed").withColumn("_first", F.lit(None).cast("boolean")))
    return decided(told, "1 discovery", F.when(F.col("malformed"), "malformed").when(F.col("_first").isNull(), "repeated"))


# stage 2

PUBLISHERS = f"s2 AS (SELECT s1.*, publisher, CASE WHEN publisher NOT IN {CREDIBLE} THEN 'not credible' END AS r2 FROM s1 JOIN pubs USING (page_id) WHERE r1 IS NULL)"


def publisher_stage(reviews: DataFrame) -> Stage:
    told = publishers.with_publisher(reviews)
    listed = told.sparkSession.createDataFrame([(c, True) for c in CREDIBLE], "publisher string, _listed boolean")
    return decided(told.join(small(listed), "publisher", "left"), "2 publisher", F.when(F.col("_listed").isNull(), "not credible"))


# stage 3

ARTICLES = """s3 AS (SELECT s2.* EXCLUDE (r1, r2), article.article, CASE WHEN claim_id % 10 = 9 THEN 'pending' WHEN claim_id % 23 = 0 OR trim(article.article) = '' THEN 'inaccessible' WHEN length(article.article) < 300 THEN 'too short' END AS r3 FROM s2 JOIN article USING (page_id) WHERE r2 IS NULL)"""


def article_stage(reviews: DataFrame, pages: DataFrame) -> Stage:
    """Articles by page, cleaned once a page; one in 23 can't be reached, and one in ten waits."""
    cleaned = articles.with_article(pages.select("page_id", "html")).select("page_id", "article")
    told = reviews.join(cleaned, "page_id", "left").withColumn("article", F.when(F.col("claim_id") % 23 != 0, F.col("article")))
    lost = F.coalesce(F.trim("article"), F.lit("")) == ""
    return decided(told, "3 article", F.when(lost, "inaccessible").when(F.length("article") < 300, "too short"), F.col("claim_id") % 10 == 9)


# stage 4

_OK = "substr(md5({0}), 1, 1) < '4'"
_ARCHIVE = "https://web.archive.example/web/2024/"
APPEARANCES = f"""asked AS (SELECT claim_id, CAST(p AS INTEGER) AS place, 'https://given.example/' || CASE p WHEN 0 THEN 'p' ELSE 'q' END || '/' || claim_id AS url FROM s3, (VALUES (0), (1)) t(p) WHERE r3 IS NULL AND claim_id % 8 = 0
UNION ALL SELECT claim_id, CAST(place AS INTEGER), url FROM s3 JOIN links USING (page_id) WHERE r3 IS NULL AND claim_id % 8 <> 0),
had AS (SELECT claim_id, place, url, CASE WHEN {_OK.format('url')} THEN url WHEN {_OK.format(f"'{_ARCHIVE}' || url")} THEN '{_ARCHIVE}' || url END AS chosen FROM asked),
kept_at AS (SELECT claim_id, count(*) AS n_appearances, arg_min(lower(regexp_extract(url, '^[a-zA-Z]+://(?:[^/?#@]*@)?([^/?#:]+)', 1)), place) AS at_host FROM had WHERE chosen IS NOT NULL GROUP BY 1),
s4 AS (SELECT s3.* EXCLUDE (r3), n_appearances, at_host, CASE WHEN n_appearances IS NULL THEN 'no appearance' END AS r4 FROM s3 LEFT JOIN kept_at USING (claim_id) WHERE r3 IS NULL)"""


def appearance_stage(reviews: DataFrame, pages: DataFrame) -> Stage:
    """Given appearances, else the links of the article's page; two that could be fetched, archived copies standing in."""
    named = appearances.given(reviews.withColumnRenamed("claim_id", "review_id")).filter("url is not null").withColumnRenamed("review_id", "claim_id")
    links = appearances.extract(pages)
    found = appearances.lacking(reviews).select("claim_id", "page_id").join(links, "page_id").select("claim_id", "place", "url")
    asked = named.select("claim_id", "place", "url").unionByName(found).withColumn("archived_url", F.concat(F.lit(_ARCHIVE), "url"))
    tried = asked.select("url").union(asked.select("archived_url")).distinct()
    fetched = tried.select("url", (F.substring(F.md5(F.col("url").cast("binary")), 1, 1) < "4").alias("ok"))
    had = appearances.retrieved(asked, fetched)
    seen = had.groupBy("claim_id").agg(F.count(F.lit(1)).alias("n_appearances"), F.min_by(url.host("url"), "place").alias("at_host"))
    return decided(reviews.join(seen, "claim_id", "left"), "4 appearance", F.when(F.col("n_appearances").isNull(), "no appearance"))


# stage 5

_BLANK = "trim(coalesce({0}, '')) = ''"
_SQUEEZED = r"regexp_replace(regexp_replace(regexp_replace({0}, '[ \t\n\r]+', ' ', 'g'), '^ | $', '', 'g'), '" + claims.LEAD_IN + "', '')"
_FIRST = r"CASE WHEN regexp_extract(c, '(?s)^(.*?[.!?])(?:\s|$)', 1) <> '' THEN regexp_extract(c, '(?s)^(.*?[.!?])(?:\s|$)', 1) ELSE c END"
_WORDS = r"len(list_filter(regexp_split_to_array({0}, '[ \t\n\r]+'), lambda w: w <> ''))"
CLAIMS_OF = f"""kept_media AS (SELECT claim_id AS media_set, media_id, is_video, origin FROM media WHERE (claim_id, media_id) NOT IN (SELECT (claim_id, dropped_id) FROM near_ WHERE sim > 0.85)),
four AS (SELECT * FROM kept_media QUALIFY row_number() OVER (PARTITION BY media_set ORDER BY is_video DESC, origin, media_id) <= 4),
sets_ AS (SELECT media_set, count(*) AS n, string_agg(CASE WHEN is_video THEN 'video' ELSE 'image' END, ', ' ORDER BY is_video DESC, origin, media_id) AS kinds, min(round(1 - ((media_id * 37) % 41) / 20.0::DOUBLE, 6)) AS seen FROM four GROUP BY 1),
s5a AS (SELECT s4.* EXCLUDE (r4), CASE WHEN claim_id % 3 <> 0 THEN coalesce(n, 0) ELSE 0 END AS n_media, CASE WHEN claim_id % 3 <> 0 THEN kinds END AS kinds, CASE WHEN claim_id % 3 <> 0 THEN seen END AS seen FROM s4 LEFT JOIN sets_ USING (media_set) WHERE r4 IS NULL),
s5b AS (SELECT *, {_SQUEEZED.format("CASE WHEN " + _BLANK.format('raw') + " THEN article ELSE raw END")} AS c FROM s5a),
s5c AS (SELECT * EXCLUDE (c), concat_ws(' ', claimant, 'on ' || at_host, 'in ' || strftime(date, '%Y-%m')) || ': ' || {_FIRST} || CASE WHEN n_media > 0 THEN ' [' || kinds || ']' ELSE '' END AS claim FROM s5b),
s5 AS (SELECT *, CASE WHEN regexp_matches(claim, '{claims._any(claims.VERDICT_WORDS)}') THEN 'verdict exposed' WHEN regexp_matches(claim, '{claims._any(claims.MEDIA_WORDS)}') AND n_media = 0 THEN 'media missing' WHEN {_WORDS.format('claim')} > 70 THEN 'too long' END AS r5 FROM s5c)"""


def claim_stage(reviews: DataFrame, items: DataFrame) -> Stage:
    """Media of each claim without near duplicates, four at most; claims rewritten with their context, then validated.

    Sets of media are cleaned once each and then joined; two in three reviews have one.
    """
    four = media.cap(media.dedup(items))
    each = F.struct((~F.col("is_video")).alias("later"), "origin", "media_id", F.when(F.col("is_video"), "video").otherwise("image").alias("kind"))
    sets = four.groupBy(F.col("claim_id").alias("media_set")).agg(
        F.count(F.lit(1)).alias("_n"), F.transform(F.array_sort(F.collect_list(each)), lambda x: x["kind"]).alias("_kinds"), F.min(F.round(1 - ((F.col("media_id") * 37) % 41) / 20.0, 6)).alias("_seen")
    )
    n_sets = items.select(F.expr("count_if(media_id < 1000000) div 10").alias("sets"))
    has = F.col("claim_id") % 3 != 0
    told = reviews.crossJoin(F.broadcast(n_sets)).withColumn("media_set", F.col("claim_id") % F.col("sets")).join(sets, "media_set", "left")
    none = F.expr("cast(array() as array<string>)")
    told = told.withColumns({"n_media": F.when(has, F.coalesce("_n", F.lit(0))).otherwise(0), "kinds": F.when(has, F.coalesce("_kinds", none)).otherwise(none), "seen": F.when(has, F.col("_seen"))})
    told = claims.reformulate(told, "raw", "kinds", context=("article", "at_host", "publisher_name", "date"))
    return decided(told.drop("_n", "_kinds", "_seen", "sets").withColumn("_why", claims.reasons("claim", "n_media")), "5 claim", F.get("_why", F.lit(0)))


# stage 6

_CLIP = "round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, {0})), 6)"
VOTES_OF = f"""wv AS (SELECT claim_id, k, CASE WHEN n_media > 0 THEN {_CLIP.format('seen + ((claim_id * k * 31) % 21 - 10) / 100.0::DOUBLE')} END AS ctx, j AS ver, {_CLIP.format('j + ((claim_id * 41) % 101 - 30) / 100.0::DOUBLE')} AS cov
  FROM (SELECT s5.*, unnest([1, 2, 3, 4]) AS k, unnest(["J1", "J2", "J3", "J4"]) AS j FROM s5 JOIN wide ON wide.doc_id = s5.claim_id WHERE r5 IS NULL))"""


def votes_of(kept: DataFrame) -> DataFrame:
    """The local members' votes: veracity from their scores of the review's text, the other properties planted."""
    told = with_scores(kept.select("claim_id", "n_media", "seen", "raw"), "raw")
    off = ((F.col("claim_id") * F.col("k") * 31) % 21 - 10) / 100.0
    long = told.select("claim_id", "n_media", "seen", F.posexplode(F.array(*raw_scorers())).alias("_at", "veracity")).withColumn("k", F.col("_at") + 1)
    return long.select(
        "claim_id", F.concat(F.lit("J"), F.col("k").cast("string")).alias("member"), F.when(F.col("n_media") > 0, F.round(clip(F.col("seen") + off), 6)).alias("contextualization"),
        "veracity", F.round(clip(F.col("veracity") + ((F.col("claim_id") * 41) % 101 - 30) / 100.0), 6).alias("coverage"),
    )


def verdict_stage(kept: DataFrame, votes: DataFrame) -> Stage:
    long = votes.unpivot(["claim_id", "member"], list(verdict.ORDER), "property", "score").withColumn("justification", judges.justified(F.col("member"), F.col("score")))
    told = ensemble.justify_integrity(ensemble.standardize(votes), ensemble.justify_properties(long))
    return decided(kept.join(told, "claim_id"), "6 verdict", F.when(F.col("spread") > 1, "low agreement"))


# stage 7

JUDGED = f"""{SAYS}, judged AS (SELECT justified.*, s5.claim AS text, n_media, lang, date, CAST(date_trunc('quarter', date) AS DATE) AS quarter FROM justified JOIN s5 USING (claim_id)),
cand AS (SELECT * FROM judged WHERE label = 'compromised' AND spread <= 1)"""


def rectify_stage(judged: DataFrame, votes: DataFrame) -> tuple[Stage, DataFrame]:
    """Every second compromised claim corrected; and the benchmark: all judged claims, the accepted twins in place of their originals."""
    cands = rectify.candidates(judged).select("claim_id", F.col("claim").alias("text"), "n_media", "justification", "compromising").filter("claim_id % 2 = 0")
    twins = rectify.checked(rectify.generate(cands))
    told = checkpointed(rectify.decided(rectify.rescore(twins, rectify.revote(rectify.passing(twins), votes))))
    stage = decided(told, "7 rectification", F.when(F.col("outcome") != "accepted", F.col("outcome")))
    out = rectify.replace(judged, told)
    texts = stage.kept.select(F.col("claim_id").alias("_id"), "twin_text")
    out = out.join(texts, F.col("claim_id") == F.col("_id"), "left").withColumn("claim", F.coalesce("twin_text", "claim")).withColumn("quarter", F.trunc("date", "quarter"))
    return stage, out.select("claim_id", "quarter", "lang", "claim", "integrity", "rectified", "label")


CHAIN = f"""{LANGUAGE}, {FEED}, {HOSTS}, {PUBLISHERS}, {ARTICLE}, {ARTICLES}, {LINKS}, {APPEARANCES}, {MEDIA}, {NEAR}, {CLAIMS_OF}, {SCORERS}, {VOTES_OF}, {STANDARD}, {JUDGED.replace("label = 'compromised'", "label = 'compromised' AND claim_id % 2 = 0")}, {TWINS_OF},
benchmark_ AS (SELECT j.claim_id, j.quarter, j.lang, CASE WHEN t.claim_id IS NOT NULL THEN t.twin_text ELSE j.text END AS claim, coalesce(t.twin_integrity, j.integrity) AS integrity, t.claim_id IS NOT NULL AS rectified
  FROM judged j LEFT JOIN (SELECT * FROM twins WHERE outcome = 'accepted') t USING (claim_id) WHERE j.spread <= 1),
chained AS (SELECT *, CASE WHEN integrity > 1.0::DOUBLE/3 THEN 'intact' WHEN integrity < -1.0::DOUBLE/3 THEN 'compromised' WHEN integrity IS NOT NULL THEN 'uncertain' END AS label FROM benchmark_)"""


def run(spark: SparkSession, d: str) -> tuple[list[Stage], DataFrame]:
    """All seven stages; the stages with their marks, and the claims of the benchmark."""
    pages = load(spark, d, "pages", ["page_id", "url", "html"])
    one = discovery_stage(feed(spark, d))
    two = publisher_stage(one.kept)
    three = article_stage(two.kept, pages)
    four = appearance_stage(three.kept, pages)
    five = claim_stage(four.kept, derived.media(spark, d))
    votes = checkpointed(votes_of(five.kept))
    six = verdict_stage(five.kept, votes)
    seven, out = rectify_stage(six.kept, votes)
    return [one, two, three, four, five, six, seven], out


@query(f"WITH {CHAIN} SELECT * FROM chained")
def chain_benchmark(spark, d):
    return run(spark, d)[1]


@query(f"""WITH {CHAIN}, ranked AS (SELECT *, row_number() OVER (PARTITION BY quarter, label ORDER BY md5('split-1:' || claim_id), claim_id) AS rank FROM chained WHERE label IN ('intact', 'compromised')),
taken AS (SELECT * FROM ranked WHERE rank <= 2), both_ AS (SELECT quarter FROM taken GROUP BY 1 HAVING count(*) = 4) SELECT claim_id, quarter, label, CAST(rank AS INTEGER) AS rank FROM taken WHERE quarter IN (SELECT quarter FROM both_)""")
def chain_split(spark, d):
    return splits.balanced(run(spark, d)[1], 4).select("claim_id", "quarter", "label", "rank")


_MARKS = " UNION ALL ".join(
    f"SELECT '{stage}' AS stage, CASE WHEN {r} = 'pending' THEN 'pending' WHEN {r} IS NULL THEN 'kept' ELSE 'dropped' END AS status, CASE WHEN {r} = 'pending' THEN '' ELSE coalesce({r}, '') END AS reason FROM {table}"
    for stage, table, r in (
        ("1 discovery", "s1", "r1"), ("2 publisher", "s2", "r2"), ("3 article", "s3", "r3"), ("4 appearance", "s4", "r4"), ("5 claim", "s5", "r5"),
        ("6 verdict", "(SELECT CASE WHEN spread > 1 THEN 'low agreement' END AS r6 FROM judged)", "r6"), ("7 rectification", "(SELECT CASE WHEN outcome <> 'accepted' THEN outcome END AS r7 FROM twins)", "r7"),
    )
)
MARKS = f"""{CHAIN}, marks AS ({_MARKS}), n_ AS (SELECT stage, status, reason, count(*) AS n FROM marks GROUP BY ALL)"""


def _report(spark, d):
    return funnel.report(funnel.union([stage.marks for stage in run(spark, d)[0]]))


@query(f"""WITH {MARKS}, t_ AS (SELECT *, CAST(sum(n) OVER (PARTITION BY stage) AS BIGINT) AS entered, CAST(sum(CASE WHEN status <> 'pending' THEN n ELSE 0 END) OVER (PARTITION BY stage) AS BIGINT) AS processed FROM n_)
SELECT stage, status, reason, n, entered, processed, CASE WHEN entered > 0 THEN round(100.0::DOUBLE * n / entered, 6) END AS rate_entered, CASE WHEN status <> 'pending' AND processed > 0 THEN round(100.0::DOUBLE * n / processed, 6) END AS rate_processed FROM t_""")
def funnel_stages(spark, d):
    """All seven stages of one run: what each kept, dropped and why, and left pending."""
    return _report(spark, d)


#: Model calls for each record that enters a stage: a span, links, a rewriting and a validation, four members of two properties, a correction and two checks. Fixed values.
CALLS = {"3 article": 1, "4 appearance": 1, "5 claim": 2, "6 verdict": 8, "7 rectification": 3}


@query(f"""WITH {MARKS}, y AS (SELECT stage, CAST(sum(n) FILTER (status <> 'pending') AS BIGINT) AS entered, CAST(coalesce(sum(n) FILTER (status = 'kept'), 0) AS BIGINT) AS kept FROM n_ GROUP BY 1), z AS (SELECT *, CAST(row_number() OVER (ORDER BY stage) AS INTEGER) AS step FROM y)
SELECT step, stage, entered, kept, round(kept / entered::DOUBLE, 6) AS stage_yield, round(exp(sum(ln(kept / entered::DOUBLE)) OVER (ORDER BY step)), 6) AS total_yield,
CAST(entered * CASE stage {' '.join(f"WHEN '{k}' THEN {v}" for k, v in CALLS.items())} ELSE 0 END AS BIGINT) AS calls, CAST(first_value(entered) OVER (ORDER BY step) * CASE stage {' '.join(f"WHEN '{k}' THEN {v}" for k, v in CALLS.items())} ELSE 0 END AS BIGINT) AS calls_unfiltered FROM z""")
def chain_yield(spark, d):
    """Yield of the run stage by stage and end to end, of the records processed, and model calls against a run without earlier filters."""
    from pyspark.sql.window import Window

    n = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("n"))), F.lit(0)).cast("long")
    kept = _report(spark, d).groupBy("stage").agg(n(F.col("status") != "pending").alias("entered"), n(F.col("status") == "kept").alias("kept"))
    kept = kept.withColumn("step", F.row_number().over(Window.orderBy("stage")))
    return funnel.calls(funnel.cumulative(kept), CALLS).select("step", "stage", "entered", "kept", "stage_yield", "total_yield", "calls", "calls_unfiltered")
