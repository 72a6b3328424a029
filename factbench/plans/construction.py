"""Workloads of the construction pipeline, stages 1 to 7, over the given tables; SQL beside each that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factbench.functions import html, text, url
from factbench.functions.scores import decide
from factbench.functions.text import STOP_WORDS
from factbench.operators import appearances, articles, claims, discovery, ensemble, judges, media, publishers, rectify, splits, verdict
from factbench.operators.metrics import bin_index
from factbench.sources import derived
from factbench.sources.io import checkpointed, load, spread

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    """Register a workload under its function's name."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


# SQL for the derived inputs
CLAIMS = """claims AS (SELECT o_orderkey AS claim_id, o_orderdate AS claim_ts, CAST(date_trunc('quarter', o_orderdate) AS DATE) AS quarter,
  ((o_custkey * 7919) % 2001 - 1000) / 1000.0::DOUBLE AS veracity, ((o_orderkey * 104729) % 2001 - 1000) / 1000.0::DOUBLE AS coverage,
  o_custkey % 5 < 2 AS english, o_orderpriority AS raw_rating, o_orderstatus AS status FROM orders)"""
CLAIM_MEDIA = """claim_media AS (SELECT l_orderkey AS claim_id, round(1 - 25 * l_tax, 6) AS authenticity, round(1 - 20 * l_discount, 6) AS contextualization, l_returnflag = 'R' AS is_video FROM lineitem)"""
OVER_MEDIA = "over_media AS (SELECT claim_id, min(authenticity) AS authenticity, min(contextualization) AS contextualization, count(*) AS n_media FROM claim_media GROUP BY 1)"


def _evaluated(early: bool = True, source: str = "SELECT c.*, m.authenticity, m.contextualization AS ctx, coalesce(m.n_media, 0) AS n_media FROM claims c LEFT JOIN over_media m USING (claim_id)") -> str:
    ver = "CASE WHEN NOT (coalesce(ctx, 1.0) < -1.0::DOUBLE/3) THEN veracity END" if early else "veracity"
    cov = "CASE WHEN NOT (coalesce(ctx, 1.0) < -1.0::DOUBLE/3) AND NOT (coalesce(ver, 1.0) < -1.0::DOUBLE/3) THEN coverage END" if early else "coverage"
    return f"""base AS ({source}), e1 AS (SELECT *, {ver} AS ver FROM base), e2 AS (SELECT *, {cov} AS cov FROM e1), e3 AS (SELECT *, least(ctx, ver, cov) AS integrity FROM e2),
verdicts AS (SELECT *, CASE WHEN ctx = integrity THEN 'contextualization' WHEN ver = integrity THEN 'veracity' WHEN cov = integrity THEN 'coverage' END AS compromising,
  CASE WHEN integrity > 1.0::DOUBLE/3 THEN 'intact' WHEN integrity < -1.0::DOUBLE/3 THEN 'compromised' WHEN integrity IS NOT NULL THEN 'uncertain' END AS label FROM e3)"""


VERDICTS = f"{CLAIMS}, {CLAIM_MEDIA}, {OVER_MEDIA}, {_evaluated()}"


def _verdicts(spark: SparkSession, d: str, **options) -> DataFrame:
    return verdict.verdicts(derived.claims(spark, d), derived.claim_media(spark, d), **options)


def _documents(spark, d):
    return spread(load(spark, d, "documents", ["doc_id", "text"]))


# stage 1


def _count_in(words: tuple[str, ...]) -> str:
    return "len(list_filter(toks, lambda t: t IN (" + ", ".join(f"'{w}'" for w in words) + ")))"


LANGUAGE = (
    r"toks_ AS (SELECT *, list_filter(regexp_split_to_array(lower(text), '[^\p{L}]+'), lambda t: t <> '') AS toks FROM documents), "
    + "score_ AS (SELECT *, " + ", ".join(f"{_count_in(w)} / greatest(1, len(toks))::DOUBLE AS s_{lang}" for lang, w in STOP_WORDS.items()) + " FROM toks_), "
    + "told AS (SELECT *, greatest(s_en, s_fr, s_de, s_es) AS best FROM score_), "
    + "guess AS (SELECT *, CASE WHEN best > 0 THEN CASE " + " ".join(f"WHEN s_{lang} = best THEN '{lang}'" for lang in STOP_WORDS) + " END END AS detected FROM told)"
)


@query(f"WITH {LANGUAGE} SELECT lang, count(*) AS n, round(100.0::DOUBLE * avg(CASE WHEN detected = lang THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM guess GROUP BY lang")
def language_identify_accuracy(spark, d):
    told = spread(load(spark, d, "documents", ["lang", "text"])).withColumn("detected", text.language("text"))
    hit = F.coalesce((F.col("detected") == F.col("lang")).cast("double"), F.lit(0.0))
    return told.groupBy("lang").agg(F.count(F.lit(1)).alias("n"), F.round(100.0 * F.avg(hit), 6).alias("accuracy"))


@query(f"WITH {LANGUAGE} SELECT doc_id, CASE WHEN doc_id % 3 = 0 THEN coalesce(detected) ELSE lang END AS lang FROM guess")
def language_fill(spark, d):
    docs = spread(load(spark, d, "documents", ["doc_id", "lang", "text"])).withColumn("lang", F.when(F.col("doc_id") % 3 != 0, F.col("lang")))
    return discovery.fill_language(docs).select("doc_id", "lang")


@query("SELECT doc_id, text AS claim, source AS publisher_name FROM documents QUALIFY row_number() OVER (PARTITION BY text ORDER BY doc_id) = 1")
def review_dedup(spark, d):
    docs = load(spark, d, "documents", ["doc_id", "text", "source"]).withColumnsRenamed({"text": "claim", "source": "publisher_name"})
    return discovery.dedup_reviews(docs, ["claim"], ["doc_id"])


@query("SELECT CASE WHEN doc_id % 7 <> 0 THEN doc_id END AS doc_id, CASE WHEN doc_id % 7 <> 0 THEN text END AS claim, CASE WHEN doc_id % 7 <> 0 THEN source END AS publisher_name, doc_id % 7 = 0 AS malformed FROM documents")
def review_parse(spark, d):
    """The feed parser on all documents written as review markup, every seventh record planted as malformed."""
    docs = load(spark, d, "documents", ["doc_id", "text", "source"])
    good = F.to_json(F.struct(F.col("text").alias("claimReviewed"), F.col("doc_id").cast("string").alias("url"), F.struct(F.col("source").alias("name")).alias("author")))
    raw = docs.select(F.when(F.col("doc_id") % 7 != 0, good).otherwise(F.lit("{broken")).alias("raw"))
    return discovery.parse_reviews(raw).select(F.col("url").cast("long").alias("doc_id"), "claim", "publisher_name", "malformed")


@query("SELECT page_id, 'Claim of page ' || page_id AS claim, 'false' AS rating FROM pages WHERE page_id % 3 = 0")
def review_markup_in_pages(spark, d):
    """Linked data planted in every third page, found and parsed as reviews."""
    p = load(spark, d, "pages", ["page_id", "html"])
    block = F.to_json(F.struct(F.concat(F.lit("Claim of page "), F.col("page_id").cast("string")).alias("claimReviewed"), F.concat(F.lit("https://r.example/"), F.col("page_id").cast("string")).alias("url"), F.struct(F.lit("false").alias("alternateName")).alias("reviewRating")))
    planted = p.withColumn("html", F.when(F.col("page_id") % 3 == 0, F.concat("html", F.lit('<script type="application/ld+json">'), block, F.lit("</script>"))).otherwise(F.col("html")))
    parsed = discovery.parse_reviews(discovery.markup_from_html(planted))
    return parsed.select(F.regexp_extract("url", "([0-9]+)$", 1).cast("long").alias("page_id"), "claim", "rating")


# stage 2

HOSTS = r"hosts AS (SELECT page_id, url, lower(regexp_extract(url, '^[a-zA-Z]+://(?:[^/?#@]*@)?([^/?#:]+)', 1)) AS host, html FROM pages), pubs AS (SELECT *, regexp_extract(host, '([^.]+\.[^.]+)$', 1) AS publisher FROM hosts)"
#: Credible publishers among the given pages. Fixed values.
CREDIBLE = ("example.com", "example.org")


def _pages(spark, d):
    return publishers.with_publisher(load(spark, d, "pages", ["page_id", "url"]))


def _credible(spark):
    return spark.createDataFrame([(c,) for c in CREDIBLE], "domain string")


@query(f"WITH {HOSTS} SELECT host, count(*) AS n_reviews FROM pubs GROUP BY host")
def publisher_census(spark, d):
    return publishers.census(_pages(spark, d), "host")


@query(f"WITH {HOSTS} SELECT count(DISTINCT host) AS n_publishers FROM pubs")
def publisher_count(spark, d):
    return publishers.n_publishers(_pages(spark, d), "host")


@query(f"WITH {HOSTS} SELECT page_id, host FROM pubs WHERE publisher IN {CREDIBLE}")
def publisher_retain(spark, d):
    return publishers.retain_credible(_pages(spark, d), _credible(spark)).select("page_id", "host")


@query(f"WITH {HOSTS} SELECT page_id, host FROM pubs WHERE publisher NOT IN {CREDIBLE}")
def publisher_dropped(spark, d):
    return publishers.dropped(_pages(spark, d), _credible(spark)).select("page_id", "host")


@query(f"WITH {HOSTS} SELECT host FROM pubs GROUP BY host HAVING count(*) >= 5 AND avg(CASE WHEN url LIKE 'https:%' THEN 1.0 ELSE 0.0 END) >= 0.5")
def publisher_derived(spark, d):
    return publishers.derive_credible(_pages(spark, d).withColumn("secure", F.col("url").startswith("https:")), 5, 0.5, "secure", "host")


@query(f"WITH {HOSTS} SELECT page_id FROM pubs WHERE host LIKE '%.org'")
def publisher_suffix(spark, d):
    return publishers.by_suffix(load(spark, d, "pages", ["page_id", "url"]), (".org",)).select("page_id")


def _replaced(column: str, patterns: tuple[str, ...], by: str = "''") -> str:
    for p in patterns:
        column = f"regexp_replace({column}, '{p}', {by}, 'g')"
    return column


CANONICAL = r"""canon AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(regexp_replace(url, '[?#].*$', ''), '^[a-zA-Z]+://(?:www\.|m\.)*', 'https://'), '\.(?:html|htm|php)$', ''), '/+$', '') AS c FROM pages)"""


@query(rf"WITH {CANONICAL} SELECT page_id, 'https://' || lower(regexp_extract(c, '^https://([^/]*)', 1)) || regexp_extract(c, '^https://[^/]*(.*)$', 1) AS canonical FROM canon")
def url_canonical(spark, d):
    return load(spark, d, "pages", ["page_id", "url"]).select("page_id", url.canonical("url").alias("canonical"))


@query("SELECT page_id, url AS original, page_id % 2 = 0 AS archived FROM pages")
def url_unwrap_archive(spark, d):
    """Every second page's URL wrapped by an archive, some five times, then unwrapped."""
    p = load(spark, d, "pages", ["page_id", "url"])
    once = F.concat(F.lit("https://web.archive.example/web/20240102030405/"), "url")
    often = F.concat(F.lit("https://web.archive.example/web/2023/" * 2 + "https://old.example/2019id_/" * 2), once)
    given = p.withColumn("seen", F.when(F.col("page_id") % 4 == 0, often).when(F.col("page_id") % 2 == 0, once).otherwise(F.col("url")))
    return given.select("page_id", url.unwrap_archive("seen").alias("original"), url.is_archived("seen").alias("archived"))


# stage 3

_DENOISED = _replaced("html", tuple(p.replace("'", "''") for p in html.NOISE))


def _entities(c: str) -> str:
    for entity, char in html.ENTITIES:
        c = "replace({}, '{}', '{}')".format(c, entity, char.replace("'", "''"))
    return c


ARTICLE = (
    rf"clean1 AS (SELECT page_id, {_DENOISED} AS c FROM pages), "
    r"clean2 AS (SELECT page_id, c, regexp_extract(c, '(?s)<article[^>]*>(.*?)</article>', 1) AS art, regexp_extract(c, '(?s)<body[^>]*>(.*)</body>', 1) AS bod FROM clean1), "
    r"clean3 AS (SELECT page_id, CASE WHEN art <> '' THEN art WHEN bod <> '' THEN bod ELSE c END AS h FROM clean2), "
    rf"clean4 AS (SELECT page_id, {_entities(_replaced(_replaced('h', (html.BREAKS,), 'chr(10)'), ('<[^>]*>',)))} AS t FROM clean3), "
    r"article AS (SELECT page_id, regexp_replace(regexp_replace(regexp_replace(t, '[ \t]+', ' ', 'g'), ' ?\n[ \n]*', chr(10), 'g'), '^[ \n]+|[ \n]+$', '', 'g') AS article FROM clean4)"
)


@query(f"WITH {ARTICLE} SELECT page_id, article FROM article")
def article_clean(spark, d):
    return articles.with_article(spread(load(spark, d, "pages", ["page_id", "html"]))).select("page_id", "article")


@query(f"WITH {ARTICLE} SELECT count(*) AS n, CAST(sum(length(article)) AS BIGINT) AS chars, CAST(sum(CASE WHEN length(article) >= 300 THEN 1 ELSE 0 END) AS BIGINT) AS long_enough FROM article WHERE trim(article) <> ''")
def article_lengths(spark, d):
    a = articles.drop_inaccessible(articles.with_article(load(spark, d, "pages", ["page_id", "html"])))
    return a.agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("article").cast("long")).alias("chars"), F.sum((F.length("article") >= 300).cast("long")).alias("long_enough"))


@query(f"WITH {ARTICLE} SELECT page_id FROM article WHERE length(article) < 300")
def article_short(spark, d):
    a = articles.with_article(load(spark, d, "pages", ["page_id", "html"])).select("page_id", "article")
    return a.join(articles.drop_short(a, 300).select("page_id"), "page_id", "left_anti").select("page_id")


@query(r"""WITH b AS (SELECT page_id, html, regexp_extract(html, '(?s)<article[^>]*>(.*?)</article>', 1) AS body, strpos(html, '<article') AS at_, length(regexp_extract(html, '(?s)(<article[^>]*>)', 1)) AS tag FROM pages)
SELECT page_id, CAST(CASE WHEN body <> '' THEN at_ + tag - 1 END AS INTEGER) AS "start", CAST(CASE WHEN body <> '' THEN at_ + tag - 1 + length(body) END AS INTEGER) AS "end", CASE WHEN body <> '' THEN body END AS body FROM b""")
def article_body_span(spark, d):
    return articles.body_span(load(spark, d, "pages", ["page_id", "html"])).select("page_id", "start", "end", "body")


@query()
def article_density_span(spark, d):
    return articles.density_span(load(spark, d, "pages", ["page_id", "html"]))


@query()
def article_blocks(spark, d):
    return articles.blocks(load(spark, d, "pages", ["page_id", "html"])).select("page_id", "block_no", "start", "end", "link_share")


# stage 4

LINKS = r"""found AS (SELECT page_id, regexp_extract(url, '^([a-zA-Z]+://[^/?#]+)', 1) AS root, list_concat(regexp_extract_all(html, 'href="([^"]*)"', 1), regexp_extract_all(html, 'https?://[^\s"''<>]+')) AS hs FROM pages),
each_ AS (SELECT page_id, root, unnest(hs) AS href, generate_subscripts(hs, 1) AS at_ FROM found),
full_ AS (SELECT page_id, at_, CASE WHEN regexp_matches(href, '^[a-zA-Z]+://') THEN href WHEN href LIKE '/%' THEN root || href ELSE root || '/' || href END AS u FROM each_),
short AS (SELECT page_id, at_, regexp_replace(regexp_replace(regexp_replace(regexp_replace(u, '[?#].*$', ''), '^[a-zA-Z]+://(?:www\.|m\.)*', 'https://'), '\.(?:html|htm|php)$', ''), '/+$', '') AS c FROM full_),
named AS (SELECT page_id, at_, 'https://' || lower(regexp_extract(c, '^https://([^/]*)', 1)) || regexp_extract(c, '^https://[^/]*(.*)$', 1) AS url FROM short),
links AS (SELECT page_id, row_number() OVER (PARTITION BY page_id ORDER BY min(at_)) - 1 AS place, url FROM named GROUP BY page_id, url)"""


@query(f"WITH {LINKS} SELECT page_id, CAST(place AS INTEGER) AS place, url FROM links")
def appearance_links(spark, d):
    return appearances.extract(load(spark, d, "pages", ["page_id", "url", "html"]))


@query(f"WITH {LINKS} SELECT page_id, CAST(place AS INTEGER) AS place, url FROM links WHERE place < 2")
def appearance_cap2(spark, d):
    return appearances.cap(appearances.extract(load(spark, d, "pages", ["page_id", "url", "html"])), "page_id", ["place"]).drop("rank")


@query("SELECT doc_id AS review_id, CAST(p AS INTEGER) AS place, 'https://given.example/' || p || '/' || doc_id AS url FROM documents, (VALUES (0), (1)) t(p) WHERE doc_id % 8 = 0 UNION ALL SELECT doc_id, NULL, NULL FROM documents WHERE doc_id % 8 <> 0")
def appearance_given(spark, d):
    """Appearances that a feed names, planted for one review in eight; the others keep a row without any."""
    docs = load(spark, d, "documents", ["doc_id"]).withColumnRenamed("doc_id", "review_id")
    named = F.when(F.col("review_id") % 8 == 0, F.array(*[F.concat(F.lit(f"https://given.example/{p}/"), F.col("review_id").cast("string")) for p in (0, 1)]))
    return appearances.given(docs.withColumn("appearances", named))


@query("""WITH e AS (SELECT user_id AS claim_id, CAST(row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS INTEGER) AS place, event_id FROM events),
c AS (SELECT *, CASE WHEN event_id % 4 <> 0 THEN 'u' || event_id WHEN event_id % 8 = 0 THEN 'a' || event_id END AS chosen FROM e)
SELECT claim_id, place, chosen, chosen LIKE 'a%' AS from_archive FROM c WHERE chosen IS NOT NULL QUALIFY row_number() OVER (PARTITION BY claim_id ORDER BY place) <= 2""")
def appearance_retrieved(spark, d):
    """Two appearances a claim that could be fetched: a quarter of the originals is lost, half of these have an archived copy."""
    from pyspark.sql.window import Window

    e = load(spark, d, "events", ["event_id", "user_id", "ts"])
    name = lambda p: F.concat(F.lit(p), F.col("event_id").cast("string"))
    asked = e.select(F.col("user_id").alias("claim_id"), (F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1).alias("place"), name("u").alias("url"), name("a").alias("archived_url"))
    fetched = e.select(F.inline(F.array(F.struct(name("u").alias("url"), (F.col("event_id") % 4 != 0).alias("ok")), F.struct(name("a").alias("url"), (F.col("event_id") % 8 == 0).alias("ok")))))
    return appearances.retrieved(asked, fetched).select("claim_id", "place", "chosen", "from_archive")


CHOOSE = """ok AS (SELECT DISTINCT event_id FROM events WHERE event_type <> 'error'),
cand AS (SELECT event_id AS claim_id, event_id AS u, event_id + 1 AS a FROM events)"""


@query(f"""WITH {CHOOSE} SELECT claim_id, CASE WHEN o.event_id IS NOT NULL THEN u ELSE a END AS chosen, o.event_id IS NULL AS from_archive
FROM cand LEFT JOIN ok o ON o.event_id = u LEFT JOIN ok r ON r.event_id = a WHERE o.event_id IS NOT NULL OR r.event_id IS NOT NULL""")
def appearance_choose(spark, d):
    """Events as a fetch log: an error is a failed download, and the next event's id the archived copy."""
    e = load(spark, d, "events", ["event_id", "event_type"])
    cands = e.select(F.col("event_id").alias("claim_id"), F.lit(0).alias("place"), F.col("event_id").alias("url"), (F.col("event_id") + 1).alias("archived_url"))
    fetched = e.select(F.col("event_id").alias("url"), (F.col("event_type") != "error").alias("ok"))
    return appearances.choose(cands, fetched).select("claim_id", "chosen", "from_archive")


@query("SELECT event_id AS media_id, value AS seconds, 2 * CAST(json_extract_string(props, '$.k') AS INTEGER) AS mb FROM events WHERE value <= 300 AND 2 * CAST(json_extract_string(props, '$.k') AS INTEGER) <= 128")
def media_limits(spark, d):
    e = load(spark, d, "events", ["event_id", "value", "props"])
    files = e.select(F.col("event_id").alias("media_id"), F.col("value").alias("seconds"), (2 * F.get_json_object("props", "$.k").cast("int")).alias("mb"))
    return media.within_limits(files)


@query("SELECT o_orderkey AS claim_id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def appearance_without(spark, d):
    c = load(spark, d, "orders", ["o_orderkey"]).withColumnRenamed("o_orderkey", "claim_id")
    return appearances.without(c, derived.claim_media(spark, d).select("claim_id"), "claim_id")


# stage 5

MEDIA = """media AS (SELECT vec_id AS media_id, vec_id // 10 AS claim_id, vec_id % 3 = 0 AS is_video, CAST((vec_id // 3) % 3 AS INTEGER) AS origin, embedding::DOUBLE[] AS embedding FROM embeddings
UNION ALL SELECT vec_id + 1000000, vec_id // 10, (vec_id + 1000000) % 3 = 0, 2, list_prepend(embedding[1]::DOUBLE + 0.01::DOUBLE, embedding[2:]::DOUBLE[]) FROM embeddings WHERE vec_id % 5 = 0)"""
NEAR = """near_ AS (SELECT a.claim_id, a.media_id AS kept_id, b.media_id AS dropped_id, list_cosine_similarity(a.embedding, b.embedding) AS sim FROM media a JOIN media b ON a.claim_id = b.claim_id AND (a.origin, a.media_id) < (b.origin, b.media_id))"""


@query(f"WITH {MEDIA}, {NEAR} SELECT claim_id, media_id, is_video, origin FROM media WHERE (claim_id, media_id) NOT IN (SELECT (claim_id, dropped_id) FROM near_ WHERE sim > 0.85)")
def media_dedup(spark, d):
    return media.dedup(derived.media(spark, d)).select("claim_id", "media_id", "is_video", "origin")


#: Chains: copies turned by a few degrees each, so that neighbours are similar and ends are not; some items are in two claims.
CHAINS = """chains AS (SELECT e.vec_id * 100 + k AS media_id, e.vec_id // 5 AS claim_id, false AS is_video, CAST((e.vec_id + k) % 3 AS INTEGER) AS origin,
  list_transform(e.embedding::DOUBLE[], lambda x, i: x * cos(k * 0.4::DOUBLE) + f.embedding[i]::DOUBLE * sin(k * 0.4::DOUBLE)) AS embedding
  FROM embeddings e JOIN embeddings f ON f.vec_id = e.vec_id + 1, (VALUES (0), (1), (2), (3)) t(k) WHERE e.vec_id % 5 = 0
UNION ALL SELECT e.vec_id * 100, e.vec_id // 5 + 1, false, 0, list_transform(e.embedding::DOUBLE[], lambda x, i: x) FROM embeddings e WHERE e.vec_id % 10 = 0 AND e.vec_id + 1 IN (SELECT vec_id FROM embeddings))"""
CHAIN_NEAR = """near_ AS (SELECT a.claim_id, a.media_id AS kept_id, b.media_id AS dropped_id, a.origin AS a_origin, b.origin AS b_origin FROM chains a JOIN chains b ON a.claim_id = b.claim_id AND (a.origin, a.media_id) < (b.origin, b.media_id)
  WHERE list_cosine_similarity(a.embedding, b.embedding) > 0.85)"""


@query(f"WITH {CHAINS}, {CHAIN_NEAR} SELECT claim_id, media_id, origin FROM chains WHERE (claim_id, media_id) NOT IN (SELECT (claim_id, dropped_id) FROM near_)")
def media_dedup_pairwise_chains(spark, d):
    return media.dedup(derived.media_chains(spark, d)).select("claim_id", "media_id", "origin")


@query(f"""WITH RECURSIVE {CHAINS}, {CHAIN_NEAR},
placed AS (SELECT claim_id, media_id, row_number() OVER (PARTITION BY claim_id ORDER BY origin, media_id) AS at_ FROM chains),
walk AS (SELECT claim_id, 0 AS at_, CAST([] AS BIGINT[]) AS kept FROM placed GROUP BY 1
  UNION ALL SELECT w.claim_id, w.at_ + 1, CASE WHEN len(list_filter(w.kept, lambda k: list_contains(p.rivals, k))) > 0 THEN w.kept ELSE list_append(w.kept, p.media_id) END
  FROM walk w JOIN (SELECT x.claim_id, x.media_id, x.at_, coalesce(list(n.kept_id) FILTER (n.kept_id IS NOT NULL), CAST([] AS BIGINT[])) AS rivals FROM placed x LEFT JOIN near_ n ON n.claim_id = x.claim_id AND n.dropped_id = x.media_id GROUP BY 1, 2, 3) p ON p.claim_id = w.claim_id AND p.at_ = w.at_ + 1),
done AS (SELECT claim_id, unnest(arg_max(kept, at_)) AS media_id FROM walk GROUP BY 1) SELECT claim_id, media_id, origin FROM chains JOIN done USING (claim_id, media_id)""")
def media_dedup_greedy(spark, d):
    return media.dedup(derived.media_chains(spark, d), mode="greedy").select("claim_id", "media_id", "origin")


@query(f"""WITH RECURSIVE {CHAINS}, {CHAIN_NEAR}, links AS (SELECT claim_id, kept_id AS a, dropped_id AS b FROM near_ UNION SELECT claim_id, dropped_id, kept_id FROM near_),
reach AS (SELECT claim_id, media_id AS a, media_id AS r FROM chains UNION SELECT reach.claim_id, reach.a, l.b FROM reach JOIN links l ON l.claim_id = reach.claim_id AND l.a = reach.r),
groups AS (SELECT claim_id, a AS media_id, min(r) AS grp FROM reach GROUP BY 1, 2)
SELECT claim_id, media_id, origin FROM chains JOIN groups USING (claim_id, media_id) QUALIFY row_number() OVER (PARTITION BY claim_id, grp ORDER BY origin, media_id) = 1""")
def media_dedup_components(spark, d):
    return media.dedup(derived.media_chains(spark, d), mode="components").select("claim_id", "media_id", "origin")


@query(f"""WITH {MEDIA}, {NEAR}, kept AS (SELECT * FROM media WHERE (claim_id, media_id) NOT IN (SELECT (claim_id, dropped_id) FROM near_ WHERE sim > 0.85))
SELECT claim_id, media_id, CAST(row_number() OVER (PARTITION BY claim_id ORDER BY is_video DESC, origin, media_id) AS INTEGER) AS rank FROM kept QUALIFY rank <= 4""")
def media_cap4(spark, d):
    return media.cap(media.dedup(derived.media(spark, d))).select("claim_id", "media_id", "rank")


PAIRS = """pairs AS (SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS similarity FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id)"""


def _vectors(spark, d):
    return load(spark, d, "embeddings", ["vec_id", "embedding"]).withColumnRenamed("vec_id", "media_id")


@query(f"WITH {PAIRS} SELECT a, b, similarity FROM pairs WHERE similarity > 0.35")
def media_near_pairs(spark, d):
    return media.exact_pairs(_vectors(spark, d), 0.35)


@query(f"WITH {MEDIA} SELECT a.media_id AS a, b.media_id AS b, round(list_cosine_similarity(a.embedding, b.embedding), 6) AS similarity FROM media a JOIN media b ON a.media_id < b.media_id WHERE round(list_cosine_similarity(a.embedding, b.embedding), 6) > 0.85")
def media_near_pairs_lsh(spark, d):
    """Random-hyperplane buckets on the planted copies; at their similarity recall is one but for a chance below 1e-9."""
    return media.near_pairs(derived.media(spark, d).select("media_id", "embedding"), 0.85)


@query("SELECT event_type, CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 ELSE 3 END AS precedence, count(*) AS n FROM events GROUP BY 1, 2")
def media_precedence(spark, d):
    """Events as media of three origins, and of none that is known."""
    e = load(spark, d, "events", ["event_type"])
    origin = F.when(F.col("event_type") == "view", "original").when(F.col("event_type") == "click", "archived").when(F.col("event_type") == "purchase", "article").otherwise("elsewhere")
    return e.groupBy("event_type", media.precedence(origin).alias("precedence")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT vec_id AS media_id FROM embeddings WHERE label = (vec_id // 10) % 10")
def media_relevant(spark, d):
    e = load(spark, d, "embeddings", ["vec_id", "label"]).select(F.col("vec_id").alias("media_id"), "label", F.expr("cast((vec_id div 10) % 10 as int)").alias("claim_label"))
    return media.retain_relevant(e, lambda claim, own: claim == own).select("media_id")


REWRITTEN = rf"""squeezed AS (SELECT doc_id, regexp_replace(regexp_replace(regexp_replace(text, '[ \t\n\r]+', ' ', 'g'), '^ | $', '', 'g'), '{claims.LEAD_IN}', '') AS c FROM documents),
rewritten AS (SELECT doc_id, CASE WHEN regexp_extract(c, '(?s)^(.*?[.!?])(?:\s|$)', 1) <> '' THEN regexp_extract(c, '(?s)^(.*?[.!?])(?:\s|$)', 1) ELSE c END AS claim FROM squeezed)"""


@query(f"WITH {REWRITTEN} SELECT doc_id, claim || CASE WHEN doc_id % 3 = 0 THEN ' [video]' WHEN doc_id % 3 = 1 THEN ' [image, image]' ELSE '' END AS claim FROM rewritten")
def claim_rewrite(spark, d):
    kinds = F.when(F.col("doc_id") % 3 == 0, F.array(F.lit("video"))).when(F.col("doc_id") % 3 == 1, F.array(F.lit("image"), F.lit("image"))).otherwise(F.expr("cast(array() as array<string>)"))
    docs = _documents(spark, d).withColumn("kinds", kinds)
    return claims.reformulate(docs, "text", "kinds").select("doc_id", "claim")


_N_WORDS = r"len(regexp_split_to_array(regexp_replace({0}, '^[ \t\n\r]+|[ \t\n\r]+$', '', 'g'), '[ \t\n\r]+'))"


@query(
    rf"SELECT doc_id, concat_ws('; ', CASE WHEN trim(coalesce(text, '')) = '' THEN 'empty' END, CASE WHEN regexp_matches(text, '{claims._any(claims.VERDICT_WORDS)}') THEN 'verdict exposed' END, CASE WHEN regexp_matches(text, '{claims._any(claims.MEDIA_WORDS)}') AND doc_id % 2 = 0 THEN 'media missing' END, CASE WHEN "
    + _N_WORDS.format("text") + " > 70 THEN 'too long' END) AS reasons FROM documents"
)
def claim_validate(spark, d):
    docs = _documents(spark, d).withColumn("n_media", (F.col("doc_id") % 2).cast("int"))
    return claims.with_reasons(docs, "text", "n_media").select("doc_id", F.array_join("reasons", "; ").alias("reasons"))


@query("SELECT item_id, " + _N_WORDS.format("text") + " > 70 AS too_long FROM benchmark")
def claim_too_long(spark, d):
    return load(spark, d, "benchmark").select("item_id", claims.too_long("text").alias("too_long"))


# stage 6

RATING = "rating AS (SELECT * FROM (VALUES ('1-urgent', 1.0::DOUBLE), ('2-high', 0.5), ('3-medium', 0.0), ('4-not specified', -0.5), ('5-low', -1.0)) r(raw, score))"


@query(f"WITH {RATING} SELECT o_orderstatus AS status, count(*) AS n, round(avg(score), 6) AS mean_score FROM orders LEFT JOIN rating ON lower(trim(o_orderpriority)) = raw GROUP BY 1")
def rating_map(spark, d):
    rated = verdict.map_rating(derived.claims(spark, d), "raw_rating", judges.rating_table(spark))
    return rated.groupBy("status").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("score"), 6).alias("mean_score"))


@query(f"WITH {VERDICTS} SELECT claim_id, authenticity, ctx AS contextualization, ver AS veracity, cov AS coverage FROM verdicts")
def verdict_properties(spark, d):
    return _verdicts(spark, d).select("claim_id", "authenticity", "contextualization", "veracity", "coverage")


@query(f"WITH {VERDICTS} SELECT claim_id, integrity, compromising, label FROM verdicts")
def verdict_integrity(spark, d):
    return _verdicts(spark, d).select("claim_id", "integrity", "compromising", "label")


@query(f"WITH {CLAIMS}, {CLAIM_MEDIA}, {OVER_MEDIA}, {_evaluated(False)} SELECT claim_id, integrity, compromising, label FROM verdicts")
def verdict_no_early_stop(spark, d):
    return _verdicts(spark, d, early_stop=False).select("claim_id", "integrity", "compromising", "label")


@query(f"WITH {CLAIMS}, {_evaluated(source='SELECT c.*, NULL::DOUBLE AS authenticity, NULL::DOUBLE AS ctx, 0 AS n_media FROM claims c')} SELECT claim_id, integrity, compromising, label FROM verdicts")
def verdict_text_only(spark, d):
    return verdict.verdicts(derived.claims(spark, d), None).select("claim_id", "integrity", "compromising", "label")


@query(f"WITH {CLAIMS}, {CLAIM_MEDIA}, over_media AS (SELECT claim_id, avg(authenticity) AS authenticity, avg(contextualization) AS contextualization, count(*) AS n_media FROM claim_media GROUP BY 1), {_evaluated()} SELECT label, count(*) AS n FROM verdicts GROUP BY label")
def verdict_mean_over_media(spark, d):
    media = derived.claim_media(spark, d, placed=True)  # added in the order of the table's rows, as one thread of SQL would
    return verdict.verdicts(derived.claims(spark, d), media, how="mean", order=derived.PLACE).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query(f"""WITH {VERDICTS}, c AS (SELECT 4 * (2 * n_media + CASE WHEN coalesce(ctx, 1.0) < -1.0::DOUBLE/3 THEN 0 ELSE 1 + CASE WHEN ver >= -1.0::DOUBLE/3 THEN 1 ELSE 0 END END) AS stop_, 4 * (2 * n_media + 2) AS all_ FROM verdicts)
SELECT CAST(sum(stop_) AS BIGINT) AS with_stop, CAST(sum(all_) AS BIGINT) AS without_stop, round(sum(stop_)::DOUBLE / sum(all_), 6) AS ratio FROM c""")
def verdict_call_savings(spark, d):
    return verdict.call_savings(derived.claims(spark, d), derived.claim_media(spark, d))


@query(f"WITH {VERDICTS}, l AS (SELECT unnest(['contextualization', 'veracity', 'coverage']) AS property, unnest([ctx, ver, cov]) AS score FROM verdicts) SELECT property, CASE WHEN score < -1.0::DOUBLE/3 THEN 'negative' WHEN score > 1.0::DOUBLE/3 THEN 'positive' WHEN score IS NOT NULL THEN 'unknown' END AS decision, count(*) AS n FROM l GROUP BY ALL")
def verdict_decisions(spark, d):
    long = _verdicts(spark, d).unpivot(["claim_id"], list(verdict.ORDER), "property", "score")
    return long.groupBy("property", decide("score").alias("decision")).agg(F.count(F.lit(1)).alias("n"))


SCORERS = r"""parts AS (SELECT doc_id, string_split(text, chr(10)) AS ls, regexp_split_to_array(regexp_replace(text, '^[ \t\n\r]+|[ \t\n\r]+$', '', 'g'), '[ \t\n\r]+') AS ws, length(regexp_replace(text, '[\p{L}\p{N} \t\n\r]', '', 'g')) / greatest(1, length(text))::DOUBLE AS sym, text FROM documents),
raw_ AS (SELECT doc_id, text, ws, 2 * (len(list_distinct(ls)) / len(ls)::DOUBLE) - 1 AS r1, 1 - 30 * abs(sym - 0.02::DOUBLE) AS r2, (len(ws) - 50) / 100::DOUBLE AS r3, 2 * (len(list_distinct(ws)) / len(ws)::DOUBLE) - 1 AS r4 FROM parts),
wide AS (SELECT doc_id, text, ws, round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, r1)), 6) AS "J1", round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, r2)), 6) AS "J2", round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, r3)), 6) AS "J3", round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, r4)), 6) AS "J4" FROM raw_),
votes AS (SELECT doc_id AS claim_id, unnest(['J1', 'J2', 'J3', 'J4']) AS member, unnest(["J1", "J2", "J3", "J4"]) AS score FROM wide),
ens AS (SELECT claim_id, round(avg(score), 9) AS mean, min(score) AS low, max(score) AS high, round(max(score) - min(score), 6) AS spread FROM votes GROUP BY 1)"""


def _votes(spark, d):
    return judges.local_votes(_documents(spark, d))


def _wide(spark, d):
    """The same votes, a row per claim: what needs all members of a claim then needs no shuffle."""
    return judges.wide_votes(_documents(spark, d))


def _ensemble(spark, d):
    return ensemble.combine_wide(_wide(spark, d), list(text.raw_scorers()))


@query(f"WITH {SCORERS} SELECT claim_id, mean, low, high, spread FROM ens")
def ensemble_mean(spark, d):
    return ensemble.combine(_votes(spark, d), ["claim_id"]).select("claim_id", "mean", "low", "high", "spread")


@query(f"WITH {SCORERS} SELECT claim_id, mean, spread FROM ens WHERE spread <= 1")
def ensemble_agreement(spark, d):
    return ensemble.filter_agreement(_ensemble(spark, d).select("claim_id", "mean", "spread"), in_place=True)


@query(f"WITH {SCORERS} SELECT claim_id, spread FROM ens WHERE spread > 1")
def ensemble_dropped(spark, d):
    return ensemble.dropped_by_spread(_ensemble(spark, d).select("claim_id", "spread"), in_place=True)


@query(f"WITH {SCORERS} SELECT claim_id, score FROM votes WHERE member = 'J2'")
def ensemble_single(spark, d):
    return ensemble.single(_votes(spark, d), "J2").select("claim_id", "score")


@query(f"""WITH {SCORERS}, j AS (SELECT v.claim_id, v.member, v.member || ' scores ' || CAST(round(v.score, 3) AS VARCHAR) AS jt, round(abs(v.score - avg(v.score) OVER (PARTITION BY v.claim_id)), 6) AS far FROM votes v)
SELECT claim_id, arg_min(jt, (far, member)) AS justification, string_agg(jt, ' | ' ORDER BY member) AS all_justifications FROM j GROUP BY 1""")
def ensemble_justification(spark, d):
    return ensemble.justify(_votes(spark, d), ["claim_id"])


WIDE_VOTES = f"""{CLAIMS}, {CLAIM_MEDIA}, {OVER_MEDIA}, wv AS (SELECT c.claim_id, i AS k, CASE WHEN m.contextualization IS NOT NULL THEN round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, m.contextualization + ((c.claim_id * i * 31) % 601 - 300) / 1000.0::DOUBLE)), 6) END AS ctx,
 round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, c.veracity + ((c.claim_id * i * 37) % 601 - 300) / 1000.0::DOUBLE)), 6) AS ver, round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE, c.coverage + ((c.claim_id * i * 41) % 601 - 300) / 1000.0::DOUBLE)), 6) AS cov
 FROM claims c LEFT JOIN over_media m USING (claim_id), (VALUES (1), (2), (3), (4)) t(i))"""


def _wide_votes(spark, d):
    """Four members' own property scores: the planted ones with an integer-hash deviation."""
    from factbench.functions.scores import clip

    base = derived.claims(spark, d).join(verdict.over_media(derived.claim_media(spark, d)), "claim_id", "left").withColumn("k", F.explode(F.array(*[F.lit(i) for i in (1, 2, 3, 4)])))
    off = lambda p: ((F.col("claim_id") * F.col("k") * p) % 601 - 300) / 1000.0
    return base.select("claim_id", F.concat(F.lit("J"), F.col("k").cast("string")).alias("member"), *[F.round(clip(F.col(c) + off(p)), 6).alias(c) for c, p in (("contextualization", 31), ("veracity", 37), ("coverage", 41))])


#: Stage 6 on the members' votes in ``wv``: means, the gates, the least; the members' own least for the spread.
STANDARD = """own_ AS (SELECT *, least(ctx, ver, cov) AS own FROM wv),
mean_ AS (SELECT claim_id, avg(ctx) AS c0, avg(ver) AS v0, avg(cov) AS o0, round(max(own) - min(own), 6) AS spread FROM own_ GROUP BY 1),
gate_ AS (SELECT *, coalesce(c0, 1.0) < -1.0::DOUBLE/3 AS stop1, coalesce(c0, 1.0) < -1.0::DOUBLE/3 OR coalesce(v0, 1.0) < -1.0::DOUBLE/3 AS stop2, round(c0, 9) AS c, round(v0, 9) AS v, round(o0, 9) AS o FROM mean_),
std AS (SELECT claim_id, spread, round(least(c0, CASE WHEN NOT stop1 THEN v0 END, CASE WHEN NOT stop2 THEN o0 END), 9) AS integrity,
  CASE WHEN c = least(c, CASE WHEN NOT stop1 THEN v END, CASE WHEN NOT stop2 THEN o END) THEN 'contextualization' WHEN NOT stop1 AND v = least(c, v, CASE WHEN NOT stop2 THEN o END) THEN 'veracity' WHEN NOT stop2 THEN 'coverage' END AS compromising,
  CASE WHEN integrity > 1.0::DOUBLE/3 THEN 'intact' WHEN integrity < -1.0::DOUBLE/3 THEN 'compromised' WHEN integrity IS NOT NULL THEN 'uncertain' END AS label FROM gate_)"""
_NEAREST = "arg_min(CASE WHEN {p} IS NOT NULL THEN 'J' || k || ' scores ' || CAST(round({p}, 3) AS VARCHAR) END, (round(abs({p} - m_{p}), 6), k)) FILTER ({p} IS NOT NULL)"
SAYS = f"""far_ AS (SELECT *, avg(ctx) OVER w AS m_ctx, avg(ver) OVER w AS m_ver, avg(cov) OVER w AS m_cov FROM wv WINDOW w AS (PARTITION BY claim_id)),
says AS (SELECT claim_id, {', '.join(_NEAREST.format(p=p) + f' AS {n}_justification' for p, n in (('ctx', 'contextualization'), ('ver', 'veracity'), ('cov', 'coverage')))} FROM far_ GROUP BY 1),
justified AS (SELECT std.*, says.* EXCLUDE (claim_id), CASE compromising WHEN 'contextualization' THEN contextualization_justification WHEN 'veracity' THEN veracity_justification WHEN 'coverage' THEN coverage_justification END AS justification FROM std JOIN says USING (claim_id))"""
JUSTIFIED = f"{WIDE_VOTES}, {STANDARD}, {SAYS}"
_REVOTE = """CASE WHEN w.{c} IS NULL THEN NULL WHEN w.claim_id % 11 = 3 AND w.k = 2 THEN -0.9::DOUBLE WHEN w.{c} <= 1.0::DOUBLE/3 THEN round(greatest(-1.0::DOUBLE, least(1.0::DOUBLE,
  CASE WHEN (w.claim_id * 31) % 40 = 0 THEN round(w.{c} / 2, 6) ELSE round(0.334::DOUBLE + ((w.claim_id * 7919) % 667) / 1001.0::DOUBLE, 6) END + ((w.claim_id * 13 + (48 + w.k) * 29) % 41 - 20) / 400.0::DOUBLE)), 6) ELSE w.{c} END AS {c}"""


def _justified(spark, d, votes=None):
    votes = _wide_votes(spark, d) if votes is None else votes
    long = votes.unpivot(["claim_id", "member"], list(verdict.ORDER), "property", "score").withColumn("justification", judges.justified(F.col("member"), F.col("score")))
    return ensemble.justify_integrity(ensemble.standardize(votes), ensemble.justify_properties(long))


_GATED = "CASE WHEN NOT (coalesce({c}, 1.0) < -1.0::DOUBLE/3) THEN {v} END"


@query(f"""WITH {WIDE_VOTES}, m AS (SELECT claim_id, avg(ctx) AS c, avg(ver) AS v0, avg(cov) AS o0 FROM wv GROUP BY 1), g AS (SELECT *, {_GATED.format(c='c', v='v0')} AS v FROM m)
SELECT claim_id, round(least(c, v, CASE WHEN NOT (coalesce(c, 1.0) < -1.0::DOUBLE/3) AND NOT (coalesce(v, 1.0) < -1.0::DOUBLE/3) THEN o0 END), 9) AS integrity FROM g""")
def ensemble_mean_then_min(spark, d):
    return ensemble.integrity_votes(_wide_votes(spark, d)).select("claim_id", "integrity")


@query(f"""WITH {WIDE_VOTES}, g AS (SELECT *, {_GATED.format(c='ctx', v='ver')} AS v FROM wv), h AS (SELECT claim_id, least(ctx, v, CASE WHEN NOT (coalesce(ctx, 1.0) < -1.0::DOUBLE/3) AND NOT (coalesce(v, 1.0) < -1.0::DOUBLE/3) THEN cov END) AS own FROM g)
SELECT claim_id, round(avg(own), 9) AS integrity, round(max(own) - min(own), 6) AS spread FROM h GROUP BY 1""")
def ensemble_min_then_mean(spark, d):
    return ensemble.integrity_votes(_wide_votes(spark, d), order="min_then_mean", gate="member").select("claim_id", "integrity", "spread")


@query(f"WITH {WIDE_VOTES} SELECT claim_id, round(greatest(max(ctx) - min(ctx), max(ver) - min(ver), max(cov) - min(cov)), 6) AS spread FROM wv GROUP BY 1")
def ensemble_property_spread(spark, d):
    return ensemble.property_spread(_wide_votes(spark, d))


@query(f"WITH {WIDE_VOTES}, {STANDARD} SELECT claim_id, integrity, spread, compromising, label FROM std")
def ensemble_standardize(spark, d):
    return ensemble.standardize(_wide_votes(spark, d)).select("claim_id", "integrity", "spread", "compromising", "label")


@query(f"WITH {JUSTIFIED} SELECT claim_id, contextualization_justification, veracity_justification, coverage_justification, justification FROM justified")
def integrity_justification(spark, d):
    """A justification for every property, and the compromising property's as that of the integrity."""
    return _justified(spark, d).select("claim_id", *[f"{p}_justification" for p in verdict.ORDER], "justification")


# stage 7

TEXTS = """texts AS (SELECT o_orderkey AS claim_id, 'Customer ' || o_custkey % 100 || ' ordered goods with priority ' || lower(substr(o_orderpriority, 3)) || CASE WHEN o_orderkey % 3 = 0 THEN ', as a video shows' ELSE '' END || CASE WHEN o_orderkey % 13 = 0 THEN ': ' || repeat('123456789 ', 5) ELSE '' END AS text,
  coalesce(n_media, 0) AS n_media FROM orders LEFT JOIN over_media m ON m.claim_id = o_orderkey)"""
_SYMBOLS = r"length(regexp_replace(text, '[\p{L}\p{N} \t\n\r]', '', 'g')) / greatest(1, length(text))::DOUBLE < 0.15::DOUBLE"
#: From candidates of one line of text, in ``cand``, to outcomes, in ``twins``.
TWINS_OF = f"""tw1 AS (SELECT *, CASE compromising WHEN 'contextualization' THEN 'Seen in its context: ' WHEN 'veracity' THEN 'In fact: ' ELSE 'With what was left out: ' END || CASE WHEN {_SYMBOLS} THEN text ELSE '' END || CASE WHEN compromising = 'coverage' THEN ' (' || coalesce(justification, '') || ')' ELSE '' END AS twin_text FROM cand),
tw2 AS (SELECT *, NOT (regexp_matches(twin_text, '{claims._any(claims.MEDIA_WORDS)}') AND n_media = 0) AS consistent,
  len(list_filter(regexp_split_to_array(twin_text, '[ \t\n\r]+'), lambda w: w <> '')) BETWEEN 4 AND 70 AND length(regexp_replace(twin_text, '[^0-9]', '', 'g')) / greatest(1, length(twin_text))::DOUBLE <= 0.25 AS shareable FROM tw1),
tvotes AS (SELECT w.claim_id, w.k, {', '.join(_REVOTE.format(c=c) for c in ('ctx', 'ver', 'cov'))} FROM wv w JOIN tw2 t ON t.claim_id = w.claim_id AND t.consistent AND t.shareable),
{STANDARD.replace('std', 'tstd').replace('FROM wv', 'FROM tvotes').replace('own_', 'town_').replace('mean_', 'tmean_').replace('gate_', 'tgate_')},
twins AS (SELECT t.*, s.integrity AS twin_integrity, s.spread AS twin_spread, CASE WHEN NOT t.consistent THEN 'inconsistent' WHEN NOT t.shareable THEN 'not shareable' WHEN s.spread > 1 THEN 'low agreement' WHEN s.integrity > 1.0::DOUBLE/3 THEN 'accepted' ELSE 'not intact' END AS outcome
  FROM tw2 t LEFT JOIN tstd s USING (claim_id))"""
TWINS = f"""{JUSTIFIED}, {TEXTS}, cand AS (SELECT j.*, t.text, t.n_media FROM justified j JOIN texts t USING (claim_id) WHERE label = 'compromised' AND spread <= 1), {TWINS_OF}"""


def _twins(spark, d):
    """Compromised claims with high agreement, corrected, checked, and scored again by the same ensemble."""
    votes = _wide_votes(spark, d)
    judged = ensemble.filter_agreement(_justified(spark, d, votes))
    cands = rectify.candidates(judged).join(derived.claim_texts(spark, d), "claim_id")
    twins = rectify.checked(rectify.generate(cands))
    return rectify.decided(rectify.rescore(twins, rectify.revote(rectify.passing(twins), votes)))


@query(f"WITH {TWINS} SELECT claim_id, twin_text, twin_integrity, twin_spread, outcome FROM twins")
def rectify_accept(spark, d):
    return _twins(spark, d).select("claim_id", "twin_text", "twin_integrity", "twin_spread", "outcome")


@query(f"WITH {TWINS} SELECT outcome, count(*) AS n, round(100.0::DOUBLE * count(*) / sum(count(*)) OVER (), 6) AS percent FROM twins GROUP BY outcome")
def rectify_report(spark, d):
    return rectify.report(_twins(spark, d))


REPLACED = f"""{TWINS}, replaced AS (SELECT v.claim_id, c.quarter, coalesce(t.twin_integrity, v.integrity) AS integrity, t.claim_id IS NOT NULL AS rectified FROM std v JOIN claims c USING (claim_id) LEFT JOIN (SELECT * FROM twins WHERE outcome = 'accepted') t USING (claim_id) WHERE v.spread <= 1),
final AS (SELECT *, CASE WHEN integrity > 1.0::DOUBLE/3 THEN 'intact' WHEN integrity < -1.0::DOUBLE/3 THEN 'compromised' WHEN integrity IS NOT NULL THEN 'uncertain' END AS label FROM replaced)"""


def _final(spark, d, half: bool = True):
    """Claims with high agreement after rectification. Half of the candidates, by integer hash, are rectified, so that both classes stay."""
    judged = ensemble.filter_agreement(ensemble.standardize(_wide_votes(spark, d))).join(derived.claims(spark, d).select("claim_id", "claim_ts", "quarter"), "claim_id")
    twins = _twins(spark, d)
    return rectify.replace(judged, twins.filter("claim_id % 2 = 0") if half else twins)


HALF = REPLACED.replace("WHERE outcome = 'accepted'", "WHERE outcome = 'accepted' AND claim_id % 2 = 0")


@query(f"WITH {REPLACED} SELECT claim_id, integrity, rectified, label FROM final")
def rectify_replace(spark, d):
    return _final(spark, d, half=False).select("claim_id", "integrity", "rectified", "label")


@query(f"WITH {SCORERS} SELECT doc_id, len(ws) >= 4 AND len(ws) <= 70 AND length(regexp_replace(text, '[^0-9]', '', 'g')) / greatest(1, length(text))::DOUBLE <= 0.25 AS shareable FROM wide")
def rectify_shareable(spark, d):
    return _documents(spark, d).select("doc_id", rectify.shareable("text").alias("shareable"))


@query(rf"""WITH l AS (SELECT doc_id, unnest(list_distinct(string_split(text, chr(10)))) AS line, string_split(text, chr(10)) AS ls FROM documents),
k AS (SELECT doc_id, line, list_position(ls, line) AS at_ FROM l WHERE length(regexp_replace(line, '[\p{{L}}\p{{N}} \t\n\r]', '', 'g')) / greatest(1, length(line))::DOUBLE < 0.15::DOUBLE)
SELECT d.doc_id, coalesce((SELECT string_agg(line, chr(10) ORDER BY at_) FROM k WHERE k.doc_id = d.doc_id), '') AS twin_text FROM documents d""")
def rectify_text(spark, d):
    """The local corrector of texts: repeated lines and lines of mostly symbols go."""
    return rectify.generate_text(_documents(spark, d)).select("doc_id", "twin_text")


@query(rf"SELECT doc_id, NOT (regexp_matches(text, '{claims._any(claims.MEDIA_WORDS)}') AND doc_id % 2 = 0) AS consistent FROM documents")
def rectify_consistent(spark, d):
    docs = _documents(spark, d).withColumn("n_media", (F.col("doc_id") % 2).cast("int"))
    return docs.select("doc_id", rectify.consistent(docs, "text", "n_media").alias("consistent"))


RANKED = f"""{HALF}, ranked AS (SELECT *, row_number() OVER (PARTITION BY quarter, label ORDER BY md5('split-1:' || claim_id), claim_id) AS rank FROM final WHERE label IN ('intact', 'compromised'))"""


def _balanced_sql(half: int) -> str:
    return f"""WITH {RANKED}, taken AS (SELECT * FROM ranked WHERE rank <= {half}), full_ AS (SELECT quarter FROM taken GROUP BY 1 HAVING count(*) = {2 * half})
SELECT claim_id, quarter, label, CAST(rank AS INTEGER) AS rank FROM taken WHERE quarter IN (SELECT quarter FROM full_)"""


@query(_balanced_sql(50))
def split_balanced(spark, d):
    return splits.balanced(_final(spark, d), 100).select("claim_id", "quarter", "label", "rank")


@query(_balanced_sql(5))
def split_longitudinal(spark, d):
    return splits.longitudinal(_final(spark, d), 10).select("claim_id", "quarter", "label", "rank")


@query(_balanced_sql(500))
def split_balanced_1000(spark, d):
    """The published size: 1000 a quarter. Quarters of small tables don't have that many."""
    return splits.balanced(_final(spark, d), 1000).select("claim_id", "quarter", "label", "rank")


@query(_balanced_sql(50))
def split_longitudinal_100(spark, d):
    return splits.longitudinal(_final(spark, d), 100).select("claim_id", "quarter", "label", "rank")


@query(f"WITH {HALF} SELECT quarter, CAST(sum(CASE WHEN label = 'intact' THEN 1 ELSE 0 END) AS BIGINT) AS n_intact, CAST(sum(CASE WHEN label = 'compromised' THEN 1 ELSE 0 END) AS BIGINT) AS n_compromised, least(sum(CASE WHEN label = 'intact' THEN 1 ELSE 0 END), sum(CASE WHEN label = 'compromised' THEN 1 ELSE 0 END)) >= 100 AS eligible FROM final GROUP BY 1")
def split_eligible(spark, d):
    return splits.eligible(_final(spark, d), 100)


@query(f"WITH {HALF} SELECT claim_id, label FROM final WHERE quarter = (SELECT max(quarter) FROM final)")
def split_latest(spark, d):
    return splits.latest(_final(spark, d)).select("claim_id", "label")


@query(f"""WITH {RANKED}, a AS (SELECT claim_id FROM ranked WHERE rank <= 50 AND quarter IN (SELECT quarter FROM ranked WHERE rank <= 50 GROUP BY 1 HAVING count(*) = 100)), b AS (SELECT claim_id FROM ranked WHERE rank <= 5 AND quarter IN (SELECT quarter FROM ranked WHERE rank <= 5 GROUP BY 1 HAVING count(*) = 10))
SELECT (SELECT count(*) FROM (SELECT claim_id FROM a INTERSECT SELECT claim_id FROM b)) AS "both", (SELECT count(*) FROM (SELECT claim_id FROM a EXCEPT SELECT claim_id FROM b)) AS first_only, (SELECT count(*) FROM (SELECT claim_id FROM b EXCEPT SELECT claim_id FROM a)) AS second_only,
(SELECT count(*) - count(DISTINCT claim_id) FROM a) + (SELECT count(*) - count(DISTINCT claim_id) FROM b) AS repeated""")
def split_overlap(spark, d):
    """The small split lies in the large one where both have a quarter, and no claim is in either twice."""
    final = checkpointed(_final(spark, d))
    return splits.overlap(splits.balanced(final, 100), splits.longitudinal(final, 10))


@query("SELECT doc_id, quality FROM labels WHERE CAST('0x' || substr(md5('sample-1:' || doc_id), 1, 8) AS BIGINT) < CASE quality WHEN 0 THEN 2147483648 WHEN 1 THEN 429496729 ELSE 0 END")
def sample_by_class(spark, d):
    """A stratified sample: half of the poor documents by hash, a tenth of the good ones."""
    return splits.sample_by_class(load(spark, d, "labels", ["doc_id", "quality"]), "doc_id", "quality", {0: 0.5, 1: 0.1})


@query("SELECT doc_id FROM documents WHERE CAST('0x' || substr(md5('sample-1:' || doc_id), 1, 8) AS BIGINT) < 858993459")
def sample_by_hash(spark, d):
    """A sampling operator: a fifth of the documents by hash."""
    return splits.sample_by_hash(load(spark, d, "documents", ["doc_id"]), "doc_id", 0.2)


@query(f"WITH {SCORERS} SELECT CAST((mean > 1.0::DOUBLE/3)::INT - (mean < -1.0::DOUBLE/3)::INT AS INTEGER) AS bin, count(*) AS n FROM ens GROUP BY 1")
def ensemble_bins(spark, d):
    return _ensemble(spark, d).groupBy(bin_index("mean", 3).alias("bin")).agg(F.count(F.lit(1)).alias("n"))
