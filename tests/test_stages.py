"""Stages 1 to 5 on small fixtures."""

import datetime

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from factbench.functions import html, text, url
from factbench.operators import appearances, articles, claims, discovery, funnel, media, publishers
from factbench.sources import derived
from factbench.sources.io import load


def one(spark, value, *columns):
    r = spark.createDataFrame([(value,)], "x string").select(*columns).first()
    return r[0] if len(columns) == 1 else tuple(r)


FEED = [
    '{"claimReviewed": "a", "url": "https://e.org/1", "datePublished": "2020-05-01", "reviewRating": {"alternateName": "half true"}, "itemReviewed": {"appearance": [{"url": "https://s.com/9"}]}}',
    '[{"claimReviewed": "b", "url": "https://e.org/2", "datePublished": "2020-05-02", "inLanguage": "de"}, {"claimReviewed": "b", "url": "https://f.org/3", "datePublished": "2020-05-03"}]',
    '{"claimReviewed": "old", "url": "https://e.org/4", "datePublished": "2010-01-01"}',
    "{broken",
]


def test_review_feed(spark):
    raw = spark.createDataFrame([(x,) for x in FEED], "raw string")
    out = discovery.parse_reviews(raw, since=datetime.date(2016, 1, 1), until=datetime.date(2026, 3, 31))
    good = {r["url"]: r for r in out.filter("not malformed").collect()}
    assert set(good) == {"https://e.org/1", "https://e.org/2", "https://f.org/3"}
    assert good["https://e.org/1"]["rating"] == "half true" and good["https://e.org/1"]["appearances"] == ["https://s.com/9"]
    assert out.filter("malformed").count() == 1


def test_markup_in_pages(spark):
    pages = spark.createDataFrame([(1, f'<html><script type="application/ld+json">{FEED[0]}</script><p>x</p></html>')], "page_id long, html string")
    assert discovery.parse_reviews(discovery.markup_from_html(pages)).first()["claim"] == "a"


def test_language(spark):
    assert one(spark, "the cat is on the mat", text.language("x")) == "en"
    assert one(spark, "der Hund und die Katze", text.language("x")) == "de"
    assert one(spark, "1234 !!", text.language("x")) is None
    df = spark.createDataFrame([("le chat est dans la maison", None), ("the dog", "xx")], "text string, lang string")
    assert [r["lang"] for r in discovery.fill_language(df).collect()] == ["fr", "xx"]


def test_first_of_repeated_reviews(spark):
    df = spark.createDataFrame([("k", 2, "b"), ("k", 1, "a"), ("m", 5, "c")], "k string, n int, v string")
    assert sorted(r["v"] for r in discovery.dedup_reviews(df, ["k"], ["n"]).collect()) == ["a", "c"]


@pytest.mark.parametrize(
    ("given", "want"),
    [
        ("http://www.Example.com/A/?q=1#top", "https://example.com/A"),
        ("https://m.example.com/x.html", "https://example.com/x"),
        ("https://example.com", "https://example.com"),
    ],
)
def test_canonical(spark, given, want):
    assert one(spark, given, url.canonical("x")) == want
    assert one(spark, want, url.canonical("x")) == want


def test_archives(spark):
    inner = "https://news.example/p?x=1"
    once = f"https://web.archive.example/web/20200102030405/{inner}"
    nested = f"https://web.archive.example/web/2021/{once}"
    for given in (inner, once, nested, "https://old.example/2019id_/" * 5 + nested):
        assert one(spark, given, url.unwrap_archive("x")) == inner
    codes = spark.createDataFrame([("https://perma.cc/AB12", inner)], "archive_url string, original_url string")
    df = spark.createDataFrame([("https://perma.cc/AB12",), ("https://perma.cc/ZZ99",), (once,)], "u string")
    got = {r["u"]: (r["original"], r["archived"]) for r in url.resolve_archives(df, "u", codes).collect()}
    assert got["https://perma.cc/AB12"] == (inner, True)
    assert got["https://perma.cc/ZZ99"] == ("https://perma.cc/ZZ99", True)
    assert got[once] == (inner, True)


def test_host_and_domain(spark):
    assert one(spark, "https://u:p@Blog.News.example.org:80/x", url.host("x"), url.registrable_domain("x"), url.platform("x")) == ("blog.news.example.org", "example.org", "example")


PAGE = (
    "<html><head><script>var t='</p>';</script></head><body><nav><a href='/n'>n</a></nav><!-- c --><div class=\"ad\">buy</div>"
    "<article><h1>Title</h1><p>One &amp; two.<br>Three &lt;3</p><p>See <a href=\"/a\">this</a> long enough paragraph of plain words here.</p></article><footer>f</footer></body></html>"
)


def test_main_text(spark):
    assert one(spark, PAGE, html.main_text("x")) == "Title\nOne & two.\nThree <3\nSee this long enough paragraph of plain words here."


def test_body_is_verbatim(spark):
    df = spark.createDataFrame([(1, PAGE), (2, "<p>none</p>")], "page_id long, html string")
    rows = {r["page_id"]: r for r in articles.body_span(df).collect()}
    assert PAGE[rows[1]["start"] : rows[1]["end"]] == rows[1]["body"] and rows[1]["body"].startswith("<h1>")
    assert rows[2]["body"] is None


def test_density_span_is_verbatim(spark, small):
    pages = load(spark, small, "pages", ["page_id", "html"])
    both = articles.density_span(pages).join(pages, "page_id").collect()
    found = [r for r in both if r["body"] is not None]
    assert len(both) == pages.count() and found and all(r["html"][r["start"] : r["end"]] == r["body"] for r in found)
    assert all(r["start"] is None and r["end"] is None for r in both if r["body"] is None)


def test_blocks(spark):
    df = spark.createDataFrame([(1, PAGE)], "page_id long, html string")
    rows = articles.blocks(df).orderBy("block_no").collect()
    assert [r["text"] for r in rows][1] == "Title" and all(PAGE[r["start"] : r["end"]] for r in rows)


def test_short_and_empty_articles(spark):
    df = spark.createDataFrame([("x" * 200,), ("x" * 199,), ("  ",), (None,)], "article string")
    assert articles.drop_inaccessible(df).count() == 2
    assert articles.drop_short(df).count() == 1
    assert articles.drop_short(df, 1, min_words=2).count() == 0


def test_appearances(spark):
    pages = spark.createDataFrame([(1, "http://www.e.com/x/y", '<a href="/a?q">1</a><a href="b.html">2</a><a href="/a?q">3</a><a href="https://Z.com/k">4</a>')], "page_id long, url string, html string")
    rows = appearances.extract(pages).orderBy("place").collect()
    assert [r["url"] for r in rows] == ["https://e.com/a", "https://e.com/b", "https://z.com/k"]
    assert appearances.cap(appearances.extract(pages), "page_id", ["place"]).count() == 2


def test_fallback_to_archive(spark):
    c = spark.createDataFrame([(1, 0, "u1", "a1"), (2, 0, "u2", "a2"), (3, 0, "u3", None)], "claim_id long, place int, url string, archived_url string")
    f = spark.createDataFrame([("u1", True), ("u2", False), ("a2", True), ("u3", False)], "url string, ok boolean")
    got = {r["claim_id"]: (r["chosen"], r["from_archive"]) for r in appearances.choose(c, f).collect()}
    assert got == {1: ("u1", False), 2: ("a2", True)}
    reviews = spark.createDataFrame([(1,), (2,), (3,)], "claim_id long")
    assert appearances.require(reviews, c.filter("claim_id < 3"), "claim_id").count() == 2
    assert appearances.without(reviews, c.filter("claim_id < 3"), "claim_id").count() == 1


def test_two_that_could_be_fetched(spark):
    """The cap counts appearances that were retrieved, not those that were tried."""
    c = spark.createDataFrame([(1, i, f"u{i}", f"a{i}") for i in range(5)], "claim_id long, place int, url string, archived_url string")
    f = spark.createDataFrame([("u0", False), ("a0", False), ("u1", False), ("a1", True), ("u2", False), ("u3", True), ("u4", True)], "url string, ok boolean")
    assert [r["chosen"] for r in appearances.retrieved(c, f).orderBy("place").collect()] == ["a1", "u3"]


def test_links_equal_in_canonical_form_are_one(spark):
    source = '<a href="https://www.x.com/a?q=1">1</a><a href="https://x.com/a/">2</a> <a href="https://web.archive.example/web/2020/https://m.x.com/a.html">3</a><a href="https://x.com/b">4</a>'
    pages = spark.createDataFrame([(1, "http://e.com/", source)], "page_id long, url string, html string")
    assert [(r["place"], r["url"]) for r in appearances.extract(pages).orderBy("place").collect()] == [(0, "https://x.com/a"), (1, "https://x.com/b")]


def test_given_appearances(spark):
    df = spark.createDataFrame([(1, ["a", "b"]), (2, None), (3, [])], "review_id long, appearances array<string>")
    assert appearances.given(df).filter("url is not null").count() == 2
    assert sorted(r["review_id"] for r in appearances.lacking(df).collect()) == [2, 3]


def test_publishers(spark):
    df = publishers.with_publisher(spark.createDataFrame([("https://a.x.org/1",), ("https://b.x.org/2",), ("https://y.com/3",)], "url string"))
    listed = spark.createDataFrame([("x.org",)], "domain string")
    assert publishers.retain_credible(df, listed).count() == 2 and publishers.dropped(df, listed).count() == 1
    assert {r["publisher"]: r["n_reviews"] for r in publishers.census(df).collect()} == {"x.org": 2, "y.com": 1}
    assert [r[0] for r in publishers.derive_credible(df, 2).collect()] == ["x.org"]
    assert publishers.n_publishers(df, approximate=True).first()[0] == 2
    assert publishers.by_suffix(df, (".org",)).count() == 2


def test_video_limits(spark):
    df = spark.createDataFrame([(1, 300.0, 128), (2, 300.1, 1), (3, 1.0, 129)], "media_id long, seconds double, mb int")
    assert [r["media_id"] for r in media.within_limits(df).collect()] == [1]


def items(spark, rows):
    return spark.createDataFrame([(1, i, o, v, [float(x) for x in e]) for i, o, v, e in rows], "claim_id long, media_id long, origin int, is_video boolean, embedding array<double>")


CHAIN = [(1, 0, False, (1, 0)), (2, 0, False, (0.8, 0.6)), (3, 0, False, (0.28, 0.96))]  # 1~2, 2~3, not 1~3


def test_dedup_modes_on_a_chain(spark):
    ids = lambda mode: sorted(r["media_id"] for r in media.dedup(items(spark, CHAIN), 0.75, mode).collect())
    assert ids("pairwise") == [1] and ids("greedy") == [1, 3] and ids("components") == [1]


def test_an_item_of_two_claims_is_judged_in_each(spark):
    rows = [(1, 11, 1, (1, 0)), (1, 12, 0, (1, 0.01)), (2, 11, 0, (1, 0)), (2, 13, 0, (0, 1))]
    df = spark.createDataFrame([(c, m, o, False, [float(x) for x in e]) for c, m, o, e in rows], "claim_id long, media_id long, origin int, is_video boolean, embedding array<double>")
    for mode in ("pairwise", "greedy", "components"):
        assert sorted((r["claim_id"], r["media_id"]) for r in media.dedup(df, 0.85, mode).collect()) == [(1, 12), (2, 11), (2, 13)]


def test_components_of_a_long_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(1000)] + [(5000, 5001)], "a long, b long")
    got = {r["node"]: r["component"] for r in media.components(links).collect()}
    assert got == {**dict.fromkeys(range(1001), 0), 5000: 5000, 5001: 5000}


def test_originals_win(spark):
    rows = items(spark, [(1, 2, False, (1, 0)), (2, 0, False, (1, 0.01))])
    for mode in ("pairwise", "greedy", "components"):
        assert [r["media_id"] for r in media.dedup(rows, 0.85, mode).collect()] == [2]


def test_cap_takes_videos_first(spark):
    rows = items(spark, [(i, 0, False, (1, 0)) for i in (1, 2, 3)] + [(i, 2, True, (1, 0)) for i in (4, 5, 6)])
    assert sorted(r["media_id"] for r in media.cap(rows).collect()) == [1, 4, 5, 6]


def test_precedence(spark):
    assert [one(spark, o, media.precedence("x")) for o in ("original", "archived", "article", "elsewhere")] == [0, 1, 2, 3]


def test_buckets_find_planted_copies(spark, small):
    m = derived.media(spark, small).select("media_id", "embedding")
    exact = {tuple(r)[:2] for r in media.exact_pairs(m, 0.85).collect()}
    found = {tuple(r)[:2] for r in media.near_pairs(m, 0.85).collect()}
    assert exact and found == exact


def test_buckets_of_other_dimensions(spark):
    """Vectors of 128 dimensions: planted neighbours are found, and buckets stay small."""
    rng = np.random.default_rng(3)
    x = rng.standard_normal((400, 128))
    x = np.r_[x, x[:50] + 0.3 * rng.standard_normal((50, 128))]
    m = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "media_id long, embedding array<double>")
    assert sorted((r["a"], r["b"]) for r in media.near_pairs(m, 0.85).collect()) == [(i, 400 + i) for i in range(50)]
    bits, tables = media.lsh_shape(450, 0.85, 0.999)
    rows = pa.RecordBatch.from_arrays([pa.array(range(450)), pa.array(x.tolist())], names=["media_id", "v"])
    sizes = [np.unique(b.column(1).to_numpy(), return_counts=True)[1].max() for b in media._bucket_rows(bits, tables)([rows])]
    assert len(sizes) == tables and max(sizes) < 100
    assert media.lsh_shape(10**6, 0.85, 0.99)[0] == 16
    with pytest.raises(ValueError, match="components"):
        media.near_pairs(m.union(spark.createDataFrame([(999, [1.0])], m.schema)), 0.85)


def test_claim_rules(spark):
    assert one(spark, "Social media posts claiming that  the moon\nis cheese. More text.", claims.rewritten("x")) == "the moon is cheese."
    assert one(spark, "A photo shows it was a HOAX", claims.exposes_verdict("x"), claims.lacks_media("x", F.lit(0)), claims.lacks_media("x", F.lit(1))) == (True, True, False)
    assert one(spark, "falsehood", claims.exposes_verdict("x")) is False
    assert one(spark, "w " * 70, claims.too_long("x")) is False and one(spark, "w " * 71, claims.too_long("x")) is True


def test_validation_gives_all_reasons(spark):
    df = spark.createDataFrame([("fake video " + "w " * 70, 0), ("plain", 0)], "claim string, n_media int")
    kept, gone = claims.validate(df)
    assert kept.count() == 1 and gone.first()["reasons"] == ["verdict exposed", "media missing", "too long"]


def test_blank_claims_are_dropped(spark):
    df = spark.createDataFrame([(None, 0), ("  ", 0), ("plain", 0)], "claim string, n_media int")
    kept, gone = claims.validate(df)
    assert kept.count() == 1 and [r["reasons"] for r in gone.collect()] == [["empty"], ["empty"]]


def test_claims_are_rewritten_in_context(spark):
    rows = [("Posts claim that it rains. More.", "An article. More.", "x.com", "Ann", datetime.date(2024, 5, 1), ["video"]), (None, "An article. More.", None, None, None, [])]
    df = spark.createDataFrame(rows, "text string, article string, place string, who string, day date, kinds array<string>")
    context = ("article", "place", "who", "day")
    assert [r["claim"] for r in claims.reformulate(df, kinds="kinds", context=context).collect()] == ["Ann on x.com in 2024-05: it rains. [video]", "An article."]
    video = claims.reformulate(df, kinds="kinds", context=context, video_rewriter=lambda raw, *_: F.lit("seen"), rewriter=lambda raw, article, place, who, day: article)
    assert [r["claim"] for r in video.collect()] == ["seen [video]", "An article. More."]


def test_domains_under_suffixes_of_two_labels(spark):
    got = [one(spark, f"https://{h}/x", url.registrable_domain("x")) for h in ("news.bbc.co.uk", "a.folha.com.br", "b.c.org", "co.uk")]
    assert got == ["bbc.co.uk", "folha.com.br", "c.org", "co.uk"]


def test_pages_without_a_good_block_stay(spark):
    df = spark.createDataFrame([(1, "<p>" + "word " * 20 + "</p>"), (2, "<p>short</p>"), (3, None)], "page_id long, html string")
    got = {r["page_id"]: r["body"] for r in articles.density_span(df).collect()}
    assert set(got) == {1, 2, 3} and got[1].startswith("word") and got[2] is got[3] is None


def test_chain_adds_up(spark, small):
    """What a stage keeps is what enters the next, and every benchmark claim is there once."""
    from factbench.plans import chain

    rows = [r.asDict() for r in chain.funnel_stages(spark, small).collect()]
    stages = sorted({r["stage"] for r in rows})
    kept = {s: sum(r["n"] for r in rows if r["stage"] == s and r["status"] == "kept") for s in stages}
    entered = {s: next(r["entered"] for r in rows if r["stage"] == s) for s in stages}
    assert len(stages) == 7 and all(kept[a] == entered[b] for a, b in zip(stages[:5], stages[1:6], strict=True)) and entered[stages[0]] == 200
    assert all(sum(r["n"] for r in rows if r["stage"] == s) == entered[s] for s in stages)
    assert {r["status"] for r in rows} == {"kept", "dropped", "pending"}
    out = chain.chain_benchmark(spark, small).collect()
    assert len({r["claim_id"] for r in out}) == len(out) == kept["6 verdict"] and sum(r["rectified"] for r in out) == kept["7 rectification"] > 0


def test_funnel_adds_up(spark):
    rows = [("s", "kept", None)] * 94 + [("s", "dropped", "none")] * 105 + [("s", "pending", None)] * 9
    out = {r["status"]: r for r in funnel.report(spark.createDataFrame(rows, "stage string, status string, reason string")).collect()}
    assert sum(r["n"] for r in out.values()) == out["kept"]["entered"] == 208
    assert abs(out["dropped"]["rate_processed"] - 52.763819) < 1e-6 and out["pending"]["rate_processed"] is None
