"""Registered queries against SQL and against plain versions; the pipeline's stages."""

import brute
import oracle
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from factbench.llm import queries


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_matches_sql(spark, small, name):
    mine, theirs = queries.QUERIES[name](spark, small).toPandas(), oracle.connect(small).execute(queries.ORACLES[name]).df()
    assert sorted(mine.columns) == sorted(theirs.columns) and oracle.rows(mine) == oracle.rows(theirs)


def test_every_operator_has_a_query():
    assert {n.split("_")[0] for n in queries.QUERIES} == {*(f"op{n}" for n in range(1, 11)), "pipeline"}


def test_pipeline_stages(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    told = stages["language"](spark, docs, small).persist()
    assert told.columns == docs.columns and told.count() == docs.filter(F.col("text").rlike(r"\p{L}")).count()
    kept = stages["near_duplicates"](spark, told, small).persist()
    rows = [tuple(r) for r in told.select("doc_id", "text").collect()]
    groups = brute.jaccard_groups(rows, 5, 80)
    assert {r["doc_id"] for r in kept.collect()} == {d for d, (_, c) in groups.items() if c == d}
    cut = stages["repeated_passages"](spark, kept, small).persist()
    assert cut.columns == docs.columns
    want = brute.repeats([tuple(r) for r in kept.select("doc_id", "text").collect()])
    for r in cut.collect():
        n, gone, _ = want.pop(r["doc_id"])
        assert len(brute.WORD.findall(r["text"])) == n - gone and r["n_chars"] == len(r["text"])
    assert all(n == gone > 0 for n, gone, _ in want.values())
    mixed = stages["mixture"](spark, cut, small).persist()
    assert sorted((r["doc_id"], r["text"]) for r in mixed.collect()) == sorted(brute.mixed([(r["doc_id"], r["source"], r["text"]) for r in cut.collect()]))
    done = stages["tokens"](spark, mixed, small)
    assert done.count() == mixed.count() and done.filter("not round_trip").count() == 0


def test_pipeline_of_odd_documents(spark, small):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "hello world again and again", "en", None, 5), (3, "hello world again and again", "en", None, 5), (None, "no id here", "de", "b", 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("taken", F.lit("clash"))
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, small)
        assert "taken" in docs.columns and {r["text"] for r in docs.collect()} <= {"hello world again and again", "no id here", "no id", "hello world", "hello world again"}
    assert corpus_pipeline.STAGES[-1][1](spark, docs, small).count() == docs.count()
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs.limit(0), small).count() == 0


def test_pipeline_drops_unlearned_languages_and_gibberish(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    odd = [
        (-1, "zxqv wkjh qqpz vbnm xkcd jjqw zzxy kqvw", "en", "x", 39),
        (-2, "hyvää huomenta kaikille ystäville tänään on kaunis päivä ja aurinko paistaa", None, "x", 75),
        (-3, "Съешь же ещё этих мягких французских булок", None, "x", 42),
    ]
    told = corpus_pipeline.language(spark, docs.union(spark.createDataFrame(odd, docs.schema)), small)
    ids = {r["doc_id"] for r in told.select("doc_id").collect()}
    assert not ids & {-1, -2, -3}
    assert ids == {r["doc_id"] for r in docs.filter(F.col("text").rlike(r"\p{L}")).select("doc_id").collect()}
