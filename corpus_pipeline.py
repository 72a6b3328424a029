"""A corpus pipeline of five stages, each on all that the one before kept.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factbench.llm.byte_bpe import encode
from factbench.llm.common import stored
from factbench.llm.kernel_langid import UNKNOWN, predict, train
from factbench.llm.mixture import mixed_rows
from factbench.llm.repeat_windows import remove_repeats
from factbench.llm.token_groups import link_groups


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a known language: those without text or letters, or with fewer known byte runs than held-out texts tell, go."""
    model = train(docs, F.lit(True), support=True)
    told = predict(docs, model, pred="_lang_pred", score="_lang_score", support="_lang_support")
    return told.filter((F.col("_lang_pred") != UNKNOWN) & (F.col("_lang_support") >= (model.least_support if model else 0.0))).select(docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, the one with the smallest id; five-word shingles, similarity of 0.8 or more."""
    groups = link_groups(docs, words=5, threshold=80)
    gone = groups.filter("doc_id > component_id").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without passages of 13 words or more that one with a smaller id has; those with nothing left go."""
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    cut = remove_repeats(docs.select("doc_id", "text", F.struct(*others).alias("_row")), window=13, carry=["_row"])
    changed = F.col("n_removed") > 0
    text = F.when(changed, F.col("kept")).otherwise(F.col("text"))
    new = {"doc_id": F.col("doc_id"), "text": text, "n_chars": F.when(changed, F.length("kept").cast("long")).otherwise(F.col("_row.n_chars"))}
    rows = cut.filter(~changed | (F.col("n_removed") < F.col("n_words")))
    return rows.select([new[c].alias(c) if c in new else F.col(f"_row.{c}") for c in docs.columns])


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources mixed to weights 5, 2, 1: documents repeat for each epoch, and the last one of each budget is cut to fit."""
    mixed = mixed_rows(docs)
    return mixed.withColumn("n_chars", F.length("text").cast("long"))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row's token ids, packed as little-endian unsigned 32-bit integers, with their number and whether they decode to the text."""
    import public_tokenizers

    coded = encode(docs.select("doc_id", "lang", "source", "text"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, decoded="decoded")
    whole = F.col("decoded") == F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return coded.select("doc_id", "lang", "source", F.floor(F.length("ids") / 4).alias("n_tokens"), "ids", whole.alias("round_trip"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("mixture", mixture),
    ("tokens", tokens),
]

#: No SQL: the language model is fitted, and the tokens are byte-level BPE. Tests compare with plain versions.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Apply all stages to the documents of a table folder, each written as Parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for n, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if n < len(STAGES) - 1:
            docs = stored(docs)
    return docs
