"""The queries of the operators in this subpackage, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

Query = Callable[[SparkSession, str], DataFrame]


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_curve_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.curve_search import search

    vectors = _table(spark, sf_dir, "embeddings")
    return search(vectors, vectors.filter("vec_id % 20 = 0"))


def op2_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.common import stored
    from factbench.llm.mixture import count_words, mix

    docs = _table(spark, sf_dir, "documents")
    slim = stored(docs.select("doc_id", "source", count_words("text").alias("size")))
    return mix(slim, "size").select("doc_id", "size", "source_size", "target", "taken")


def op3_kernel_langid(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.kernel_langid import predict, train

    docs = _table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held_out = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))
    model = train(docs, ~held_out)
    out = predict(docs.select("doc_id", "text"), model, carry=["doc_id"])
    return out.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def op4_repeat_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.repeat_windows import remove_repeats

    out = remove_repeats(_table(spark, sf_dir, "documents"), window=13)
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op5_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.url_templates import judge

    bad = F.greatest(1 - F.col("quality"), F.col("toxic")).alias("bad")
    labels = _table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), bad)
    return judge(_table(spark, sf_dir, "pages"), labels)


def op6_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from factbench.llm.byte_bpe import encode

    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    coded = encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN, decoded="decoded", carry=["doc_id"])
    return coded.select("doc_id", F.floor(F.length("ids") / 4).alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op7_token_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.token_groups import link_groups

    return link_groups(_table(spark, sf_dir, "documents"), words=4, threshold=85)


def op8_perspectives(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.perspectives import rotate

    out = rotate(_table(spark, sf_dir, "conversations"))
    masks = F.array_join(F.transform("masks", lambda m: F.concat_ws("-", m["start"], m["end"])), ",")
    return out.withColumn("masks", masks)


def op9_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.multi_index import near_groups

    return near_groups(_table(spark, sf_dir, "embeddings"), threshold=0.9)


def op10_bin_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from factbench.llm.bin_shards import shard

    rows = shard(_table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir).withColumn("ids", F.sha2("ids", 256)).withColumnRenamed("ids", "ids_sha256")


QUERIES: dict[str, Query] = {
    "op1_curve_search": op1_curve_search,
    "op2_mixture": op2_mixture,
    "op3_kernel_langid": op3_kernel_langid,
    "op4_repeat_windows": op4_repeat_windows,
    "op5_url_templates": op5_url_templates,
    "op6_byte_bpe": op6_byte_bpe,
    "op7_token_groups": op7_token_groups,
    "op8_perspectives": op8_perspectives,
    "op9_multi_index": op9_multi_index,
    "op10_bin_shards": op10_bin_shards,
    "pipeline": pipeline,
}

#: Least node that links (a, b), both ways round, reach; names: the nodes' table.
_REACH = """reach(node, r) AS (SELECT {node}, {node} FROM {names} UNION SELECT reach.node, l.b FROM reach JOIN links l ON l.a = reach.r)"""

_VALID = "SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0"

ORACLES: dict[str, str] = {
    "op1_curve_search": f"""
WITH v AS ({_VALID}),
s AS (SELECT q.vec_id AS query_id, v.vec_id, list_reduce(list_transform(list_zip(q.e, v.e), lambda p: p[1] * p[2]), lambda x, y: x + y) AS score FROM v q JOIN v ON q.vec_id % 20 = 0 AND q.vec_id <> v.vec_id)
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s QUALIFY rank <= 20
""",
    "op4_repeat_windows": r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
i AS (SELECT doc_id, ws, unnest(range(1, len(ws) - 11)) AS i FROM d),
p AS (SELECT doc_id, i, array_to_string(ws[i:i + 12], ' ') AS win FROM i),
m AS (SELECT win, min(doc_id) AS least FROM p GROUP BY win),
f AS (SELECT doc_id, i FROM p JOIN m USING (win) WHERE doc_id > least),
g AS (SELECT DISTINCT doc_id, i + k AS at_ FROM f, range(13) r(k)),
w AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS at_ FROM d),
k AS (SELECT w.doc_id, string_agg(word, ' ' ORDER BY at_) AS kept, count(*) AS n FROM w ANTI JOIN g ON w.doc_id = g.doc_id AND w.at_ = g.at_ GROUP BY 1)
SELECT d.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(len(ws) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)
""",
    "op7_token_groups": r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
i AS (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 2, 2))) AS i FROM d WHERE len(ws) > 0),
s AS (SELECT DISTINCT doc_id, array_to_string(ws[i:i + 3], ' ') AS shingle FROM i),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS common FROM s a JOIN s b ON a.shingle = b.shingle AND a.doc_id <> b.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * common >= 85 * (x.n + y.n - common)),
""" + _REACH.format(node="doc_id", names="d") + """
SELECT d.doc_id, coalesce(max(n.n), 0) AS n_shingles, min(r) AS component_id FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN reach ON reach.node = d.doc_id GROUP BY d.doc_id
""",
    "op9_multi_index": f"""
WITH RECURSIVE v AS ({_VALID}),
links AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.9),
""" + _REACH.format(node="vec_id", names="embeddings") + """,
n AS (SELECT a, count(*) AS n FROM links GROUP BY 1)
SELECT vec_id, coalesce(max(n), 0) AS n_links, min(r) AS component_id, vec_id = min(r) AS kept FROM embeddings LEFT JOIN n ON a = vec_id JOIN reach ON node = vec_id GROUP BY vec_id
""",
    "op2_mixture": r"""
WITH d AS (
  SELECT doc_id, source, CAST(CASE WHEN text IS NULL THEN 0 ELSE len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) END AS BIGINT) AS size,
         md5('mix-1:' || coalesce(CAST(doc_id AS VARCHAR), '-')) AS k FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
r AS (SELECT *, row_number() OVER (ORDER BY source NULLS LAST) AS at_ FROM s),
w AS (SELECT *, CASE (at_ - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS w, 2.0::DOUBLE * source_size AS cap FROM r),
c AS (SELECT *, sum(cap) OVER o AS caps, sum(w) OVER () - sum(w) OVER o AS rest, 1.5::DOUBLE * CAST(sum(source_size) OVER () AS BIGINT) AS al
      FROM w WINDOW o AS (ORDER BY cap / w, at_ ROWS UNBOUNDED PRECEDING)),
f AS (SELECT *, caps + cap / w * rest <= al AS full_ FROM c),
t AS (SELECT source, source_size, CASE WHEN full_ THEN cap ELSE (al - sum(CASE WHEN full_ THEN cap ELSE 0 END) OVER ()) / sum(CASE WHEN full_ THEN 0 ELSE w END) OVER () * w END AS target FROM f),
p AS (SELECT doc_id, source, size, CAST(coalesce(sum(size) OVER (PARTITION BY source ORDER BY k, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before_ FROM d),
j AS (SELECT p.*, t.source_size, t.target, CAST(floor(t.target) AS BIGINT) AS budget,
             CASE WHEN t.source_size > 0 THEN CAST(floor(floor(t.target) / t.source_size) AS BIGINT) ELSE 0 END AS epochs
      FROM p JOIN t ON p.source IS NOT DISTINCT FROM t.source)
SELECT doc_id, size, source_size, target, CAST(epochs * size + greatest(0, least(size, budget - epochs * source_size - before_)) AS BIGINT) AS taken FROM j
""",
    "op8_perspectives": r"""
WITH r AS (SELECT conv_id, turn, coalesce(role, 'unknown') AS who, coalesce(text, '') AS txt FROM conversations),
s AS (SELECT *, coalesce(sum(length(txt) + 16) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, who, txt ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS seq FROM r),
c AS (SELECT DISTINCT conv_id, who AS perspective FROM r WHERE who <> 'system'),
e AS (SELECT s.*, c.perspective, CAST(seq // 1048576 AS INTEGER) AS part, replace(txt, '<|', '<||') AS body,
      CASE WHEN who = perspective THEN '<|assistant|>' || chr(10) WHEN who = 'system' THEN '<|system|>' || chr(10)
      ELSE '<|user name=' || replace(replace(replace(replace(replace(replace(who, '%', '%25'), '<', '%3C'), '|', '%7C'), '>', '%3E'), chr(10), '%0A'), chr(13), '%0D') || '|>' || chr(10) END AS head
      FROM s JOIN c ON s.conv_id IS NOT DISTINCT FROM c.conv_id),
b AS (SELECT *, length(head) + length(body) + 8 AS n FROM e),
o AS (SELECT *, CAST(coalesce(sum(n) OVER (PARTITION BY conv_id, perspective, part ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS at_ FROM b)
SELECT conv_id, perspective, part, CAST(count(*) AS INTEGER) AS n_turns, CAST(sum(CASE WHEN who = perspective THEN 1 ELSE 0 END) AS INTEGER) AS n_own,
       string_agg(head || body || '<|end|>' || chr(10), '' ORDER BY seq) AS rendered,
       coalesce(string_agg(CASE WHEN who = perspective THEN CAST(at_ + length(head) AS VARCHAR) || '-' || CAST(at_ + n - 1 AS VARCHAR) END, ',' ORDER BY seq), '') AS masks
FROM o GROUP BY conv_id, perspective, part
""",
}
