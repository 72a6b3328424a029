"""URL filtering by rules and by a tree of path templates.

Per host, variable segments become wildcards, sibling branches of similar labelled shares merge, and leaves whose bad
share, smoothed toward that of their parent, is high are rejected. The tree grows level by level over distinct
generalised paths, never over pages.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.llm.common import settles, stored

#: (host, path) that a rule names, and its verdict. Fixed values.
RULES = (("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block"))

_PARTS = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def url_host(url: str) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end, A-Z lower-cased; empty for null or no ``://``."""
    return F.coalesce(F.translate(F.regexp_extract(url, _PARTS, 1), string.ascii_uppercase, string.ascii_lowercase), F.lit(""))


def url_path(url: str) -> Column:
    """After the host up to ``?``, ``#`` or the end; empty for null or no ``://``."""
    return F.coalesce(F.regexp_extract(url, _PARTS, 2), F.lit(""))


def matched_rule(host: str, path: str, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest rule that fits; null if none does. A rule fits its host and all subdomains."""
    out = F.lit(None)
    for domain, start, verdict in sorted(rules, key=lambda r: (len(r[0] + r[1]), r)):
        fits = ((F.col(host) == domain) | F.col(host).endswith(f".{domain}")) & F.col(path).startswith(start)
        out = F.when(fits, F.struct(F.lit(domain + start).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def segments(path: str, depth: int) -> Column:
    """Segments with variable parts generalised by form; those from place ``depth`` on are one segment, so that nothing is lost."""
    known = F.filter(F.split(path, "/"), lambda s: s != "")
    shape = lambda s: F.regexp_replace(F.regexp_replace(s, r"^(?=.*[0-9])[0-9A-Fa-f-]{8,}", "{hex}"), r"(?<!\{)[0-9]+", "{num}")
    out = F.transform(known, shape)
    tail = F.array(F.array_join(F.slice(out, depth, F.greatest(F.lit(1), F.size(out))), "/"))
    return F.when(F.size(out) > depth, F.concat(F.slice(out, 1, depth - 1), tail)).otherwise(out)


def _share(bad: Column, labelled: Column, toward: Column, strength: float) -> Column:
    """Share of bad labels, smoothed by ``strength`` pseudo-labels at another share."""
    return (bad + strength * toward) / (labelled + strength)


@settles
def templates(pages: DataFrame, labels: DataFrame, fan: int = 20, rare: float = 0.05, z: float = 1.96, few: int = 5, support: int = 30, close: float = 0.1, strength: float = 10.0) -> DataFrame:
    """(path_key, template, n, labelled, bad, impurity, backing): the template of every distinct generalised path.

    ``pages`` has page_id, path_key, host and segs; ``labels`` has page_id and bad (0 or 1). A child stays itself if
    its bad share differs from its siblings' by more than ``z`` standard errors, or if it has ``support`` labels
    and its share is not within ``close`` of theirs; the others merge into ``*``. So do, among more than ``fan`` children,
    those with under ``rare`` of their parent's pages and under ``few`` labels. ``impurity`` is a template's bad share,
    smoothed toward its parent's, the host's toward the share of all labels; ``backing`` is the number of labels
    behind it, pseudo-labels included.
    """
    # a page's label comes in by key; hosts of any size are combined before the shuffle
    rows = pages.join(labels, "page_id", "left")
    paths = stored(rows.groupBy("path_key", "host", "segs").agg(F.count(F.lit(1)).alias("n"), F.count("bad").alias("labelled"), F.sum(F.coalesce("bad", F.lit(0))).alias("bad")))
    deepest, prior = paths.agg(F.max(F.size("segs")), F.try_divide(F.sum("bad"), F.sum("labelled"))).first()
    hosts = paths.groupBy("host").agg(F.sum("labelled").alias("_l"), F.sum("bad").alias("_b"))
    hosts = hosts.select("host", _share(F.col("_b"), F.col("_l"), F.lit(prior or 0.0), strength).alias("impurity"), (F.col("_l") + strength).alias("backing"))
    tree = stored(paths.join(hosts, "host").withColumn("prefix", F.col("host")))
    for level in range((deepest or 0) + 1):
        tree = tree.withColumn("child", F.coalesce(F.get("segs", F.lit(level)), F.lit("")))
        kids = tree.groupBy("prefix", "child").agg(*[F.sum(c).alias(f"k_{c}") for c in ("n", "labelled", "bad")], F.max("impurity").alias("above"))
        above = kids.groupBy("prefix").agg(F.count(F.lit(1)).alias("kids"), *[F.sum(f"k_{c}").alias(f"p_{c}") for c in ("n", "labelled", "bad")])
        rest, pooled = F.col("p_labelled") - F.col("k_labelled"), F.try_divide("p_bad", "p_labelled")
        error = F.sqrt(pooled * (1 - pooled) * (F.try_divide(F.lit(1), F.col("k_labelled")) + F.try_divide(F.lit(1), rest)))
        off = F.abs(F.try_divide("k_bad", "k_labelled") - F.try_divide(F.col("p_bad") - F.col("k_bad"), rest))
        apart = (off > z * error) | ((F.col("k_labelled") >= support) & (off > close))
        known = (F.col("k_labelled") > 0) & (rest > 0)
        named = F.when((F.col("child") == "") | (F.col("kids") == 1), F.col("child")).when((F.col("kids") > fan) & (F.col("k_n") < rare * F.col("p_n")) & (F.col("k_labelled") < few), "*").when(F.when(known, apart).otherwise(False), F.col("child")).otherwise("*")
        step = kids.join(above, "prefix").withColumn("_named", named)
        merged = step.groupBy("prefix", "_named").agg(F.sum("k_labelled").alias("_l"), F.sum("k_bad").alias("_b"), F.max("above").alias("_above"))
        merged = merged.select("prefix", "_named", _share(F.col("_b"), F.col("_l"), F.col("_above"), strength).alias("_impurity"), (F.col("_l") + strength).alias("_backing"))
        step = step.select("prefix", "child", "_named").join(merged, ["prefix", "_named"])
        tree = tree.join(step, ["prefix", "child"])
        # a path that ended above keeps its share; an only child has its parent's labels, and its share
        ends, same = F.size("segs") < level, (F.col("_backing") == F.col("backing"))
        tree = tree.withColumns({"impurity": F.when(ends | same, F.col("impurity")).otherwise(F.col("_impurity")), "backing": F.when(ends, F.col("backing")).otherwise(F.col("_backing"))})
        tree = tree.withColumn("prefix", F.when(F.col("_named") == "", F.col("prefix")).otherwise(F.concat_ws("/", "prefix", "_named"))).drop("_named", "child", "_impurity", "_backing")
        tree = stored(tree)  # each level reads the one before twice
    return tree.select("path_key", F.col("prefix").alias("template"), "n", "labelled", "bad", "impurity", "backing")


def judge(pages: DataFrame, labels: DataFrame, url: str = "url", rules=RULES, depth: int = 8, z: float = 1.96, reject: float = 0.5, **tree) -> DataFrame:
    """(page_id, host, path, rule, verdict, template, impurity) for every page.

    A fitting rule decides; else the page's template is blocked if its smoothed bad share is above ``reject``, or if
    that share less ``z`` standard errors is above the share of all labels. Null urls and urls without ``://`` have
    empty host and path. Pages without labels are judged as their template; with no labels at all everything the rules
    don't block is allowed. Repeated rows are judged alike; further columns are left out. Segments from place ``depth`` on
    count as one.
    """
    slim = pages.select("page_id", url_host(url).alias("host"), url_path(url).alias("path"))
    slim = slim.withColumn("segs", segments("path", depth)).withColumn("path_key", F.xxhash64("host", "segs"))
    marks = labels.filter("page_id is not null").groupBy("page_id").agg(F.max("bad").alias("bad"))
    known = templates(slim, marks, **tree)
    prior = known.agg(F.try_divide(F.sum("bad"), F.sum("labelled"))).first()[0] or 0.0
    least = F.col("impurity") - z * F.sqrt(F.col("impurity") * (1 - F.col("impurity")) / F.col("backing"))
    verdicts = known.select("path_key", "template", "impurity", ((F.col("impurity") > reject) | (least > prior)).alias("_bad"))
    ruled = matched_rule("host", "path", rules)
    return slim.join(verdicts, "path_key", "left").withColumn("_rule", ruled).select(
        "page_id", "host", "path", F.col("_rule.rule").alias("rule"),
        F.coalesce(F.col("_rule.verdict"), F.when(F.col("_bad"), "block").otherwise("allow")).alias("verdict"), "template", "impurity",
    )
