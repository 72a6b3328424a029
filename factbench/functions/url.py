"""URLs: host, registrable domain, canonical form, archives, platforms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factbench.sources.io import small

#: Wrapping archives put the original URL behind a run of digits; archives may wrap each other. Fixed value.
WRAPPED = r"^(?:https?://[^/]+/(?:web/)?[0-9]{4,14}[a-z_]*/)+(https?://.+)$"
#: Hosts whose archive URLs hide the original behind a short code. Fixed values.
OPAQUE_HOSTS = ("perma.cc", "archive.ph", "archive.is", "archive.today", "ghostarchive.org")


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def host(url: Column | str) -> Column:
    return F.lower(F.regexp_extract(_c(url), r"^[a-zA-Z]+://(?:[^/?#@]*@)?([^/?#:]+)", 1))


#: Suffixes of two labels under which names are registered. Fixed values; callers may give others.
SUFFIXES = (
    "ac.uk", "co.uk", "gov.uk", "org.uk", "com.ar", "com.au", "net.au", "org.au", "com.bd", "com.br", "net.br", "org.br", "com.cn", "com.co", "com.eg", "com.hk",
    "co.id", "or.id", "co.il", "org.il", "co.in", "org.in", "ac.jp", "co.jp", "or.jp", "co.ke", "co.kr", "or.kr", "com.mx", "com.my", "com.ng", "co.nz", "org.nz",
    "com.pe", "com.ph", "com.pk", "com.pl", "com.sg", "com.tr", "com.tw", "org.tw", "com.ua", "com.ve", "com.vn", "co.za", "org.za",
)


def registrable_domain(url: Column | str, suffixes: tuple[str, ...] = SUFFIXES) -> Column:
    """The label before the public suffix, and the suffix: the last label of the host, or its last two if they are a listed suffix."""
    known = "|".join(s.replace(".", r"\.") for s in suffixes)
    return F.regexp_extract(host(url), rf"([^.]+\.(?:{known})|[^.]+\.[^.]+)$" if suffixes else r"([^.]+\.[^.]+)$", 1)


def canonical(url: Column | str) -> Column:
    """Scheme https, lower-case host without www. or m., no query, fragment, page extension or trailing slash."""
    c = F.regexp_replace(_c(url), r"[?#].*$", "")
    c = F.regexp_replace(c, r"^[a-zA-Z]+://(?:www\.|m\.)*", "https://")
    c = F.regexp_replace(c, r"\.(?:html|htm|php)$", "")
    c = F.regexp_replace(c, r"/+$", "")
    return F.concat(F.lit("https://"), F.lower(F.regexp_extract(c, r"^https://([^/]*)", 1)), F.regexp_extract(c, r"^https://[^/]*(.*)$", 1))


def is_archived(url: Column | str) -> Column:
    return _c(url).rlike(WRAPPED) | host(url).isin(*OPAQUE_HOSTS)


def unwrap_archive(url: Column | str) -> Column:
    """The original behind wrapping archives, however many; other URLs as they are."""
    return F.regexp_replace(_c(url), WRAPPED, "$1")


def resolve_archives(df: DataFrame, url: str, codes: DataFrame) -> DataFrame:
    """Add ``original`` and ``archived``; opaque codes come from a table (archive_url, original_url), one row a code."""
    looked = small(codes.select(F.col("archive_url").alias("_a"), F.col("original_url").alias("_o")))
    out = df.join(looked, F.col(url) == F.col("_a"), "left")
    return out.withColumn("original", F.coalesce("_o", unwrap_archive(url))).withColumn("archived", is_archived(url)).drop("_a", "_o")


def platform(url: Column | str) -> Column:
    return F.regexp_extract(registrable_domain(url), r"^([^.]+)", 1)
