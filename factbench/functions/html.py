"""HTML: main text and links with regular expressions that Java and RE2 read alike."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: What is not article text, in the order of removal: scripts first, as their strings may hold tags. Fixed values.
NOISE = (r"(?s)<!--.*?-->", r"(?s)<script[^>]*>.*?</script>", r"(?s)<style[^>]*>.*?</style>", r"(?s)<nav[^>]*>.*?</nav>", r"(?s)<footer[^>]*>.*?</footer>", r'(?s)<div class="ad"[^>]*>.*?</div>')
BREAKS = r"(?i)</(?:p|h[1-6]|li|div|tr|article)>|<br\s*/?>"
#: Entities decoded last, ampersand after the rest. Fixed values.
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&middot;", "·"), ("&copy;", "©"), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&"))


def _c(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def denoised(html: Column | str) -> Column:
    c = _c(html)
    for pattern in NOISE:
        c = F.regexp_replace(c, pattern, "")
    return c


def article_html(html: Column | str) -> Column:
    """The article element, or the body, or all there is."""
    c = denoised(html)
    found = F.regexp_extract(c, r"(?s)<article[^>]*>(.*?)</article>", 1)
    body = F.regexp_extract(c, r"(?s)<body[^>]*>(.*)</body>", 1)
    return F.when(found != "", found).when(body != "", body).otherwise(c)


def plain(html: Column | str) -> Column:
    """Text without tags, entities decoded, blanks squeezed; block ends become line feeds."""
    c = F.regexp_replace(_c(html), BREAKS, "\n")
    c = F.regexp_replace(c, r"<[^>]*>", "")
    for entity, char in ENTITIES:
        c = F.replace(c, F.lit(entity), F.lit(char))
    c = F.regexp_replace(c, r"[ \t]+", " ")
    c = F.regexp_replace(c, r" ?\n[ \n]*", "\n")
    return F.regexp_replace(c, r"^[ \n]+|[ \n]+$", "")


def main_text(html: Column | str) -> Column:
    return plain(article_html(html))


def hrefs(html: Column | str) -> Column:
    return F.regexp_extract_all(_c(html), F.lit(r'href="([^"]*)"'), F.lit(1))


def bare_urls(text: Column | str) -> Column:
    return F.regexp_extract_all(_c(text), F.lit(r"https?://[^\s\"'<>]+"), F.lit(0))


def ld_json(html: Column | str) -> Column:
    """Blocks of linked data embedded in a page."""
    return F.regexp_extract_all(_c(html), F.lit(r'(?s)<script type="application/ld\+json">(.*?)</script>'), F.lit(1))
