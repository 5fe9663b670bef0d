"""Page context: title, navigation anchors and paragraphs of raw HTML."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

#: Entities and what they stand for; the ampersand comes last.
ENTITIES = [("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")]


def visible(html: Column) -> Column:
    """HTML without scripts, styles and comments."""
    out = F.coalesce(html, F.lit(""))
    for pattern in ("(?is)<script\\b.*?</script>", "(?is)<style\\b.*?</style>", "(?s)<!--.*?-->"):
        out = F.regexp_replace(out, pattern, "")
    return out


def plain(markup: Column) -> Column:
    """Text of a fragment: tags out, entities decoded, white space folded."""
    out = F.regexp_replace(markup, "<[^>]*>", " ")
    for entity, char in ENTITIES:
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(out, "[ \\t\\r\\n]+", " "))


def context(pages: DataFrame) -> DataFrame:
    """(page_id, title, anchors, paragraphs) of ``pages`` (page_id, html)."""
    shown = pages.select("page_id", visible(F.col("html")).alias("h"))
    found = lambda tag: F.transform(F.regexp_extract_all("h", F.lit(f"(?is)<{tag}\\b[^>]*>(.*?)</{tag}>"), F.lit(1)), plain)
    return shown.select("page_id", F.element_at(F.concat(found("title"), F.array(F.lit(""))), 1).alias("title"), found("a").alias("anchors"), found("p").alias("paragraphs"))
