"""Web pages as documents, by patterns alone (a plain projection; no UDF)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

DROPPED = r'(?s)<!--.*?-->|<script.*?</script>|<style.*?</style>|<nav.*?</nav>|<head.*?</head>|<footer.*?</footer>|<div class="ad">.*?</div>'
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&middot;", "·"), ("&amp;", "&"))


def page_text(html: Column) -> Column:
    """Visible text on one line."""
    text = F.regexp_replace(F.regexp_replace(html, DROPPED, " "), "<[^>]*>", " ")
    for a, b in ENTITIES:
        text = F.replace(text, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(text, r"\s+", " "))


def pages_as_documents(pages: DataFrame) -> DataFrame:
    """Pages in the schema of documents; the language from the page's own mark."""
    text = page_text(F.col("html"))
    lang = F.regexp_extract("html", r'<html lang="([a-z]+)"', 1)
    return pages.select(F.col("page_id").alias("doc_id"), text.alias("text"), lang.alias("lang"), F.lit("web").alias("source")).withColumn("n_chars", F.length("text").cast("long"))
