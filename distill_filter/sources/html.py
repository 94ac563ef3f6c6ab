"""Web pages to text, with built-in functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Elements that go with all they hold, and the entities that are read.
DROPPED = ("script", "style", "nav", "head")
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&"))


def page_text(html: Column) -> Column:
    """Comments, dropped elements and tags out, entities read, white space runs to one space."""
    text = F.regexp_replace(html, "(?s)<!--.*?-->", " ")
    for name in DROPPED:
        text = F.regexp_replace(text, f"(?s)<{name}[ >].*?</{name}>", " ")
    text = F.regexp_replace(text, "<[^>]*>", " ")
    for entity, char in ENTITIES:
        text = F.replace(text, F.lit(entity), F.lit(char))
    return F.btrim(F.regexp_replace(text, "[ \t\n\r]+", " "))


def pages_as_documents(pages: DataFrame) -> DataFrame:
    """(doc_id, text, host): pages in the shape that snippets are cut from."""
    return pages.select(F.col("page_id").alias("doc_id"), page_text(F.col("html")).alias("text"), F.parse_url("url", F.lit("HOST")).alias("host"))
