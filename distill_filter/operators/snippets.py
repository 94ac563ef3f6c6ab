"""Documents to snippets, and snippets to a repeatable random stream."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.hashing import SPAN, hash_int
from ..functions.text import tokens


def cut(docs: DataFrame, width: int = 64, overlap: int = 0, min_tokens: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(snippet_id, doc_id, seq, text, n_tokens): windows of `width` tokens, `width - overlap` apart; tails are kept.

    Null and blank texts give no snippet. One narrow pass: nothing is shuffled. Rows carry their own piece only, never their
    document's tokens: rows that wait for Python are copied whole.
    """
    step = width - overlap
    rows = docs.select(F.col(id_col).alias("doc_id"), tokens(F.col(text_col)).alias("toks")).select("doc_id", "toks", F.size("toks").alias("of"))
    last = F.greatest(F.ceil((F.col("of") - overlap) / step), F.lit(1)).cast("int") - 1
    pieces = F.transform(F.sequence(F.lit(0), last), lambda k: F.array_join(F.slice("toks", k * step + 1, width), " "))
    rows = rows.select("doc_id", "of", F.posexplode(F.when(F.col("of") >= max(min_tokens, 1), pieces)).alias("seq", "text"))
    n_tokens = F.least(F.lit(width), F.col("of") - F.col("seq") * step)
    rows = rows.select(F.concat_ws("#", "doc_id", "seq").alias("snippet_id"), "doc_id", "seq", "text", n_tokens.alias("n_tokens"))
    return rows.where(F.col("n_tokens") >= min_tokens) if min_tokens > 1 else rows


#: Rows that a bucket of the stream should hold: it is one task's sort.
BUCKET_ROWS = 1 << 18


def bucket_digits(rows: int) -> int:
    """Hex digits of the key that name a bucket, so that one holds BUCKET_ROWS rows or fewer: 2 at least."""
    return max(2, math.ceil(math.log(max(1, rows / BUCKET_ROWS), 16)))


def order(snippets: DataFrame, seed: int = 7, digits: int = 2) -> DataFrame:
    """snippets with stream_key, stream_bucket (16^digits of them) and stream_pos, the place in the order of md5(seed:snippet_id).

    A rank in two steps: rows are ranked inside their bucket, and bucket offsets, one row each, are broadcast. Only
    ids and keys need to move where the text is wanted later: see `order_ids`.
    """
    bucket = F.conv(F.substring("stream_key", 1, digits), 16, 10).cast("int")
    keyed = snippets.withColumn("stream_key", F.md5(F.concat_ws(":", F.lit(seed), "snippet_id"))).withColumn("stream_bucket", bucket)
    sizes = keyed.groupBy("stream_bucket").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("stream_bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("stream_bucket", before.alias("before"))
    inside = F.row_number().over(Window.partitionBy("stream_bucket").orderBy("stream_key", "snippet_id"))
    ranked = keyed.withColumn("inside", inside)
    return ranked.join(F.broadcast(offsets), "stream_bucket").withColumn("stream_pos", (F.col("before") + F.col("inside") - 1).cast("bigint")).drop("before", "inside")


def order_ids(snippets: DataFrame, seed: int = 7, digits: int = 2) -> DataFrame:
    """(snippet_id, stream_pos) alone: the text is not shuffled."""
    return order(snippets.select("snippet_id"), seed, digits).select("snippet_id", "stream_pos")


def prefix(snippets: DataFrame, seed: int = 7, share: float = 0.1) -> DataFrame:
    """The first `share` of the stream without ranking it: a narrow filter on the hash."""
    return snippets.where(F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), "snippet_id")), 1, 8), 16, 10).cast("bigint") < int(share * SPAN))


def first(snippets: DataFrame, n: int, seed: int = 7) -> DataFrame:
    """The first n rows of the stream, in one scan that keeps n rows a task: for an n that one task can hold."""
    return snippets.orderBy(F.md5(F.concat_ws(":", F.lit(seed), "snippet_id")), "snippet_id").limit(n)


def held_out(text: F.Column, share: float = 0.2, seed: int = 7) -> F.Column:
    """A split by hash of the text, so that copies of a text fall on one side."""
    return hash_int(f"test{seed}", text) < int(share * SPAN)
