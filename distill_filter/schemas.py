"""Declared schemas of the tables that the engine reads and keeps, and a check on read."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import ByteType, DoubleType, IntegerType, LongType, StringType, StructField, StructType

KINDS = {"bigint": LongType(), "int": IntegerType(), "tinyint": ByteType(), "string": StringType(), "double": DoubleType()}


def declared(columns: str) -> StructType:
    """A schema from `name type, ...`, without a session."""
    return StructType([StructField(name, KINDS[kind]) for name, kind in (c.split() for c in columns.split(","))])


DOCUMENTS = declared("doc_id bigint, text string, lang string, source string, n_chars bigint")
SNIPPETS = declared("snippet_id string, doc_id bigint, seq int, text string, n_tokens int")
VERDICTS = declared("spec string, teacher_id string, snippet_id string, call_no int, verdict tinyint, reason string, n_in_tokens int, n_out_tokens int")
BAND_TRACE = declared("policy string, round int, t bigint, lo double, hi double, s_hat double, loss double, beta double, bought int")
LABELS = declared("policy string, round int, ord int, snippet_id string, stream_pos bigint, verdict int")


def require_columns(df: DataFrame, schema: StructType, what: str = "table") -> DataFrame:
    """df, if it has the schema's columns with their types; other columns pass through."""
    have = {f.name: f.dataType for f in df.schema}
    missing = [f.name for f in schema if f.name not in have]
    wrong = [f"{f.name}: {have[f.name].simpleString()}, not {f.dataType.simpleString()}" for f in schema if f.name in have and have[f.name] != f.dataType]
    if missing or wrong:
        raise ValueError(f"{what}: missing {missing}, wrong {wrong}")
    return df
