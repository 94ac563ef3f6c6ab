"""Functions for SQL users: rules and students by name, a table function that cuts snippets, and grouped fits."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType

from ..operators import students
from ..operators.teacher import COMMON_SHARE, HOSTILE, JUNK_MARKS, LEGAL, REPEAT
from .text import BLANK


def rule_sql(common: list[str] | None = None) -> str:
    """The five rules as one SQL expression over spec and t, as the columns of operators.teacher state them.

    Null text: as empty. An unknown spec: null. Without `common`, as there, no token counts as mainstream.
    """
    text = lambda x: "'" + x.replace("\\", "\\\\").replace("'", "\\'") + "'"
    among = lambda words: ", ".join(map(text, words))
    toks = f"filter(split(coalesce(t, ''), {text(BLANK)}), x -> x <> '')"
    junk = " OR ".join(f"contains(coalesce(t, ''), {text(m)})" for m in JUNK_MARKS)
    legal = " OR ".join(f"lower(coalesce(t, '')) RLIKE {text(p)}" for p in LEGAL)
    cases = {
        "topic_hostile": f"exists({toks}, x -> regexp_replace(lower(x), '[^a-z]', '') IN ({among(HOSTILE)}))",
        "topic_legal": legal,
        "topic_private": f"exists({toks}, x -> x RLIKE '[0-9]')",
        "mainstream": f"size(filter({toks}, x -> lower(x) IN ({among(common or [''])}))) >= {COMMON_SHARE} * size({toks})",
        "quality": f"NOT ({junk} OR size(array_distinct(transform({toks}, x -> lower(x)))) < {REPEAT} * size({toks}))",
    }
    return "CASE spec " + " ".join(f"WHEN '{k}' THEN CAST(({v}) AS INT)" for k, v in cases.items()) + " END"


class CutSnippets:
    """SELECT * FROM documents, LATERAL cut_snippets(text, 64)"""

    def eval(self, text: str, width: int) -> Iterator[tuple[int, str, int]]:
        words = [w for w in re.split(BLANK, text or "") if w]
        for k in range(0, len(words), width):
            yield k // width, " ".join(words[k : k + width]), len(words[k : k + width])


def register(spark: SparkSession, models: dict[str, students.LogOdds] | None = None, common: list[str] | None = None) -> None:
    """teacher_verdict(spec, text), passes(filter, text) for each model, and the table function cut_snippets(text, width).

    common: the tokens that the mainstream rule goes by, a list that teacher.common_tokens bounds.
    """
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION teacher_verdict(spec STRING, t STRING) RETURNS INT RETURN {rule_sql(common)}")
    spark.udtf.register("cut_snippets", F.udtf(CutSnippets, returnType="seq: int, snippet: string, n_tokens: int"))
    if models:
        held = models

        @F.pandas_udf(IntegerType())
        def passes(name: pd.Series, line: pd.Series) -> pd.Series:
            def one(n: str, x: str | None) -> int | None:
                m = held.get(n)
                return None if m is None else int(m.prior + sum(m.weights.get(t, 0) for t in set((x or "").split(" "))) > 0)

            return pd.Series([one(n, x) for n, x in zip(name, line, strict=True)], dtype="Int32")

        spark.udf.register("passes_line", passes)
        shape = "regexp_replace(regexp_replace(regexp_replace(regexp_replace(t, '[^ -~]', ''), '[A-Z]+', '^'), '[a-z]+', 'L'), '[0-9]+', 'D')"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION passes(f STRING, t STRING) RETURNS INT RETURN passes_line(f, concat(lower(t), ' ', {shape}))")


def cuts_per_filter(scored: DataFrame) -> DataFrame:
    """scored(filter, margin_micro, label) to one empirical cut for each filter: a group is a filter's distinct scores."""

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        f = frame.sort_values("margin_micro")
        wrong = f.n1.cumsum() + f.n0.sum() - f.n0.cumsum()
        at = int(wrong.to_numpy().argmin())
        below = float(f.n0.sum()) <= float(wrong.iloc[at])
        return pd.DataFrame({"filter": [f["filter"].iloc[0]], "cut": [-(1 << 62) if below else int(f.margin_micro.iloc[at])], "errors": [int(min(f.n0.sum(), wrong.iloc[at]))]})

    counts = scored.groupBy("filter", "margin_micro").agg(F.sum("label").alias("n1"), F.sum(1 - F.col("label")).alias("n0"))
    return counts.groupBy("filter").applyInPandas(one, "filter string, cut bigint, errors bigint")
