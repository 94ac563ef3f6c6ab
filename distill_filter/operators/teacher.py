"""Simulated annotators: rules for the five filters, noise, grades, reasons, and a cache that pays each call once."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import TeacherConfig
from ..functions.hashing import SPAN, hash_int
from ..functions.text import letters_only, tokens

#: The hostile lexicon, the licence phrases, and the junk marks of the rules.
HOSTILE = ("disgusting", "idiot", "clown", "loser", "moron", "pathetic", "scum", "stupid", "trash", "worthless")
LEGAL = ("all rights reserved", "licen[cs]ed under", "released under", "copyright")
JUNK_MARKS = ("***", "###", "%%%", "&&&", "$$$", "!! ", " | ")
#: The weak teacher knows only these insults and marks.
WEAK_HOSTILE, WEAK_JUNK = HOSTILE[:4], JUNK_MARKS[:3]
COMMON_SHARE, COMMON_DF, REPEAT = 0.30, 0.05, 0.3


def evidence(spec: str, text: Column, weak: bool = False) -> Column:
    """How many signs of the spec's target a snippet shows; for quality: how many signs of junk."""
    toks = tokens(text)
    if spec == "topic_hostile":
        words = WEAK_HOSTILE if weak else HOSTILE
        return F.size(F.filter(toks, lambda t: letters_only(t).isin(*words)))
    if spec == "topic_legal":
        found = [F.lower(text).rlike(p).cast("int") for p in (LEGAL[:1] if weak else LEGAL)]
        return sum(found[1:], found[0])
    if spec == "topic_private":
        return F.size(F.filter(toks, lambda t: t.rlike("[0-9]{5}" if weak else "[0-9]")))
    if spec == "quality":
        marks = [F.contains(text, F.lit(m)).cast("int") for m in (WEAK_JUNK if weak else JUNK_MARKS)]
        repeats = (F.size(F.array_distinct(F.transform(toks, F.lower))) < REPEAT * F.size(toks)).cast("int")
        return sum(marks, F.lit(0) if weak else repeats)
    raise ValueError(f"{spec} has no rule over the text alone")


def common_tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(token): lower-cased tokens that occur in COMMON_DF of all documents at least; 1 / COMMON_DF times the mean number of tokens at most."""
    seen = docs.select(F.explode(F.array_distinct(F.transform(tokens(F.col(text_col)), F.lower))).alias("token")).groupBy("token").agg(F.count("*").alias("df"))
    return seen.crossJoin(F.broadcast(docs.agg(F.count("*").alias("n")))).where(F.col("df") >= COMMON_DF * F.col("n")).select("token")


def rule(spec: str, text: Column, weak: bool = False, common: list[str] | None = None) -> Column:
    """The exact verdict, 1 for pass."""
    if spec == "mainstream":
        toks = tokens(text)
        share = F.size(F.filter(toks, lambda t: F.lower(t).isin(*(common or [""]))))
        return (share >= (COMMON_SHARE + 0.1 * weak) * F.size(toks)).cast("int")
    n = evidence(spec, text, weak)
    return ((n == 0) if spec == "quality" else (n > 0)).cast("int")


def pass_probability(spec: str, text: Column, config: TeacherConfig, common: list[str] | None = None) -> Column:
    """What a call says on average: the rule, softened by noise, or graded by the amount of evidence."""
    weak = config.teacher_id == "weak"
    if config.mode == "graded":
        n = evidence(spec, text, weak)
        up = F.element_at(F.array(*(F.lit(x) for x in (0.05, 0.35, 0.65, 0.85, 0.95))), F.least(n, F.lit(4)) + 1)
        return F.lit(1.0) - up if spec == "quality" else up
    y = rule(spec, text, weak, common)
    if config.mode == "noisy":
        return F.when(y == 1, F.lit(1 - config.eps_pos)).otherwise(F.lit(config.eps_neg))
    return y.cast("double")


def verdict(spec: str, text: Column, snippet_id: Column, config: TeacherConfig = TeacherConfig(), call_no: int | Column = 0, common: list[str] | None = None) -> Column:
    """One call's verdict; repeat calls draw anew, a call repeated with the same number says the same."""
    if config.mode == "exact":
        return rule(spec, text, config.teacher_id == "weak", common)
    draw = hash_int(config.teacher_id, spec, snippet_id, F.lit(call_no) if isinstance(call_no, int) else call_no)
    return (draw < F.floor(pass_probability(spec, text, config, common) * SPAN)).cast("int")


def reason(spec: str, text: Column) -> Column:
    """The words or marks that a verdict stands on, comma-joined; empty if there are none."""
    if spec == "topic_hostile":
        found = F.filter(F.transform(tokens(text), letters_only), lambda t: t.isin(*HOSTILE))
    elif spec == "topic_private":
        found = F.filter(tokens(text), lambda t: t.rlike("[0-9]"))
    elif spec == "topic_legal":
        found = F.filter(F.array(*(F.when(F.lower(text).rlike(p), F.lit(p)) for p in LEGAL)), lambda t: t.isNotNull())
    else:
        found = F.filter(F.array(*(F.when(F.contains(text, F.lit(m)), F.lit(m)) for m in JUNK_MARKS)), lambda t: t.isNotNull())
    return F.array_join(F.array_sort(F.array_distinct(found)), ",")


def annotate(snippets: DataFrame, spec: str, config: TeacherConfig = TeacherConfig(), call_no: int = 0, common: list[str] | None = None, with_reason: bool = False) -> DataFrame:
    """snippets with a verdict column, and the reason where it is asked for: the full-teacher baseline is this on everything."""
    out = snippets.withColumn("verdict", verdict(spec, F.col("text"), F.col("snippet_id"), config, call_no, common))
    return out.withColumn("reason", reason(spec, F.col("text"))) if with_reason else out


def ask(requests: DataFrame, cache: DataFrame, spec: str, config: TeacherConfig = TeacherConfig(), call_no: int = 0) -> tuple[DataFrame, DataFrame]:
    """(new, all): verdicts of requests(snippet_id, text) that the cache lacks, and all that were asked for.

    The cache holds (spec, teacher_id, snippet_id, call_no, verdict); a call is billed once, however often it is asked,
    retried or asked twice in one request.
    """
    mine = cache.where((F.col("spec") == spec) & (F.col("teacher_id") == config.teacher_id) & (F.col("call_no") == call_no))
    missing = requests.dropDuplicates(["snippet_id"]).join(mine.select("snippet_id"), "snippet_id", "left_anti")
    new = annotate(missing, spec, config, call_no).select(F.lit(spec).alias("spec"), F.lit(config.teacher_id).alias("teacher_id"), "snippet_id", F.lit(call_no).alias("call_no"), "verdict")
    known = mine.select("spec", "teacher_id", "snippet_id", "call_no", "verdict").join(requests.select("snippet_id").distinct(), "snippet_id", "left_semi")
    return new, known.select(new.columns).union(new)
