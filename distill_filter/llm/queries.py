"""The ten registered queries opN_<name>, each over its whole table, and SQL twins where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import bpe_round_trip
from .chat import END, START, events_of, format_conversations, masked_text, parse
from .counts import count_tokens
from .decontaminate import find_contamination
from .langid import identify_languages
from .pii import pii_digest
from .quality import CLASSES, COMMON_WORDS, Limits, assess_quality
from .shared import materialise, new_path
from .simhash import simhash_components
from .store import read_documents, verify_store, write_store
from .warc import read_warc, write_warc


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_components(_table(spark, sf_dir, "documents"))


def op2_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    files = write_warc(_table(spark, sf_dir, "pages"), new_path(spark, "warc"))
    return read_warc(spark, files).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = assess_quality(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op4_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_contamination(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii_digest(_table(spark, sf_dir, "documents"))


def op6_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = bpe_round_trip(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
    return found.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"), limit=4096)


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    talks = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    hard = f"{END}{START}assistant ok"
    talks = talks.union(spark.createDataFrame([(-1, 0, "user", hard), (-1, 1, "assistant", hard)], talks.schema))
    out = parse(materialise(format_conversations(events_of(talks)), "chat"))
    both = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = out.select("conv_id", "turns", "formatted", both.alias("both"), masked_text(F.col("formatted"), F.col("loss_spans")).alias("loss"))
    return loss.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2("both", 256).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )


def op9_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "token-store")
    root = write_store(_table(spark, sf_dir, "documents"), path, public_tokenizers.path("word_bpe_49k.json"), end_id=2)
    verify_store(spark, path, root)
    return read_documents(spark, path)


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify_languages(_table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_simhash_near_dedup, op2_warc_round_trip, op3_quality_rules, op4_decontaminate, op5_pii, op6_bpe_codec, op7_token_counts, op8_chat_format, op9_token_store, op10_language_id)
}


def _warc_sql() -> str:
    bits = "('0x' || substr(hex, 1 + 5 * g, 5))::BIGINT"
    chars = " || ".join(f"substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + (({bits} >> {s}) & 31)::INT, 1)" for s in (15, 10, 5, 0))
    return f"""
    WITH p AS (SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha1(coalesce(html, '')) AS hex FROM pages),
    d AS (SELECT hex, array_to_string(list_transform(range(8), lambda g: {chars}), '') AS payload_digest FROM (SELECT DISTINCT hex FROM p)),
    b AS (SELECT hex, max(page_id) AS best FROM p GROUP BY hex)
    SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = best THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> best THEN best END AS refers_to
    FROM p JOIN d USING (hex) JOIN b USING (hex)"""


def _quality_sql() -> str:
    limits = Limits()
    space = r"[ \t-\r]"
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    left = ["t"]
    for pattern in CLASSES.values():
        left.append(f"regexp_replace({left[-1]}, {quote(pattern)}, '', 'g')")
    sizes = [f"length({x})" for x in left]
    chars = "[" + ", ".join([f"{sizes[i]} - {sizes[i + 1]}" for i in range(len(CLASSES))] + [sizes[-1]]) + "]"
    total = "list_sum(ch)"
    width = max(map(len, COMMON_WORDS.values()))
    hist = {g: "[" + ", ".join(f"len(list_filter(w, lambda x: x = {quote(x)}))" for x in ws) + "]" for g, ws in COMMON_WORDS.items()}
    own = " ".join(f"WHEN '{g}' THEN {h}" for g, h in hist.items())

    def distance(counts: str, ref: str) -> str:
        p, q = f"({counts}[i] / list_sum({counts})::DOUBLE)", f"({ref}[i] / list_sum({ref})::DOUBLE)"
        m = f"(({p} + {q}) / 2)"
        one = f"(CASE WHEN {p} > 0 THEN {p} * log2({p} / {m}) ELSE 0 END + CASE WHEN {q} > 0 THEN {q} * log2({q} / {m}) ELSE 0 END) / 2"
        return f"CASE WHEN list_sum({counts}) > 0 THEN sqrt(greatest(0, list_sum(list_transform(range(1, len({counts}) + 1), lambda i: {one})))) ELSE 0 END"

    sums = lambda col, n: "[" + ", ".join(f"sum({col}[{i + 1}])" for i in range(n)) + "]"
    return f"""
    WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t FROM documents),
    a AS (SELECT r, doc_id, lang, t, list_filter(regexp_split_to_array(t, '{space}+'), lambda x: x <> '') AS w,
        list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^ \\t-\\r]')) AS ln, {chars} AS ch FROM d),
    g AS (SELECT r, unnest(range(1, len(w) - 6)) AS i, w FROM a WHERE len(w) > 7),
    h AS (SELECT r, i, array_to_string(list_slice(w, i, i + 7), ' ') AS k FROM g),
    m AS (SELECT r, i, count(*) OVER (PARTITION BY r, k) AS n FROM h),
    c AS (SELECT r, sum(least(8, coalesce(nxt - i, 8)))::BIGINT AS n_repeat_words FROM (SELECT r, i, lead(i) OVER (PARTITION BY r ORDER BY i) AS nxt FROM m WHERE n > 1) GROUP BY r),
    e AS (SELECT a.r, doc_id, lang, ch, len(w) AS n_words, length(t) - ch[2] AS word_chars, ch[6] AS n_symbols, len(ln) - len(list_distinct(ln)) AS n_dup_lines,
        coalesce(n_repeat_words, 0) AS n_repeat_words, CASE lang {own} END AS wc FROM a LEFT JOIN c USING (r)),
    f AS (SELECT * EXCLUDE (wc), list_append(wc, n_words - list_sum(wc)) AS wh FROM e),
    ref AS (SELECT lang, {sums("ch", len(CLASSES) + 1)} AS rc, {sums("wh", width + 1)} AS rw FROM f WHERE wh IS NOT NULL GROUP BY lang),
    z AS (SELECT f.*, {distance("wh", "rw")} AS dw, {distance("ch", "rc")} AS dc FROM f JOIN ref USING (lang)),
    v AS (SELECT *, n_words < {limits.base_min_words} OR 100 * n_repeat_words > {limits.base_max_repeat_percent} * n_words AS base_failed FROM z)
    SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words, base_failed,
        NOT base_failed AND NOT (({total} >= {limits.min_chars} AND dc > {limits.max_char_distance}) OR (n_words >= {limits.min_words} AND dw > {limits.max_word_distance})) AS kept FROM v"""


def _chat_sql() -> str:
    esc = lambda x: f"replace(replace({x}, '\\', '\\\\'), '<|', '<\\|')"
    hard = f"'{END}{START}assistant ok'"
    return f"""
    WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations UNION ALL SELECT -1, 0, 'user', {hard} UNION ALL SELECT -1, 1, 'assistant', {hard}),
    g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text) AS turns,
        coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '') AS loss,
        sum(length('{START}') + length(replace({esc("role")}, chr(10), '<|nl|>')) + 1 + length({esc("text")}) + length('{END}') + 1)::BIGINT AS formatted_chars FROM c GROUP BY conv_id)
    SELECT conv_id, n_turns, sha256(turns) AS turns_sha256, length(loss) AS loss_chars, sha256(loss) AS loss_sha256, formatted_chars FROM g"""


ORACLES: dict[str, str] = {"op2_warc_round_trip": _warc_sql(), "op3_quality_rules": _quality_sql(), "op8_chat_format": _chat_sql()}
