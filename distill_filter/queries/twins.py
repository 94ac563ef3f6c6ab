"""SQL text of the derived tables, as chains of common table expressions."""

from __future__ import annotations

from ..config import RunConfig, StudentConfig
from ..operators.students import CLIP, MICRO
from ..operators.teacher import COMMON_DF, COMMON_SHARE, HOSTILE, JUNK_MARKS, LEGAL, REPEAT, WEAK_HOSTILE, WEAK_JUNK
from ..operators.threshold import CLOSE, ZERO
from ..sources.html import DROPPED, ENTITIES

SPAN = 1 << 32
SEED_LABELS = 256


def quoted(values) -> str:
    return ", ".join("'" + str(v).replace("'", "''") + "'" for v in values)


def hash_int(*parts: str) -> str:
    return f"('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 8))::BIGINT"


def tokens(text: str = "text") -> str:
    return rf"list_filter(regexp_split_to_array(coalesce({text}, ''), '[ \t\n\r]+'), lambda x: x <> '')"


def shape(text: str) -> str:
    for pattern, mark in (("[^ -~]", ""), ("[A-Z]+", "^"), ("[a-z]+", "L"), ("[0-9]+", "D")):
        text = f"regexp_replace({text}, '{pattern}', '{mark}', 'g')"
    return text


def features(text: str = "text") -> str:
    return f"list_filter(list_distinct(string_split(lower({text}) || ' ' || {shape(text)}, ' ')), lambda x: x <> '')"


def snippets(width: int = 64, source: str = "documents", key: str = "doc_id", name: str = "snips", text: str = "text") -> str:
    return f"""{name}_t AS (SELECT {key} AS doc_id, {tokens(text)} AS tk FROM {source}),
    {name} AS (SELECT concat(doc_id, '#', seq) AS snippet_id, doc_id, seq::INT AS seq, array_to_string(list_slice(tk, seq * {width} + 1, seq * {width} + {width}), ' ') AS text,
        least({width}, len(tk) - seq * {width})::INT AS n_tokens FROM (SELECT doc_id, tk, unnest(range(0, (len(tk) + {width - 1}) // {width})) AS seq FROM {name}_t))"""


def page_text(html: str) -> str:
    """Text of a page's HTML, as sources.html has it."""
    text = f"regexp_replace({html}, '(?s)<!--.*?-->', ' ', 'g')"
    for name in DROPPED:
        text = f"regexp_replace({text}, '(?s)<{name}[ >].*?</{name}>', ' ', 'g')"
    text = f"regexp_replace({text}, '<[^>]*>', ' ', 'g')"
    for entity, char in ENTITIES:
        text = f"replace({text}, {quoted([entity])}, {quoted([char])})"
    return f"trim(regexp_replace({text}, '[ \\t\\n\\r]+', ' ', 'g'))"


def evidence(spec: str, text: str = "text", weak: bool = False) -> str:
    if spec == "topic_hostile":
        return f"len(list_filter({tokens(text)}, lambda x: regexp_replace(lower(x), '[^a-z]', '', 'g') IN ({quoted(WEAK_HOSTILE if weak else HOSTILE)})))"
    if spec == "topic_legal":
        return "(" + " + ".join(f"regexp_matches(lower({text}), '{p}')::INT" for p in (LEGAL[:1] if weak else LEGAL)) + ")"
    if spec == "topic_private":
        return f"len(list_filter({tokens(text)}, lambda x: regexp_matches(x, '{'[0-9]{5}' if weak else '[0-9]'}')))"
    marks = " + ".join(f"contains({text}, '{m}')::INT" for m in (WEAK_JUNK if weak else JUNK_MARKS))
    repeats = f"(len(list_distinct(list_transform({tokens(text)}, lambda x: lower(x)))) < {REPEAT} * len({tokens(text)}))::INT"
    return f"({marks}{'' if weak else ' + ' + repeats})"


COMMON = f"""common AS (SELECT token FROM (SELECT token, count(*) AS df FROM (SELECT unnest(list_distinct(list_transform({tokens()}, lambda x: lower(x)))) AS token FROM documents)
    GROUP BY token) WHERE df >= {COMMON_DF} * (SELECT count(*) FROM documents))"""


def rule(spec: str, text: str = "text", weak: bool = False) -> str:
    """1 for pass; mainstream needs a column cm: the list of the tokens of the CTE `common`."""
    if spec == "mainstream":
        known = f"len(list_filter({tokens(text)}, lambda x: list_contains(cm, lower(x))))"
        return f"({known} >= {COMMON_SHARE + 0.1 * weak} * len({tokens(text)}))::INT"
    return f"({evidence(spec, text, weak)} {'= 0' if spec == 'quality' else '> 0'})::INT"


def stream(spec: str = "quality", seed: int = 7) -> str:
    """snips and stream(snippet_id, doc_id, text, stream_pos, label)."""
    if spec == "mainstream":
        return f"""{snippets()}, {COMMON}, stream AS (SELECT snippet_id, doc_id, seq, n_tokens, text, row_number() OVER (ORDER BY md5(concat('{seed}:', snippet_id)), snippet_id) - 1 AS stream_pos, {rule(spec)} AS label FROM snips, (SELECT list(token) AS cm FROM common))"""
    return f"""{snippets()}, stream AS (SELECT snippet_id, doc_id, seq, n_tokens, text, row_number() OVER (ORDER BY md5(concat('{seed}:', snippet_id)), snippet_id) - 1 AS stream_pos, {rule(spec)} AS label FROM snips)"""


def student(labelled: str, name: str, config: StudentConfig = StudentConfig()) -> str:
    """<name>_w(token, df1, df0, w_micro) with a row for the prior under '', from labelled(text, verdict)."""
    a = config.smoothing
    return f"""{name}_n AS (SELECT coalesce(sum(verdict), 0)::BIGINT AS n1, coalesce(sum(1 - verdict), 0)::BIGINT AS n0 FROM {labelled}),
    {name}_c AS (SELECT token, sum(verdict)::BIGINT AS df1, sum(1 - verdict)::BIGINT AS df0 FROM (SELECT verdict, unnest({features()}) AS token FROM {labelled}) GROUP BY token),
    {name}_o AS (SELECT token, df1, df0, ln((df1 + {a}) / (n1 + {2 * a})) - ln((df0 + {a}) / (n0 + {2 * a})) AS odds, sqrt(1.0 / (df1 + {a}) + 1.0 / (df0 + {a})) AS error
        FROM {name}_c, {name}_n WHERE df1 + df0 >= {config.min_df}),
    {name}_w AS (SELECT token, df1, df0, round(odds * {MICRO})::BIGINT AS w_micro FROM {name}_o WHERE abs(odds) >= {config.z_min} * error
        UNION ALL SELECT '', n1, n0, round(ln((n1 + {a}) / (n0 + {a})) * {MICRO})::BIGINT FROM {name}_n)"""


def margins(rows: str, student_name: str, name: str) -> str:
    """<name>: rows with margin_micro."""
    return f"""{name}_s AS (SELECT snippet_id, sum(w_micro)::BIGINT AS w FROM (SELECT snippet_id, unnest({features()}) AS token FROM {rows}) JOIN {student_name}_w USING (token) WHERE token <> '' GROUP BY snippet_id),
    {name} AS (SELECT r.*, greatest(-{CLIP}, least({CLIP}, coalesce(w, 0) + (SELECT w_micro FROM {student_name}_w WHERE token = '')))::BIGINT AS margin_micro FROM {rows} r LEFT JOIN {name}_s USING (snippet_id))"""


def scored(spec: str = "quality") -> str:
    """scored(snippet_id, doc_id, text, stream_pos, label, margin_micro, score): the student of the first SEED_LABELS labels on everything."""
    return f"""{stream(spec)}, seed AS (SELECT text, label AS verdict FROM stream WHERE stream_pos < {SEED_LABELS}), {student("seed", "st")}, {margins("stream", "st", "sc")},
    scored AS (SELECT *, 1 / (1 + exp(-(margin_micro / {MICRO}))) AS score FROM sc)"""


def curve(rows: str, name: str) -> str:
    """<name>(cut, n0, n1, n1_le, n0_gt, loss) of rows(margin_micro, y)."""
    return f"""{name}_c AS (SELECT margin_micro AS cut, sum((y = 0)::INT)::BIGINT AS n0, sum((y = 1)::INT)::BIGINT AS n1 FROM {rows} GROUP BY 1 UNION ALL SELECT {ZERO}, 0, 0),
    {name} AS (SELECT cut, n0, n1, n1_le, t0 - n0_le AS n0_gt, (n1_le + t0 - n0_le) / total::DOUBLE AS loss FROM (SELECT cut, n0, n1, (sum(n1) OVER (ORDER BY cut))::BIGINT AS n1_le,
        (sum(n0) OVER (ORDER BY cut))::BIGINT AS n0_le, (sum(n0) OVER ())::BIGINT AS t0, (sum(n0 + n1) OVER ())::BIGINT AS total FROM {name}_c))"""


def radius(t: str, n: str, delta: float, scale: float = 1.0) -> str:
    """beta after t snippets."""
    return f"({scale} * sqrt(2 * ln(2 * pow(log2({t}), 2) * pow({n}, 2) / {delta}) / {t}))"


def band(curve_name: str, name: str, t: str, n: str, delta: float, scale: float = 1.0) -> str:
    """<name>(lo, hi, s_hat, loss) of a curve at update t."""
    b = radius(f"({t} + 1)", n, delta, scale)
    return f"""{name}_b AS (SELECT cut AS s_hat, loss AS best FROM {curve_name} ORDER BY loss, cut LIMIT 1),
    {name}_r AS (SELECT c.cut, c.loss, row_number() OVER (ORDER BY c.cut) AS place FROM {curve_name} c),
    {name} AS (SELECT min(cut) AS lo, max(cut) AS hi, any_value(s_hat) AS s_hat, any_value(best) AS loss FROM {name}_r, {name}_b
        WHERE loss - best <= {b} * {b} / 2 + {b} * sqrt(abs(place - (SELECT place FROM {name}_r, {name}_b WHERE cut = s_hat)) / ({t})::DOUBLE) + {CLOSE})"""


def one_round(rows: str, head: int | str, need: str, n: str, delta: float, scale: float, blocks: list[tuple[int, int]], name: str, nested: bool = True) -> str:
    """A round unrolled: per block k the CTEs <name>_k<k> (rows with y, inside, bought) and <name>_b<k> (band after it).

    head: the first position, or SQL that gives it. rows(stream_pos, snippet_id, margin_micro, label). The cap is taken by position at the end: labels bought beyond it
    in the block where it falls, and all later blocks, do not count.
    """
    at = lambda k: head + k if isinstance(head, int) else f"{head} + {k}"
    parts, before = [], f"(SELECT -(1::BIGINT << 61) AS lo, (1::BIGINT << 61) AS hi)"
    for k, (first, last) in enumerate(blocks):
        seen = " UNION ALL ".join(f"SELECT margin_micro, y FROM {name}_k{i}" for i in range(k + 1))
        parts.append(
            f"{name}_k{k} AS MATERIALIZED (SELECT r.stream_pos, r.snippet_id, r.margin_micro, r.label, r.margin_micro BETWEEN b.lo AND b.hi AS inside, "
            f"CASE WHEN r.margin_micro < b.lo THEN 0 WHEN r.margin_micro > b.hi THEN 1 ELSE r.label END AS y FROM {rows} r, {before} b WHERE r.stream_pos BETWEEN {at(first)} AND {at(last)})"
        )
        parts.append(f"{name}_a{k} AS MATERIALIZED ({seen})")
        parts.append(curve(f"{name}_a{k}", f"{name}_c{k}"))
        parts.append(band(f"{name}_c{k}", f"{name}_n{k}", str(last), n, delta, scale))
        ends = f"greatest(n.lo, b.lo) AS lo, CASE WHEN n.hi = (SELECT max(cut) FROM {name}_c{k}) THEN b.hi ELSE least(n.hi, b.hi) END AS hi" if nested else "n.lo, n.hi"
        parts.append(f"{name}_b{k} AS MATERIALIZED (SELECT {ends}, n.s_hat, n.loss FROM {name}_n{k} n, {before} b)")
        before = f"{name}_b{k}"
    every = " UNION ALL ".join(f"SELECT * FROM {name}_k{k}" for k in range(len(blocks)))
    parts.append(f"{name}_bought AS MATERIALIZED (SELECT stream_pos, snippet_id, label, row_number() OVER (ORDER BY stream_pos) AS ord FROM ({every}) WHERE inside QUALIFY ord <= {need})")
    return ", ".join(parts)


def rounds(config: RunConfig, blocks: list[tuple[int, int]], name: str = "e", rows: str = "stream") -> str:
    """A whole run of the band policy unrolled over rows(snippet_id, stream_pos, text, label): <name>_lab (text, verdict,
    stream_pos, round) are the labels bought, <name>_h<r> the head after round r, <name>_f_w the final student."""
    b, n = config.batch, f"(SELECT count(*) FROM {rows})"
    parts = [f"{name}_l0 AS MATERIALIZED (SELECT text, label AS verdict, stream_pos, snippet_id, 0 AS round FROM {rows} WHERE stream_pos < {b})", f"{name}_h0 AS (SELECT least({b}, {n}) AS head)"]
    for r in range(1, config.rounds + 1):
        head = f"(SELECT head FROM {name}_h{r - 1})"
        parts += [student(f"{name}_l{r - 1}", f"{name}_s{r}"), margins(f"(SELECT * FROM {rows} WHERE stream_pos >= {head})", f"{name}_s{r}", f"{name}_m{r}").replace(f"{name}_m{r} AS (", f"{name}_m{r} AS MATERIALIZED (")]
        parts.append(one_round(f"{name}_m{r}", head, str(b), n, config.delta, config.radius_scale, blocks, f"{name}_r{r}", config.nested))
        parts.append(f"{name}_l{r} AS MATERIALIZED (SELECT * FROM {name}_l{r - 1} UNION ALL SELECT s.text, b.label, s.stream_pos, s.snippet_id, {r} FROM {name}_r{r}_bought b JOIN {rows} s USING (snippet_id))")
        parts.append(f"{name}_h{r} AS MATERIALIZED (SELECT CASE WHEN count(*) = {b} THEN max(stream_pos) + 1 ELSE {n} END AS head FROM {name}_r{r}_bought)")
    last = config.rounds
    return ", ".join([*parts, f"{name}_lab AS (SELECT * FROM {name}_l{last})", student(f"{name}_l{last}", f"{name}_f")])


def engine(config: RunConfig, blocks: list[tuple[int, int]], spec: str = "quality", name: str = "last") -> str:
    """The whole run over the stream of a spec, and <name>: the stream with the final student's margin_micro."""
    return f"{stream(spec)}, {rounds(config, blocks)}, {margins('stream', 'e_f', name)}"
