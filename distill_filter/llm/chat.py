"""Chat formatting by event sourcing, in DataFrame functions only.

A log holds events: a delta appends to its turn's message, a message or an edit sets it, a regeneration clears it. An edit
or regeneration of a turn also undoes what the log had for later turns up to then. Logs are partitioned by conversation
once; a window marks undone events, one aggregation folds each turn, another renders the conversation, all on that
partitioning. Control strings inside texts are escaped: backslashes are doubled, and a backslash parts `<` from `|`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Fixed values of the template.
START, END, LINE = "<|im_start|>", "<|im_end|>", "<|nl|>"
SETS, CLEARS, BRANCHES = ("message", "edit"), ("regenerate",), ("edit", "regenerate")


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    """The inverse: after doubling, `<`, one backslash, `|` in a row can only come from the second step."""
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def fold_events(events: DataFrame) -> DataFrame:
    """events(conv_id, seq, kind, turn, role, text) to final messages (conv_id, turn, role, text).

    Events of a conversation count in order of seq; of equal seq in order of turn, kind and text. Kinds: delta,
    message, edit, regenerate; any other, null included, counts as delta. Null text: empty. The role is the last that a
    turn's counting events name, else empty. A turn of which no event is left has no message.
    """
    rows = events.select("conv_id", "seq", F.coalesce("kind", F.lit("delta")).alias("kind"), "turn", "role", F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.repartition("conv_id")
    order = ["seq", "turn", "kind", "text"]
    later = Window.partitionBy("conv_id").orderBy(*order).rowsBetween(1, Window.unboundedFollowing)
    back_to = F.min(F.when(F.col("kind").isin(*BRANCHES), F.col("turn"))).over(later)
    rows = rows.withColumn("back_to", back_to).where("back_to is null or turn is null or back_to >= turn")
    steps = rows.groupBy("conv_id", "turn").agg(F.array_sort(F.collect_list(F.struct(*order, "role"))).alias("steps"))
    sets = F.transform("steps", lambda s, i: F.when(s["kind"].isin(*SETS, *CLEARS), i).otherwise(F.lit(-1)))
    steps = steps.withColumn("base", F.array_max(sets))
    counting = F.slice("steps", F.greatest("base", F.lit(0)) + 1, F.size("steps"))
    texts = F.transform(counting, lambda s: F.when(s["kind"].isin(*CLEARS), F.lit("")).otherwise(s["text"]))
    role = F.element_at(F.concat(F.array(F.lit("")), F.filter(F.transform("steps", lambda s: s["role"]), lambda r: r.isNotNull())), -1)
    return steps.select("conv_id", "turn", role.alias("role"), F.array_join(texts, "").alias("text"))


def render(messages: DataFrame, learn_from: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """(conv_id, formatted, loss_spans): the text of each conversation, and where the texts to learn from stand in it.

    A span is a start, from 0, and a length, in code points of formatted, over an escaped text without its marks.
    """
    head = F.concat(F.lit(START), F.replace(escape(F.col("role")), F.lit("\n"), F.lit(LINE)), F.lit("\n"))
    rows = messages.select("conv_id", "turn", "role", head.alias("head"), escape(F.col("text")).alias("body"))
    rows = rows.withColumn("whole", F.concat("head", "body", F.lit(END + "\n")))
    before = F.sum(F.length("whole").cast("long")).over(Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, -1))
    span = F.when(F.col("role").isin(*learn_from), F.struct((F.coalesce(before, F.lit(0)) + F.length("head")).cast("long").alias("start"), F.length("body").cast("long").alias("length")))
    rows = rows.select("conv_id", F.struct("turn", "whole", span.alias("span")).alias("m"))
    whole = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list("m")).alias("m"))
    spans = F.filter(F.transform("m", lambda x: x["span"]), lambda x: x.isNotNull())
    return whole.select("conv_id", F.array_join(F.transform("m", lambda x: x["whole"]), "").alias("formatted"), spans.alias("loss_spans"))


def parse(formatted: DataFrame) -> DataFrame:
    """formatted with turns array<struct<role, text>>, read from the text alone."""

    def turn(part: Column) -> Column:
        role = F.replace(F.substring_index(part, "\n", 1), F.lit(LINE), F.lit("\n"))
        text = F.substr(part, F.length(F.substring_index(part, "\n", 1)) + 2)
        return F.struct(unescape(role).alias("role"), unescape(F.regexp_replace(text, r"<\|im_end\|>\n\z", "")).alias("text"))

    parts = F.slice(F.split("formatted", r"<\|im_start\|>", -1), 2, 1 << 30)
    return formatted.withColumn("turns", F.transform(parts, turn))


def masked_text(formatted: Column, spans: Column) -> Column:
    """What lies under the loss mask, unescaped and joined."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substr(formatted, (s["start"] + 1).cast("int"), s["length"].cast("int")))), "")


def events_of(conversations: DataFrame, delta_chars: int = 256, draft_chars: int = 16) -> DataFrame:
    """A log of which each row of conversations(conv_id, turn, role, text) is a turn of its own, as it would be streamed.

    Every turn begins with a draft, the first draft_chars code points of its text. An assistant's draft gets an answer in
    the turn after it before a regeneration undoes both; any other draft is replaced by an edit. Then the text comes in
    deltas of delta_chars code points; the edit has the first of them. Null or empty text: one empty delta. Rows count in
    order of turn, null first; rows of one turn in order of role and text, so repeated rows stay apart.
    """
    if delta_chars < 1:
        raise ValueError("a delta has one code point at least")
    rows = conversations.select("conv_id", F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    n = F.row_number().over(Window.partitionBy("conv_id").orderBy("turn", "role", "text"))
    draft = F.substring("text", 1, draft_chars)
    # one pass over a text: cutting piece after piece by place would read a long one anew for each
    cut = F.regexp_extract_all("text", F.lit(f"(?s).{{1,{delta_chars}}}"), F.lit(0))
    rows = rows.select("conv_id", n.cast("long").alias("at"), "role", draft.alias("draft"), F.when(F.col("text") == "", F.array(F.lit(""))).otherwise(cut).alias("pieces"))

    def event(kind: str | Column, turn: Column, text: Column, role: Column = F.col("role")) -> Column:
        return F.struct((F.lit(kind) if isinstance(kind, str) else kind).alias("kind"), turn.alias("turn"), role.alias("role"), text.alias("text"))

    answered = F.coalesce(F.col("role") == "assistant", F.lit(False))
    undone = F.array(event("delta", F.col("at"), F.col("draft")), event("delta", F.col("at") + 1, F.col("draft"), F.lit("user")), event("regenerate", F.col("at"), F.lit("")))
    replaced = F.array(event("delta", F.col("at"), F.col("draft")))
    streamed = F.transform("pieces", lambda p, i: event(F.when(answered | (i > 0), "delta").otherwise("edit"), F.col("at"), p))
    rows = rows.select("conv_id", "at", F.posexplode(F.concat(F.when(answered, undone).otherwise(replaced), streamed)).alias("step", "e"))
    return rows.select("conv_id", (F.col("at") * (1 << 32) + F.col("step")).alias("seq"), "e.kind", "e.turn", "e.role", "e.text")


def format_conversations(events: DataFrame, learn_from: tuple[str, ...] = ("assistant",)) -> DataFrame:
    """Fold a log and render it. A conversation's text is one row, so its messages meet in one task: nothing else does.

    Null conv_id: one conversation, as of any other id. Null role: an empty role. No events: an empty result.
    """
    return render(fold_events(events), learn_from)
