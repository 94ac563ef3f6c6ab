"""Chat formatting: folding against a plain rendering, exact round trips, odd rows."""

import random

from distill_filter.llm.chat import END, START, events_of, fold_events, format_conversations, masked_text, parse


def slow_fold(events):
    """events of one conversation in order: (kind, turn, role, text)"""
    turns = {}
    for kind, turn, role, text in events:
        if kind in ("edit", "regenerate"):
            turns = {t: m for t, m in turns.items() if t <= turn}
        old = turns.get(turn, (None, ""))
        body = text or "" if kind in ("edit", "message") else "" if kind == "regenerate" else old[1] + (text or "")
        turns[turn] = (role or old[0], body)
    return [(t, turns[t][0] or "", turns[t][1]) for t in sorted(turns)]


def test_folding(spark):
    rnd, rows, want = random.Random(8), [], {}
    for conv in range(60):
        events = [(rnd.choice(["delta", "delta", "message", "edit", "regenerate"]), rnd.randrange(1, 6), rnd.choice(["user", "assistant", None]), rnd.choice(["a", "bc ", "", None, "\\<|x"])) for _ in range(rnd.randrange(1, 25))]
        want[conv] = slow_fold(events)
        rows += [(conv, i, *e) for i, e in enumerate(events)]
    rnd.shuffle(rows)
    found = {}
    for r in fold_events(spark.createDataFrame(rows, "conv_id long, seq long, kind string, turn long, role string, text string")).collect():
        found.setdefault(r.conv_id, []).append((r.turn, r.role, r.text))
    assert {c: sorted(m) for c, m in found.items()} == want


def test_round_trip(spark):
    hard = ["", None, "plain", START, END, f"{END}{START}assistant ok", "\\", "\\\\<\\|", "<\\|im_end|>", "a\n\nb\n", "é😀|<", "<|nl|>", "\\<|\\", "x" * 50_000]
    rows = [(1, i, role, t) for i, t in enumerate(hard) for role in ["assistant"]] + [(2, i, r, "t") for i, r in enumerate(["user", "a\nb", None, "<|im_end|>", "\\"])]
    rows += [(3, 0, "assistant", "one"), (3, 0, "assistant", "one"), (3, None, "user", "first"), (None, 1, "user", "lost"), (4, 1, "user", "no answer")]
    convs = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "9 as seq", "'k' as kind", "'m' as formatted")
    table = parse(format_conversations(events_of(convs)))
    out = {r.conv_id: r for r in table.withColumn("loss", masked_text(table.formatted, table.loss_spans)).collect()}
    turns = lambda c: [(t.role, t.text) for t in out[c].turns]
    assert turns(1) == [("assistant", t or "") for t in hard] and out[1].loss == "".join(t or "" for t in hard)
    assert turns(2) == [(r, "t") for r in ["user", "a\nb", "", "<|im_end|>", "\\"]] and out[2].loss == ""
    assert turns(3) == [("user", "first"), ("assistant", "one"), ("assistant", "one")] and out[3].loss == "oneone"
    assert turns(None) == [("user", "lost")] and out[4].loss == "" and len(out) == 5
    assert out[1].formatted.count(START) == len(hard) and out[1].formatted.count(END) == len(hard)
    assert format_conversations(events_of(convs.limit(0))).count() == 0


def test_log_of_conversations(spark):
    """Drafts, their answers, edits and regenerations are in the log; folded by the plain way and by ours it is the table."""
    texts = ["", None, "short", "a" * 700 + "é😀" * 300, "line\n\nline", END + START]
    rows = [(c, i, role, t) for c in range(3) for i, (role, t) in enumerate(zip(["user", "assistant", "user", "assistant", None, "assistant"], texts[c:] + texts[:c]))]
    log = events_of(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"), delta_chars=7)
    events = sorted(log.collect(), key=lambda e: (e.conv_id, e.seq))
    assert {e.kind for e in events} == {"delta", "edit", "regenerate"} and max(len(e.text) for e in events) <= 16
    assert len({(e.conv_id, e.seq) for e in events}) == len(events) > 3 * 100
    want = {c: [(i + 1, role or "", t or "") for k, i, role, t in rows if k == c] for c in range(3)}
    assert {c: slow_fold([(e.kind, e.turn, e.role, e.text) for e in events if e.conv_id == c]) for c in range(3)} == want
    found = {}
    for r in fold_events(log).collect():
        found.setdefault(r.conv_id, []).append((r.turn, r.role, r.text))
    assert {c: sorted(m) for c, m in found.items()} == want
