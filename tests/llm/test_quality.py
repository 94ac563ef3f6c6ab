"""Quality rules against a plain rendering, and on labelled rows."""

import math
import re
from collections import Counter

from distill_filter.llm.quality import CLASSES, COMMON_WORDS, Limits, assess_quality, text_counts

SPACE = " \t\n\x0b\x0c\r"


def slow_counts(text, lang):
    text = text or ""
    words = [w for w in re.split(f"[{SPACE}]+", text) if w]
    lines = [x for x in text.split("\n") if x.strip(SPACE)]
    windows = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
    covered = {j for i in range(len(words) - 7) if windows[tuple(words[i : i + 8])] > 1 for j in range(i, i + 8)}
    kinds = [r"[a-z]", f"[{SPACE}]", "[A-Z]", "[0-9]", r"[.,;:!?'\"()-]", r"[#*$%&|<>]", r"[^\x00-\x7f]", "."]
    chars = Counter(next(i for i, k in enumerate(kinds) if re.match(k, c, re.S)) for c in text)
    hists = {g: [words.count(w) for w in ws] for g, ws in COMMON_WORDS.items()}
    hists = {g: h + [len(words) - sum(h)] for g, h in hists.items()}
    return {
        "n_words": len(words), "word_chars": sum(map(len, words)), "n_symbols": sum(c in "#*$%&|<>" for c in text), "n_dup_lines": len(lines) - len(set(lines)),
        "n_repeat_words": len(covered), "char_hist": [chars[i] for i in range(8)], "word_hist": [hists[lang]] if lang in hists else list(hists.values()),
    }


def slow_distance(counts, ref):
    p, q = [c / sum(counts) for c in counts], [c / sum(ref) for c in ref]
    kl = lambda a, b: sum(x * math.log2(x / y) for x, y in zip(a, b) if x)
    m = [(x + y) / 2 for x, y in zip(p, q)]
    return math.sqrt(max(0.0, (kl(p, m) + kl(q, m)) / 2))


def check(spark, docs):
    rows = docs.collect()
    want = [(r.doc_id, r.lang, slow_counts(r.text, r.lang)) for r in rows]
    got = sorted(text_counts(docs).collect(), key=lambda r: str((r.doc_id, r.lang, r.n_words, r.word_chars)))
    for g, (i, lang, w) in zip(got, sorted(want, key=lambda x: str((x[0], x[1], x[2]["n_words"], x[2]["word_chars"]))), strict=True):
        assert g.doc_id == i and {k: getattr(g, k) for k in w if k != "word_hist"} == {k: v for k, v in w.items() if k != "word_hist"}
        assert [h.n for h in g.word_hist] == w["word_hist"]
    refs = {}
    for _, lang, w in want:
        if lang in COMMON_WORDS:
            c, h = refs.get(lang, ([0] * 8, [0] * 99))
            refs[lang] = ([a + b for a, b in zip(c, w["char_hist"])], [a + b for a, b in zip(h, w["word_hist"][0])])
    limits = Limits()
    verdicts = {}
    for i, lang, w in want:
        failed = w["n_words"] < 20 or 100 * w["n_repeat_words"] > 30 * w["n_words"]
        near = (0.0, 0.0)
        if w["n_words"] and refs:
            pairs = [(slow_distance(h, refs[g][1]), slow_distance(w["char_hist"], refs[g][0])) for g, h in zip([lang] if lang in COMMON_WORDS else COMMON_WORDS, w["word_hist"]) if g in refs]
            near = min(pairs) if pairs else near
        far = (sum(w["char_hist"]) >= limits.min_chars and near[1] > limits.max_char_distance) or (w["n_words"] >= limits.min_words and near[0] > limits.max_word_distance)
        verdicts[i, w["n_words"]] = (failed, not failed and not far, near)
    for r in assess_quality(docs).collect():
        failed, kept, near = verdicts[r.doc_id, r.n_words]
        assert (r.base_failed, r.kept) == (failed, kept)
        if r.n_words:
            assert abs(r.word_distance - near[0]) < 1e-9 and abs(r.char_distance - near[1]) < 1e-9


def test_table(spark):
    check(spark, spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))


def test_cases(spark):
    eight = "a b c d e f g h"
    texts = [None, "", " \n\x0b", "one", eight, f"{eight} {eight}", f"{eight} x {eight} y {eight}", "z " * 30, "l1\nl1\n \n \nl2\nl1", "É€😀 < | > x\x85y", "the of " * 20_000]
    rows = [(i, t, lang) for i, t in enumerate(texts) for lang in ["en"]] + [(100 + i, t, lang) for i, t in enumerate(texts) for lang in [None, "xx"][i % 2 :][:1]] + [(None, "a b", "fr"), (7, "again", None)]
    check(spark, spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    clash = spark.createDataFrame(rows, "doc_id long, text string, lang string").selectExpr("*", "1 as words", "2 as kept", "3 as near")
    assert assess_quality(clash).count() == len(rows)
    assert assess_quality(clash.limit(0)).count() == 0 and len(CLASSES) == 7
    assert assess_quality(clash.selectExpr("doc_id", "text", "cast(null as string) as lang")).where("char_distance <> 0").count() == 0


def test_labelled_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    found = assess_quality(docs).join(labels, "doc_id").where("not base_failed").selectExpr("quality", "int(kept) as k").groupBy("quality").agg({"k": "avg"})
    kept = {r.quality: r["avg(k)"] for r in found.collect()}
    assert kept[1] > 0.995 and kept[0] < 0.1
