"""The pipeline against a plain rendering of its five decisions, and its registered queries."""

import hashlib

import numpy as np
import public_tokenizers
from test_quality import slow_counts, slow_distance
from test_simhash import slow_components, slow_fingerprint
from tokenizers import Tokenizer

import corpus_pipeline
from distill_filter.llm.decontaminate import Index, allowed, best_match, words_of
from distill_filter.llm.pii import redact_text
from distill_filter.llm.quality import COMMON_WORDS, Limits
from distill_filter.llm.queries import ORACLES, QUERIES


def test_run_equals_plain_version(spark):
    sf = "/root/testdata/sf0.001"
    rows = [r.asDict() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    found, refs, limits = {r["doc_id"]: slow_counts(r["text"], r["lang"]) for r in rows}, {}, Limits()
    for r in rows:
        c, h = refs.get(r["lang"], ([0] * 8, [0] * 99))
        f = found[r["doc_id"]]
        refs[r["lang"]] = ([a + b for a, b in zip(c, f["char_hist"])], [a + b for a, b in zip(h, f["word_hist"][0])])
    kept = []
    for r in rows:
        f = found[r["doc_id"]]
        bad = f["n_words"] < 20 or 100 * f["n_repeat_words"] > 30 * f["n_words"]
        bad = bad or sum(f["char_hist"]) >= limits.min_chars and slow_distance(f["char_hist"], refs[r["lang"]][0]) > limits.max_char_distance
        bad = bad or f["n_words"] >= limits.min_words and slow_distance(f["word_hist"][0], refs[r["lang"]][1]) > limits.max_word_distance
        kept += [] if bad else [r]
    assert set(COMMON_WORDS) >= set(refs)
    groups = slow_components({r["doc_id"]: slow_fingerprint(r["text"]) for r in kept})
    kept = [r for r in kept if groups[r["doc_id"]] == r["doc_id"]]
    index = Index([(r.item_id, words_of(r.text)) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()])
    numbers = {r["doc_id"]: index.number([r["text"]])[0].tolist() for r in kept}
    kept = [r for r in kept if not any(best_match(ws, numbers[r["doc_id"]])[0] <= allowed(len(ws), 0.8) for _, ws in index.items)]
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = {}
    for r in kept:
        ids = library.encode(redact_text(r["text"]), add_special_tokens=False).ids
        want[r["doc_id"]] = (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), True)
    assert {r.doc_id: (r.n_tokens, r.ids_sha256, r.decodes) for r in corpus_pipeline.run(spark, sf).collect()} == want and len(want) > 100


def test_near_dedup_goes_by_fingerprints(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    groups = slow_components({r.doc_id: slow_fingerprint(r.text) for r in docs.collect()})
    left = [r.doc_id for r in corpus_pipeline.simhash_near_dedup(spark, docs, "").select("doc_id").collect()]
    assert sorted(left) == sorted(i for i, g in groups.items() if i == g) and {145, 177} <= set(left)


def test_stages_on_odd_rows(spark):
    text = " ".join(f"the word{i} of" for i in range(40))
    other = " ".join(f"of other{i} the" for i in range(40)) + " a@b.co"
    rows = [(1, text, "en", "s", 9), (2, text, "en", None, None), (None, text, "en", "s", 9), (4, None, "en", "s", 0), (5, "", None, "s", 0), (6, other, "xx", "s", 1), (6, other, "xx", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumnRenamed("source", "kept")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, "/root/testdata/sf0.001")
        out.count()
        assert stage(spark, docs.limit(0), "/root/testdata/sf0.001").count() == 0
        if name != "bpe_encoding":
            assert out.columns == docs.columns
    left = corpus_pipeline.quality_rules(spark, docs, "").collect()
    assert len(left) == 5
    assert sorted(str(r.doc_id) for r in corpus_pipeline.simhash_near_dedup(spark, docs, "").collect()) == ["1", "4", "6", "6", "None"]


def test_registered():
    assert [int(n[2:].split("_")[0]) for n in QUERIES] == list(range(1, 11)) and set(ORACLES) <= set(QUERIES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "simhash_near_dedup", "benchmark_decontamination", "pii", "bpe_encoding"]
