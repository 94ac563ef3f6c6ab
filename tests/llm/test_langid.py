"""Language identification: held-out accuracy and odd inputs."""

import re
import zlib

import zstandard

from distill_filter.llm.langid import Classifier, Settings, cross_validate, identify_languages, in_fold, learn_dictionaries


def test_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    truth = {r.doc_id: r.lang for r in docs.select("doc_id", "lang").collect()}
    got = identify_languages(docs).collect()
    assert len(got) == len(truth) and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    held = [r for r in got if r.held_out]
    right = [r for r in held if r.lang_pred == truth[r.doc_id]]
    assert len(right) / len(held) > 0.97 and all(0 <= r.score <= 1 for r in got)
    sure = [r for r in held if r.accepted]
    assert len(sure) > 0.8 * len(held) and sum(r.lang_pred == truth[r.doc_id] for r in sure) / len(sure) > 0.97


def test_held_out_rows_teach_nothing(spark):
    rows = [(i, f"alpha beta gamma {i}", "aa") for i in range(60)] + [(i + 60, f"uno dos tres {i}", "bb" if zlib.crc32(str(i + 60).encode()) % 4 != 2 else "cc") for i in range(60)]
    got = identify_languages(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert {r.lang_pred for r in got} == {"aa", "bb"}


def test_cases(spark):
    rows = [(1, "hello world again", "en"), (None, "hello world", "fr"), (3, None, "en"), (5, "", "en"), (6, "12 345 !?", "en"), (7, "x" * 300_000, None), (8, "bonjour le monde", "fr"), (8, "bonjour le monde", "fr")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").selectExpr("*", "1 as score", "2 as p")
    got = {r.doc_id: r for r in identify_languages(docs).collect()}
    assert got[3].lang_pred == got[5].lang_pred == got[6].lang_pred == "und" and got[6].score == 0.0
    assert got[7].lang_pred in ("en", "fr") and got[None].held_out is False
    assert identify_languages(docs.limit(0)).count() == 0
    none = identify_languages(docs.selectExpr("doc_id", "text", "cast(null as string) as lang")).collect()
    assert {r.lang_pred for r in none} == {"und"}
    assert Classifier({"a": b"abc"}).predict("abc")[:2] == ("a", 1.0) and learn_dictionaries(docs.limit(0)) == {}


def test_equals_plain_packing(spark):
    """A compressor made afresh for each text, block and language, with a plain choice of the smallest."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    contents = learn_dictionaries(docs.where(~in_fold(docs.doc_id)))

    def packed(block, content):
        held = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        made = zstandard.ZstdCompressor(level=6, dict_data=held, write_checksum=False, write_content_size=False, write_dict_id=False)
        return len(made.compress(block))

    def plain(text):
        if text is None or not any(c.isalpha() for c in text):
            return "und", 0.0
        data = (" " + re.sub(r"[\W\d_]+", " ", text.lower()).strip() + " ").encode()
        sizes = {lang: sum(packed(data[at : at + 16384], c) for at in range(0, len(data), 16384)) for lang, c in contents.items()}
        low, high = sorted(sizes.values())[:2]
        return {lang for lang, n in sizes.items() if n == low}, (high - low) / high

    got = {r.doc_id: (r.lang_pred, r.score) for r in identify_languages(docs).collect()}
    for r in docs.collect():
        langs, score = plain(r.text)
        assert got[r.doc_id][0] in langs and got[r.doc_id][1] == score


def test_settings_are_chosen_without_the_held_out_fold(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang")
    choices = [Settings(level=1, sample_docs=20), Settings(sample_docs=20), Settings(sample_docs=20, only_letters=False)]
    plain = cross_validate(docs, choices)
    spoilt = docs.selectExpr("doc_id", "text", "if(crc32(cast(cast(doc_id as string) as binary)) % 4 = 2, 'xx', lang) as lang")
    assert cross_validate(spoilt, choices) == plain and {c for c, _, _ in plain} == set(choices)
    assert [e for _, e, _ in plain] == sorted(e for _, e, _ in plain)
    rows = docs.where(~in_fold(docs.doc_id) & docs.lang.isNotNull() & docs.text.isNotNull()).count()
    assert {n for _, _, n in plain} == {rows}
    assert [(e, n) for _, e, n in cross_validate(docs.limit(0), choices)] == [(0, 0)] * 3
