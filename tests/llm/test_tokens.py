"""BPE transducer, prefix counts and the id store against the public libraries."""

import random
import zlib

import numpy as np
import public_tokenizers
import pytest
import sentencepiece
from tokenizers import Tokenizer

from distill_filter.llm.bpe import Decoder, Encoder, LongWord, MergeTable, bpe_round_trip, sufficient_lookahead
from distill_filter.llm.counts import PrefixCounter, count_tokens, prefix_counts
from distill_filter.llm.shared import new_path
from distill_filter.llm.store import LEAST, MOST, WordEncoder, crc32_join, cut_points, read_documents, read_ids, verify_store, write_store

BYTES, WORDS, PIECES = (public_tokenizers.path(n) for n in ("byte_bpe_50k.json", "word_bpe_49k.json", "piece_bpe_32k.model"))
ODD = [
    "", " ", "  ", "a", " a", "it's I'll 'LL '", "x<|endoftext|>y", "<|endoftext|>", "<|endoftex", "é ü 漢字 😀😀", "12 345,6", "a\n\n\nb", "tab\t\tx ", "   lead", "trail   ", " nb  x", "é Å",
    "don't<|startoftext|>!", "\r\n \r\n", "\x00\x01", "ﬁ ligature ΑΣ ΣΑ", "▁a▁▁b ▁", "a" * 70, "ab" * 300, "=" * 500, "  \n  x", "'s't're", "x'", "thethethethe" * 30, "ǅ İ ß", "\x85\x1cq\x1c",
]


@pytest.fixture(scope="module")
def table():
    return MergeTable(BYTES)


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(BYTES)


@pytest.fixture(scope="module")
def texts(spark):
    return ODD + [r.text for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()]


def ids(data, kind="<u4"):
    return np.frombuffer(data, kind).tolist()


def test_encoder_equals_library(table, library, texts):
    encoder = Encoder(table)
    for t in texts:
        got = ids(encoder.encode(t))
        assert got == library.encode(t, add_special_tokens=False).ids, t
        decoder = Decoder(table)
        assert "".join(decoder.feed([i]) for i in got) + decoder.finish() == library.decode(got, skip_special_tokens=False) == t


@pytest.mark.parametrize("longest", [4, 7, 40])
def test_any_cut_gives_the_same_ids(table, library, texts, longest):
    encoder, rnd = Encoder(table, longest=longest), random.Random(longest)
    for t in texts[:200]:
        t = t[:3000]
        out, at = [], 0
        while at < len(t):
            n = rnd.randrange(1, 2 * longest)
            out += encoder.feed(t[at : at + n])
            at += n
        assert ids(b"".join([*out, *encoder.finish()])) == library.encode(t, add_special_tokens=False).ids, t


def test_endless_words(table, library):
    rnd = random.Random(2)
    for t in ["a" * 150_000, " " * 140_000 + "x", "\n" * 70_000, " " + "the" * 40_000, "".join(rnd.choice("etaoin") for _ in range(90_000)), "=" * 80_000 + "<|endoftext|>" + "=" * 80_000, "7" * 70_000 + " z"]:
        assert ids(Encoder(table).encode(t)) == library.encode(t, add_special_tokens=False).ids


def test_lookahead_is_sufficient_and_memory_bounded(table):
    assert sufficient_lookahead([], [], {}) == 0
    # a b / c with the merges bc, ab: whether ab stands hangs on one byte more
    assert sufficient_lookahead([(1, 2), (0, 1)], [3, 4], {0: 1, 1: 1, 2: 1, 3: 2, 4: 2}) == 2
    rnd, pieces = random.Random(6), [t for t in table.ids if t.isalpha()]
    for _ in range(300):
        data = b"".join(rnd.choice(pieces) for _ in range(60))
        whole = table.merge(data)
        at = rnd.randrange(1, len(data))
        part, end = table.merge(data[:at]), 0
        for k, token in enumerate(part):
            end += table.size[token]
            if end + table.lookahead > at:
                break
            assert whole[k] == token
        word = LongWord(table, block=16)
        got = []
        for i in range(0, len(data), 5):
            got += word.feed(data[i : i + 5])
            assert len(word.pending) <= 16 + 2 * table.lookahead
        assert got + list(word.finish()) == whole


def test_counts_equal_library(texts):
    counter, library = PrefixCounter(PIECES), sentencepiece.SentencePieceProcessor(model_file=PIECES)
    for t in texts:
        assert counter.count(t) == len(library.encode(t)), t
    for t in ODD + texts[40:60]:
        t = t[:400]
        got = counter.prefixes(t).tolist()
        assert got == [len(library.encode(t[:k])) for k in range(1, len(t) + 1)], t
        for budget in (0, 1, 3, 50):
            assert counter.longest_prefix(t, budget) == max([0, *(k for k in range(1, len(t) + 1) if got[k - 1] <= budget)])
    small = PrefixCounter(PIECES, kept=5)
    assert [small.count(t) for t in texts[:100]] == [counter.count(t) for t in texts[:100]]


def test_word_encoder_equals_library(texts):
    encoder, library = WordEncoder(WORDS, 1000, 1000), Tokenizer.from_file(WORDS)
    for at in range(0, len(texts), 100):
        for t, got in zip(texts[at : at + 100], encoder.encode(texts[at : at + 100])):
            assert ids(got, "<u2") == library.encode(t, add_special_tokens=False).ids, t


def test_cuts_and_crc():
    rnd = np.random.default_rng(3)
    docs = [rnd.integers(0, 49_408, n).astype("<u2") for n in (1, 63, 64, 700, 20_000, 5)] + [np.zeros(9000, "<u2")]
    docs.append(np.concatenate([docs[3][:50], docs[4]]))
    cuts = cut_points(np.concatenate(docs), np.cumsum([len(d) for d in docs]))
    start, chunks = 0, []
    for d, c in zip(docs, cuts):
        sizes = np.diff([start, *c])
        assert sizes.sum() == len(d) and (sizes[:-1] >= LEAST).all() and (sizes <= MOST).all()
        chunks.append({d[a - start : b - start].tobytes() for a, b in zip([start, *c], c)})
        start = c[-1]
    assert len(chunks[4] & chunks[7]) > 0.8 * len(chunks[4])  # a passage moved along is cut alike
    groups = [[rnd.bytes(int(rnd.integers(0, 3000))) for _ in range(rnd.integers(1, 9))] for _ in range(60)]
    parts = [p for g in groups for p in g]
    first = np.cumsum([0] + [len(g) for g in groups[:-1]])
    assert crc32_join(np.array([zlib.crc32(p) for p in parts]), np.array([len(p) for p in parts]), first).tolist() == [zlib.crc32(b"".join(g)) for g in groups]


def test_store(spark):
    rows = [(5, "Hello World"), (3, None), (9, ""), (5, "Hello World"), (None, "no name"), (-2, "first " * 20_000), (7, "first " * 20_000 + "tail"), (8, "<|endoftext|> x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as start", "2 as digest").repartition(3)
    path = new_path(spark, "store")
    root = write_store(docs, path, WORDS)
    verify_store(spark, path, root)
    with pytest.raises(ValueError):
        verify_store(spark, path, "0" * 64)
    library, at, want = Tokenizer.from_file(WORDS), 0, []
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0)):
        x = np.array([*library.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((i, at, len(x), zlib.crc32(x.tobytes())))
        at += len(x)
    assert sorted((tuple(r) for r in read_documents(spark, path).collect()), key=lambda r: r[1]) == want
    assert sorted(len(r.ids) // 2 for r in read_ids(spark, path).collect()) == sorted(n for _, _, n, _ in want)
    chunks = spark.read.parquet(f"{path}/chunks")
    assert chunks.count() == chunks.select("digest").distinct().count() < 40
    empty = new_path(spark, "store")
    verify_store(spark, empty, write_store(docs.limit(0), empty, WORDS))
    assert read_documents(spark, empty).count() == 0


def test_queries_cases(spark):
    docs = spark.createDataFrame([(1, None), (2, ""), (None, "a b"), (3, "word " * 5000), (3, "word " * 5000)], "doc_id long, text string").selectExpr("*", "3 as ids", "4 as counts", "5 as c")
    got = {r.doc_id: r for r in count_tokens(docs, PIECES).collect()}
    assert (got[1].n_bytes, got[1].n_tokens, got[1].over_limit) == (0, 0, False) and got[3].over_limit and 0 < got[3].fits_chars < 25_000
    counter = PrefixCounter(PIECES)
    assert counter.count(("word " * 5000)[: got[3].fits_chars]) <= 4096 < counter.count(("word " * 5000)[: got[3].fits_chars + 5])
    assert {r.doc_id: len(r.counts) for r in prefix_counts(docs, PIECES).collect()} == {1: 0, 2: 0, None: 3, 3: 25_000}
    back = {r.doc_id: r for r in bpe_round_trip(docs, BYTES).collect()}
    assert back[1].decoded == "" and back[3].decoded == "word " * 5000 and len(back[None].ids) == 8
    assert count_tokens(docs.limit(0), PIECES).count() == 0 == bpe_round_trip(docs.limit(0), BYTES).count()


def test_word_encoder_on_odd_unicode():
    """Words at whose ends case, normal form or classes are odd, before closing marks, against the library."""
    encoder, library, rnd = WordEncoder(WORDS, 500, 500), Tokenizer.from_file(WORDS), random.Random(8)
    assert encoder.apart
    odd = list("aZéÉßµªºÿİıǅΣςſK\u0307\u0958\u0344ﬁ漢कÅÅ٣²½'’.,;:!?-_|<>\t\r\u00a0\u0085\u200d\u1e9e\u037e") + ["don't", "<|endoftext|>", "<|startoftext|>", "<|end", "ALİ.", "foo", "BAR", "\n"]
    texts = ["ALİ.", "foo İ, bar", "x<|endoftext|>y.", "क़. a", ""]
    for _ in range(4000):
        texts.append("".join(rnd.choice(odd) + rnd.choice(["", "", " "]) for _ in range(rnd.randrange(1, 12))))
    for at in range(0, len(texts), 250):
        some = texts[at : at + 250]
        for t, got in zip(some, encoder.encode(some), strict=True):
            assert ids(got, "<u2") == library.encode(t, add_special_tokens=False).ids, t


def test_other_files_go_to_the_library(tmp_path):
    import json

    with open(WORDS, encoding="utf-8") as f:
        spec = json.load(f)
    spec["normalizer"] = {"type": "NFC"}
    path = tmp_path / "cased.json"
    path.write_text(json.dumps(spec), encoding="utf-8")
    encoder, library = WordEncoder(str(path)), Tokenizer.from_file(str(path))
    some = ["Hello World.", "", "A  b\tC"]
    assert not encoder.apart and [ids(x, "<u2") for x in encoder.encode(some)] == [library.encode(t, add_special_tokens=False).ids for t in some]
