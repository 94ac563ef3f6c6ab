"""Exact token counts of every prefix by dynamic programming over a piece vocabulary.

The tokens of a prefix are those of a shorter prefix and one more. Which one: the only piece that ends there and stays
apart from the last token before it when the two are merged alone. So each prefix stores its last token's length and its
count, and truncation and budget questions are answered without encoding again. A space mark only opens pieces, so a
text falls into segments (marks, then other characters) that are counted alone and added up.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import lru_cache

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import tidy

MARK = "▁"
SEGMENT = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+")
SEGMENTS_KEPT = 400_000
#: The prefix tables of this many first characters of segments are kept, for so many different ones.
HEAD, HEADS_KEPT = 6, 120_000


class PrefixCounter:
    """Counts for one model file; segments are remembered, and forgotten when there are too many."""

    def __init__(self, path: str, kept: int = SEGMENTS_KEPT):
        model = sentencepiece.SentencePieceProcessor(model_file=path)
        plain = [i for i in range(model.get_piece_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        self.score = {model.id_to_piece(i): -model.get_score(i) for i in plain}
        if any(MARK in p.lstrip(MARK) for p in self.score):
            raise ValueError("a piece has a space mark after another character: segments would not be independent")
        self.pieces = {p for p in self.score if len(p) == 1 or self._merge(p) == [p]}
        self.ids = {p: i for i, p in enumerate(sorted(self.pieces))}
        self.names = list(self.ids)
        #: Every end of a piece, with the piece's number if it is one itself and -1 if not.
        self.endings = {p[i:]: self.ids.get(p[i:], -1) for p in self.pieces for i in range(len(p))}
        self.joined = {p[i : i + 2] for p in self.pieces for i in range(len(p) - 1)}
        #: Whether two pieces side by side stay two, by both numbers in one.
        self.apart: dict[int, bool] = {}
        self.heads: dict[str, tuple[tuple[int, ...], tuple[int, ...]]] = {}
        self.totals = _Totals(self.total, kept)
        self.words = _Totals(lambda word: self.total(MARK + word), kept)

    def _merge(self, text: str) -> list[str]:
        parts = list(text)
        while len(parts) > 1:
            best = min(((self.score[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in self.score), default=None)
            if best is None:
                break
            i = best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def _stays_apart(self, key: int) -> bool:
        if len(self.apart) > 600_000:
            self.apart.clear()
        a, b = self.names[key >> 20], self.names[key & 0xFFFFF]
        found = self.apart[key] = self._merge(a + b) == [a, b]
        return found

    def segment(self, s: str) -> list[int]:
        """The token count of every prefix of a segment, by code points."""
        if len(s) <= HEAD:
            return self._extend(s, [-1], [0])[1][1:]
        head = s[:HEAD]  # nothing that follows changes what a prefix has, and many words begin alike
        known = self.heads.get(head)
        if known is None:
            if len(self.heads) > HEADS_KEPT:
                self.heads.clear()
            known = self.heads[head] = tuple(map(tuple, self._extend(head, [-1], [0])))
        return self._extend(s, list(known[0]), list(known[1]))[1][1:]

    def _extend(self, s: str, last: list[int], counts: list[int]) -> tuple[list[int], list[int]]:
        """The number of each prefix's last piece, -1 for none, and its count: from those of a shorter prefix on."""
        ending, known, apart = self.endings.get, self.apart.get, self._stays_apart
        for i in range(len(last), len(s) + 1):
            found = []
            for j in range(i - 1, -1, -1):
                n = ending(s[j:i])
                if n is None:
                    break
                if n >= 0:
                    found.append((j, n))
            for j, n in reversed(found):
                before = last[j]
                if before >= 0:
                    ok = known(key := before << 20 | n)
                    if not (apart(key) if ok is None else ok):
                        continue
                last.append(n)
                counts.append(counts[j] + 1)
                break
            else:  # a character of no piece: its bytes, and nothing merges across them
                last.append(-1)
                counts.append(counts[i - 1] + len(s[i - 1].encode("utf-8", "surrogatepass")))
        return last, counts

    def total(self, word: str) -> int:
        """A segment's count. Two neighbours that no piece holds side by side part it: the sides are counted alone, and remembered."""
        if word.lstrip(MARK).isalpha():
            return self.segment(word)[-1]
        joined, cuts = self.joined, [0]
        cuts += [i for i in range(1, len(word)) if word[i - 1 : i + 1] not in joined]
        if len(cuts) == 1:
            return self.segment(word)[-1]
        return sum(self.totals[word[a:b]] for a, b in zip(cuts, [*cuts[1:], len(word)]))

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        marked = text.replace(MARK, " ")
        words = marked.split(" ")
        if "" not in words:
            return sum(map(self.words.__getitem__, words))
        return sum(map(self.totals.__getitem__, SEGMENT.findall(MARK + marked.replace(" ", MARK))))

    def prefixes(self, text: str | None) -> np.ndarray:
        """The token count of text[:k] for each k from 1 on."""
        if not text:
            return np.zeros(0, np.int64)
        out, total = [], 0
        for s in SEGMENT.findall(MARK + text.replace(" ", MARK)):
            own = np.array(self.segment(s))
            out.append(own + total)
            total = int(out[-1][-1])
        return np.concatenate(out)[1:]

    def longest_prefix(self, text: str | None, budget: int) -> int:
        """Code points of the longest prefix of at most `budget` tokens."""
        total, at = 0, -1  # the first segment's mark is not of the text
        for s in SEGMENT.findall(MARK + text.replace(" ", MARK)) if text else []:
            n = self.totals[s]
            if total + n > budget:  # whole segments add up, so only this one can hold the end
                fits = [k for k, c in enumerate(self.segment(s), 1) if total + c <= budget]
                return max(0, at + (fits[-1] if fits else 0))
            total, at = total + n, at + len(s)
        return max(0, at)


class _Totals(dict):
    """Counts of what `work` counts, of keys that are not too long. When half of `most` are held, those not used since
    the last time are forgotten."""

    def __init__(self, work: Callable[[str], int], most: int):
        self.work, self.most, self.old = work, most, {}

    def __missing__(self, word: str) -> int:
        n = self.old.get(word)
        if n is None:
            n = self.work(word)
        if len(word) <= 64:
            if len(self) >= self.most // 2:
                self.old = dict(self)
                self.clear()
            self[word] = n
        return n


@lru_cache(maxsize=4)
def counter_of(path: str) -> PrefixCounter:
    """One counter for each Python worker and file."""
    return PrefixCounter(path)


COUNTED = "struct<n_tokens: long, fits_chars: long>"


def token_counter(path: str, limit: int) -> Callable:
    """A column function: text to struct(n_tokens, fits_chars), where fits_chars is its longest prefix of `limit` tokens at most."""

    def run(texts: pa.Array) -> pa.Array:
        counter = counter_of(path)
        rows = texts.to_pylist()
        tidy()
        n = [counter.count(t) for t in rows]
        fits = [len(t or "") if x <= limit else counter.longest_prefix(t, limit) for t, x in zip(rows, n, strict=True)]
        return pa.StructArray.from_arrays([pa.array(n, pa.int64()), pa.array(fits, pa.int64())], names=["n_tokens", "fits_chars"])

    run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return lambda text: F.arrow_udf(run, COUNTED)(text)


def prefix_counts(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, counts array<long>): the token count of every prefix of each whole text, by code points; null: no prefixes."""

    def run(texts: pa.Array) -> pa.Array:
        return pa.array([counter_of(path).prefixes(t) for t in texts.to_pylist()], pa.list_(pa.int64()))

    run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return docs.select(F.col(id_col).alias("doc_id"), F.arrow_udf(run, "array<bigint>")(F.col(text_col).cast("string")).alias("counts"))


def count_tokens(docs: DataFrame, path: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit, fits_chars) of every row. Narrow; whole texts; null counts as empty.

    path: a model file that every executor can read at that place. Strings of special tokens are ordinary text. Repeated
    rows and null ids are rows like others.
    """
    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes"), token_counter(path, limit)(text).alias("c"))
    return rows.select("doc_id", "n_bytes", F.col("c.n_tokens").alias("n_tokens"), (F.col("c.n_tokens") > limit).alias("over_limit"), F.col("c.fits_chars").alias("fits_chars"))
