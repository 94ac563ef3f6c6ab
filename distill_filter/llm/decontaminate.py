"""Benchmark decontamination by edit distance: a random-walk embedding, bit sampling, exact verification.

Words are the symbols. A walk reads a word, writes it down, and moves on or stays put by a random bit of that word and
step; two texts that differ by few edits write mostly the same words at the same steps, so their edit distance shows as
Hamming distance. Walks go through a whole window of an item's size, in twice as many steps as it has words. A repetition
draws the bits and a few steps from all over the walk; the words written there are its key. Walks start at every word of
a document from which a window could match: an edit breaks at most q runs of q words, so a window that matches holds a
known number of the items' runs, a bound that loses nothing. Windows that share a key with an item in any repetition are
checked by exact edit distance, so nothing is reported that is not a match. Items too short to sample are found exactly:
each of their matches holds one of their runs unbroken.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WORD = re.compile(r"[^\W_]+")
#: Code points of text that are worked on at a time, and words of items that one pass over the documents takes.
BITE, BLOCK_WORDS = 1 << 21, 1 << 20
#: Starts that walk at a time.
WALKS = 1 << 13
#: Spreads the number of a step over 64 bits.
ODD = 0x9E3779B97F4A7C15
MATCHES = "doc_id long, item_id long, edit_distance int, item_words int, start_word long, end_word long"


@dataclass(frozen=True)
class Settings:
    """similarity: 1 - edits / item words, at least; min_words: shorter items are not looked for (1: all are).

    repetitions of `sampled` steps each reach the target recall of 0.95 at the least similarity: tests measure it, with
    edits spread and in clusters. Items are handled in classes whose lengths differ by `ratio` at most. Items of fewer
    than `sample_from` words are looked up by all their runs instead, without a loss.
    """

    similarity: float = 0.8
    min_words: int = 1
    repetitions: int = 48
    sampled: int = 3
    sample_from: int = 8
    ratio: float = 1.25
    seed: int = 11


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def allowed(n: int, similarity: float) -> int:
    return int((1 - similarity) * n + 1e-9)


def best_match(item: list[int], text: list[int], masks: dict[int, int] | None = None) -> tuple[int, int]:
    """(edits, end): of all places in text where item can end, the one with the fewest edits, the first of equals.

    Bit-parallel columns of the edit table; the item may start anywhere in text.
    """
    if masks is None:
        masks = masks_of(item)
    n, full = len(item), (1 << len(item)) - 1
    top, up, down, score = 1 << (n - 1), full, 0, n
    best = (n, 0)
    for at, w in enumerate(text):
        eq = masks.get(w, 0)
        d0 = (((eq & up) + up) ^ up) | eq | down
        plus, minus = (down | ~(d0 | up)) & full, up & d0
        score += bool(plus & top) - bool(minus & top)
        plus, minus = plus << 1 & full, minus << 1 & full
        up, down = (minus | ~(d0 | plus)) & full, plus & d0
        if score < best[0]:
            best = (score, at + 1)
    return best


def masks_of(item: list[int]) -> dict[int, int]:
    masks: dict[int, int] = {}
    for i, w in enumerate(item):
        masks[w] = masks.get(w, 0) | 1 << i
    return masks


def runs_of(words: np.ndarray, q: int) -> np.ndarray:
    """A number for the run of q words at each place; 0 where a word is unknown or the text ends."""
    n = len(words) - q + 1
    if n <= 0:
        return np.zeros(len(words), np.int64)
    number, whole = np.zeros(n, np.int64), np.ones(n, bool)
    for k in range(q):
        number = number * 1_000_003 + words[k : k + n]
        whole &= words[k : k + n] > 0
    return np.concatenate([np.where(whole, number, 0), np.zeros(q - 1, np.int64)])


@dataclass
class Class:
    """Items of about the same length: their runs of q words, and the keys of each repetition sorted for look-up."""

    least: int
    most: int
    edits: int
    q: int
    need: int
    runs: np.ndarray
    #: Of short items: run, place in the item and place in self.items, sorted by run.
    holders: tuple[np.ndarray, np.ndarray, np.ndarray] | None = None
    steps: np.ndarray | None = None
    keys: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)


class Index:
    """The items of one block, ready for search; plain arrays, so that it travels to the workers."""

    def __init__(self, items: list[tuple[int, list[str]]], settings: Settings = Settings()):
        self.settings = settings
        self.vocabulary: dict[str, int] = {}
        self.items = [(i, [self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in ws]) for i, ws in items if len(ws) >= max(1, settings.min_words)]
        self.items.sort(key=lambda x: (len(x[1]), x[0]))
        rng = np.random.default_rng(settings.seed)
        self.bits = rng.integers(0, 1 << 64, (settings.repetitions, len(self.vocabulary) + 1), dtype=np.uint64)
        self.classes: list[Class] = []
        at = 0
        while at < len(self.items):
            least = len(self.items[at][1])
            short = least < settings.sample_from
            end = at
            while end < len(self.items) and (n := len(self.items[end][1])) <= least * (1 if short else settings.ratio):
                end += 1
            self.classes.append(self._class(at, end, short, rng))
            at = end
        self.longest = max([0, *(len(ws) for _, ws in self.items)])
        self.masks = [masks_of(ws) for _, ws in self.items]

    def _class(self, at: int, end: int, short: bool, rng: np.random.Generator) -> Class:
        own, s = self.items[at:end], self.settings
        least, most = len(own[0][1]), len(own[-1][1])
        needs = {q: min(n - q + 1 - q * allowed(n, s.similarity) for n in {len(ws) for _, ws in own}) for q in (3, 2, 1)}
        q = next((q for q in (3, 2) if needs[q] >= 1), 1)
        runs = [runs_of(np.array(ws, np.int64), q)[: len(ws) - q + 1] for _, ws in own]
        found = Class(least, most, allowed(most, s.similarity), q, max(1, needs[q]), np.unique(np.concatenate(runs)))
        if short:
            run, place, item = np.concatenate(runs), np.concatenate([np.arange(len(r)) for r in runs]), np.repeat(np.arange(at, end), [len(r) for r in runs])
            order = np.argsort(run, kind="stable")
            found.holders = (run[order], place[order], item[order])
            return found
        walk = 2 * least  # a walk stays put at every other step
        found.steps = np.stack([np.sort(rng.choice(walk, s.sampled, replace=False)) for _ in range(s.repetitions)])
        padded = np.zeros((len(own), most + walk + 1), np.int64)
        for row, (_, ws) in zip(padded, own, strict=True):
            row[: len(ws)] = ws
        keys, whole = self._walk(found, padded.ravel(), np.arange(len(own)) * padded.shape[1])
        for key, good in zip(keys, whole, strict=True):
            order = np.argsort(key[good], kind="stable")
            found.keys.append((key[good][order], (np.flatnonzero(good) + at)[order]))
        return found

    def _walk(self, c: Class, words: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The key of each repetition and start, and whether all its sampled words are of the vocabulary."""
        shape = (len(self.bits), len(starts))
        place, key, whole = np.broadcast_to(starts, shape).copy(), np.zeros(shape, np.int64), np.ones(shape, bool)
        rows = np.arange(len(self.bits))[:, None]
        for j in range(int(c.steps.max(initial=-1)) + 1):
            w = words[place]
            at = np.flatnonzero((c.steps == j).any(axis=1))
            key[at] = key[at] * 1_000_003 + w[at]
            whole[at] &= w[at] > 0
            turn = self.bits[:, :1] + np.uint64(j * ODD & (1 << 64) - 1)
            turn = (turn ^ turn >> np.uint64(31)) * np.uint64(ODD) | np.uint64(1)
            place += (self.bits[rows, w] * turn >> np.uint64(63)).astype(np.int64)
        return key, whole

    def candidates(self, words: np.ndarray) -> set[tuple[int, int]]:
        """(start of the item, place of the item in self.items) over words, vocabulary numbers with 0 for any other."""
        found: set[tuple[int, int]] = set()
        runs = {q: runs_of(words, q) for q in {c.q for c in self.classes}}
        places = {q: np.flatnonzero(r) for q, r in runs.items()}
        padded = np.concatenate([words, np.zeros(2 * max([0, *(c.least for c in self.classes)]) + 1, np.int64)])
        for c in self.classes:
            own, at = runs[c.q], places[c.q]
            at = at[c.runs[np.minimum(np.searchsorted(c.runs, own[at]), len(c.runs) - 1)] == own[at]]
            if c.holders is not None:
                run, place, item = c.holders
                left, right = np.searchsorted(run, own[at], "left"), np.searchsorted(run, own[at], "right")
                for p, a, b in zip(at.tolist(), left.tolist(), right.tolist(), strict=True):
                    found.update(zip((p - place[a:b]).tolist(), item[a:b].tolist(), strict=True))
                continue
            starts = self._starts(at, c, len(words))
            for first in range(0, len(starts), WALKS):
                some = starts[first : first + WALKS]
                for key, whole, (keys, items) in zip(*self._walk(c, padded, some), c.keys, strict=True):
                    begin, key = some[whole], key[whole]
                    left, right = np.searchsorted(keys, key, "left"), np.searchsorted(keys, key, "right")
                    for k in np.flatnonzero(right > left).tolist():
                        found.update((int(begin[k]), int(i)) for i in items[left[k] : right[k]])
        return found

    @staticmethod
    def _starts(at: np.ndarray, c: Class, n: int) -> np.ndarray:
        """Places of a text of n words from which a window of at most c.most + c.edits words holds c.need of the runs at `at`."""
        if len(at) < c.need:
            return at[:0]
        width = c.most + c.edits - c.q + 1
        first, last = at[: len(at) - c.need + 1], at[c.need - 1 :]
        near = last - first < width
        # a window holds these c.need runs if it starts at the first of them at the latest and reaches the last
        low, high = np.maximum(last[near] - width + 1, 0), first[near] + 1
        change = np.bincount(low, minlength=n + 1)[: n + 1] - np.bincount(high, minlength=n + 1)[: n + 1]
        return np.flatnonzero(np.cumsum(change[:n]) > 0)

    def matches(self, words: np.ndarray, candidates: set[tuple[int, int]] | list[tuple[int, int]] | None = None) -> dict[int, tuple[int, int, int, int]]:
        """item_id to (edits, item words, start, end) of its best verified match; of equal ones the first."""
        best: dict[int, tuple[int, int, int, int]] = {}
        seen: dict[int, int] = {}
        for start, item in sorted(self.candidates(words) if candidates is None else candidates):
            item_id, ws = self.items[item]
            n, most = len(ws), allowed(len(ws), self.settings.similarity)
            # each region that was checked reaches so far past its start that nearer starts need no check of their own
            if item in seen and start <= seen[item] + most:
                continue
            seen[item] = start
            low = max(0, start - most)
            region = words[low : start + n + 3 * most + 2].tolist()
            masks = self.masks[item]
            if len([w for w in region if w in masks]) < n - most:  # a match keeps so many of the item's words
                continue
            edits, end = best_match(ws, region, masks)
            if edits <= most and (item_id not in best or edits < best[item_id][0]):
                back = best_match(ws[::-1], region[:end][::-1])[1]
                best[item_id] = (edits, n, low + end - back, low + end)
        return best

    def number(self, texts: list[str | None]) -> list[np.ndarray]:
        known = self.vocabulary
        return [np.fromiter(map(known.get, words_of(t), repeat(0)), np.int64) for t in texts]


def _found(index: Index, ids: list, texts: list[str | None]) -> list[tuple]:
    """Rows of MATCHES. Documents lie end to end, with gaps that no match can cross, so that each step works on many."""
    gap = np.zeros(2 * index.longest + 2, np.int64)
    numbers = index.number(texts)
    firsts = np.cumsum([0] + [len(x) + len(gap) for x in numbers])
    line = np.concatenate([y for x in numbers for y in (x, gap)])
    hits: dict[int, list[tuple[int, int]]] = {}
    found = sorted(index.candidates(line))
    starts = np.array([s for s, _ in found], dtype=np.int64) + index.longest  # an item may begin a little before its document does
    for (start, item), k in zip(found, (np.searchsorted(firsts, starts, "right") - 1).tolist(), strict=True):
        hits.setdefault(k, []).append((start - int(firsts[k]), item))
    return [(ids[k], item, *m) for k, near in hits.items() for item, m in index.matches(numbers[k], near).items()]


def _bites(texts: list[str | None]) -> Iterator[tuple[int, int]]:
    """(first, end) of runs of texts of about BITE code points."""
    first, size = 0, 0
    for i, t in enumerate(texts):
        size += len(t or "")
        if size > BITE:
            yield first, i + 1
            first, size = i + 1, 0
    if first < len(texts):
        yield first, len(texts)


def _search(index: Index):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, texts = b.column(0).to_pylist(), b.column(1).to_pylist()
            rows = [r for first, end in _bites(texts) for r in _found(index, ids[first:end], texts[first:end])]
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=MATCHES.replace(",", "").split()[::2])

    return run


def _holds(index: Index):
    """A column function: whether a text holds any of the index's items."""

    def run(texts: pa.Array) -> pa.Array:
        all_ = texts.to_pylist()
        held = np.zeros(len(all_), bool)
        for first, end in _bites(all_):
            held[[r[0] for r in _found(index, list(range(first, end)), all_[first:end])]] = True
        return pa.array(held)

    run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return lambda text: F.arrow_udf(run, "boolean")(text)


def item_blocks(items: DataFrame, block_words: int = BLOCK_WORDS) -> Iterator[list[tuple[int, list[str]]]]:
    """The items in blocks of about block_words words: what one pass takes to the workers has this bound."""
    block, size = [], 0
    for r in items.toLocalIterator():
        ws = words_of(r.text)
        block.append((r.item_id, ws))
        size += len(ws)
        if size >= block_words:
            yield block
            block, size = [], 0
    if block:
        yield block


def _items(benchmark: DataFrame) -> DataFrame:
    return benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null")


def find_contamination(docs: DataFrame, benchmark: DataFrame, settings: Settings = Settings(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each document and benchmark item that it holds, with the edits and the words of the best place.

    Words are runs of letters and digits, lower-cased. Null or empty texts match nothing; items with a null id or without a
    word, or with fewer than min_words, are not looked for. Equal items are found each under its id. A null doc_id is kept; a doc_id
    that occurs twice has its rows for each of its texts. Documents stay where they are: one pass for each block of
    items, no shuffle. No documents or no items: an empty result.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    out = None
    for block in item_blocks(_items(benchmark)):
        found = rows.mapInArrow(_search(Index(block, settings)), MATCHES)
        out = found if out is None else out.union(found)
    return out if out is not None else docs.sparkSession.createDataFrame([], MATCHES)


def without_contaminated(docs: DataFrame, benchmark: DataFrame, settings: Settings = Settings(), text_col: str = "text") -> DataFrame:
    """docs without the rows whose text holds an item. Each row is judged by its own text, whatever its id: rows without
    an id and rows that share one too. Null and empty texts stay; no items: all stay. One pass for each block of items."""
    for block in item_blocks(_items(benchmark)):
        docs = docs.where(~_holds(Index(block, settings))(F.col(text_col).cast("string")))
    return docs
