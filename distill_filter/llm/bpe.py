"""Byte-level BPE as a bounded-lookahead streaming transducer, and an incremental decoder.

The merge list alone tells how far to the right a token's fate can depend on the text (sufficient_lookahead). So a text
of any length, even one endless word, is encoded in constant memory: a token is emitted once that many bytes after it
have been seen. Short words never wait: the end of a pre-token is a token boundary whatever follows.
"""

from __future__ import annotations

import codecs
import heapq
import json
from collections.abc import Callable, Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import tidy

#: Fixed value: the pre-token pattern of the byte-level vocabulary.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Chars past a match that can change it: two after a quote, one after white space.
PATTERN_LOOKAHEAD = 3
RUNS = {"L": regex.compile(r"\p{L}*"), "N": regex.compile(r"\p{N}*"), "P": regex.compile(r"[^\s\p{L}\p{N}]*"), "S": regex.compile(r"\s*")}
CHUNK = 1 << 16
#: Code points of a text that the encoder is fed at a time; a pre-token longer than this goes through the transducer in pieces.
PIECE = 1 << 12
WORDS_KEPT = 400_000


@lru_cache(maxsize=1)
def byte_alphabet() -> dict[str, int]:
    """The printable characters that stand for bytes in the vocabulary file: printable Latin-1 for itself, others from 256 on."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class MergeTable:
    """A vocabulary and its merge list, over bytes."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet = byte_alphabet()
        raw = lambda s: bytes(alphabet[c] for c in s)
        self.ids = {raw(t): i for t, i in spec["model"]["vocab"].items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.by_id = {i: t for t, i in self.ids.items()} | {i: s.encode() for s, i in self.special.items()}
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        self.pairs = [(self.ids[raw(a)], self.ids[raw(b)]) for a, b in merges]
        whole = [self.ids[raw(a + b)] for a, b in merges]
        self.rank = {p: (r, w) for r, (p, w) in reversed(list(enumerate(zip(self.pairs, whole, strict=True))))}
        self.one = [self.ids[bytes([b])] for b in range(256)]
        self.size = {i: len(t) for t, i in self.ids.items()}
        self.lookahead = sufficient_lookahead(self.pairs, whole, self.size)

    def merge(self, data: bytes) -> list[int]:
        """Token ids of one pre-token."""
        return self._merge_long(data) if len(data) > 64 else self._merge_short(data)

    def _merge_short(self, data: bytes) -> list[int]:
        ids, rank = [self.one[b] for b in data], self.rank
        found = [rank.get(p) for p in zip(ids, ids[1:])]
        while True:
            best = None
            for i, f in enumerate(found):
                if f is not None and (best is None or f < best):
                    best, at = f, i
            if best is None:
                return ids
            ids[at : at + 2] = [best[1]]
            del found[at]
            if at:
                found[at - 1] = rank.get((ids[at - 1], ids[at]))
            if at < len(found):
                found[at] = rank.get((ids[at], ids[at + 1]))

    def _merge_long(self, data: bytes) -> list[int]:
        n, rank = len(data), self.rank
        ids: list[int | None] = [self.one[b] for b in data]
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(f[0], i, f[1], ids[i], ids[i + 1]) for i in range(n - 1) if (f := rank.get((ids[i], ids[i + 1])))]
        heapq.heapify(heap)
        while heap:
            _, i, whole, a, b = heapq.heappop(heap)
            j = nxt[i]
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = whole, None
            nxt[i] = k = nxt[j]
            if k < n:
                prv[k] = i
                if f := rank.get((whole, ids[k])):
                    heapq.heappush(heap, (f[0], i, f[1], whole, ids[k]))
            if (h := prv[i]) >= 0 and (f := rank.get((ids[h], whole))):
                heapq.heappush(heap, (f[0], h, f[1], ids[h], whole))
        return [x for x in ids if x is not None]


def sufficient_lookahead(pairs: list[tuple[int, int]], whole: list[int], size: dict[int, int]) -> int:
    """Bytes after a token's end that fix whether it stands, whatever follows them.

    A token ends where it does unless a merge takes it, or the right part that it was formed from, to the right. Whether
    the merge (u, w) takes place hangs on w standing there at that time: on w's own bytes, and on whether w, or the
    right part of w before w was formed, had been taken by an earlier merge. Ranks fall along this chain, so one pass
    over the list in order of rank adds up the longest one: `open_to[t]` for a whole token so far, `formed[t]` for its
    right parts up to when it was formed.
    """
    open_to: dict[int, int] = {}
    formed: dict[int, int] = {}
    for (u, w), t in zip(pairs, whole, strict=True):
        need = size[w] + max(open_to.get(w, 0), formed.get(w, 0))
        formed[t] = max(formed.get(t, 0), open_to.get(w, 0), formed.get(w, 0))
        open_to[u] = max(open_to.get(u, 0), need)
    return max([0, *open_to.values()])


class LongWord:
    """One pre-token fed in pieces; holds no more than the lookahead and a block."""

    def __init__(self, table: MergeTable, block: int = 4096):
        self.table, self.block, self.pending = table, block, b""

    def feed(self, data: bytes) -> Iterator[int]:
        for at in range(0, len(data), self.block):
            self.pending += data[at : at + self.block]
            if len(self.pending) >= self.block + self.table.lookahead:
                yield from self._emit(len(self.pending) - self.table.lookahead)

    def finish(self) -> Iterator[int]:
        yield from self._emit(len(self.pending))

    def _emit(self, stable: int) -> Iterator[int]:
        end = 0
        for token in self.table.merge(self.pending):
            if (then := end + self.table.size[token]) > stable:
                break
            end = then
            yield token
        self.pending = self.pending[end:]


class _Words(dict):
    """Pre-token to its ids as little-endian unsigned 32-bit integers. When half of `most` are held, those not used since
    the last time are forgotten."""

    def __init__(self, table: MergeTable, most: int):
        self.table, self.most, self.old = table, most, {}

    def __missing__(self, word: str) -> bytes:
        out = self.old.get(word)
        if out is None:
            out = np.array(self.table.merge(word.encode("utf-8", "surrogatepass")), dtype="<u4").tobytes()
        if len(word) <= 64:
            if len(self) >= self.most // 2:
                self.old = dict(self)
                self.clear()
            self[word] = out
        return out


class Encoder:
    """Feed a text in pieces of any size; ids come out, as bytes of little-endian unsigned 32-bit integers, once stable."""

    def __init__(self, table: MergeTable, longest: int = PIECE, words_kept: int = WORDS_KEPT):
        self.table, self.longest = table, longest
        self.words = _Words(table, words_kept)
        self.pattern = regex.compile(PRETOKEN)
        self.cut = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(table.special, key=len, reverse=True)) + ")") if table.special else None
        self.reach = max([0, *map(len, table.special)]) - 1
        self._start()

    def _start(self) -> None:
        self.text, self.long, self.kind = "", None, ""

    def feed(self, piece: str) -> Iterator[bytes]:
        self.text += piece
        if self.cut is None:
            yield from self._plain(False)
            return
        while m := self.cut.search(self.text):
            rest, self.text = self.text[m.end() :], self.text[: m.start()]
            yield from self._plain(True)
            yield np.array([self.table.special[m[0]]], dtype="<u4").tobytes()
            self.text = rest
        held = next((n for n in range(min(self.reach, len(self.text)), 0, -1) if any(s.startswith(self.text[-n:]) for s in self.table.special)), 0)
        tail = self.text[len(self.text) - held :]
        self.text = self.text[: len(self.text) - held]
        yield from self._plain(False)
        self.text += tail

    def finish(self) -> Iterator[bytes]:
        yield from self._plain(True)
        self._start()

    def encode(self, text: str) -> bytes:
        """All ids of a text, fed in pieces."""
        out = [ids for at in range(0, len(text), self.longest) for ids in self.feed(text[at : at + self.longest])]
        return b"".join([*out, *self.finish()])

    def _plain(self, final: bool) -> Iterator[bytes]:
        """Encode what is stable of the text held; all of it if nothing can follow."""
        if self.long:
            yield from self._go_on(final)
        if self.long or not self.text:
            return
        stable, end = len(self.text) if final else len(self.text) - PATTERN_LOOKAHEAD, len(self.text)
        words = self.pattern.findall(self.text)  # every character is in a match
        while words and end > stable:
            end -= len(words.pop())
        yield b"".join(map(self.words.__getitem__, words))
        self.text = self.text[end:]
        if len(self.text) > self.longest + 8:  # no match ends before the last few characters: one pre-token without an end yet
            spaced = self.text[0] == " " and not self.text[1].isspace()
            self.kind = next(k for k, run in RUNS.items() if run.match(self.text[spaced]).end())
            self.long = LongWord(self.table)
            if spaced:
                yield self._ids(self.long.feed(b" "))
                self.text = self.text[1:]
            yield from self._go_on(False)

    @staticmethod
    def _ids(tokens: Iterable[int]) -> bytes:
        return np.array(list(tokens), dtype="<u4").tobytes()

    def _go_on(self, final: bool) -> Iterator[bytes]:
        end = RUNS[self.kind].match(self.text).end()
        over = final or end < len(self.text)
        if self.kind == "S" and not (final and end == len(self.text)):
            end = max(0, end - 1)  # the last white space may belong to what follows
        yield self._ids(self.long.feed(self.text[:end].encode("utf-8", "surrogatepass")))
        self.text = self.text[end:]
        if over:
            yield self._ids(self.long.finish())
            self.long = None


class Decoder:
    """Ids to text in pieces; bytes of a character that is not whole yet are kept for the next call."""

    def __init__(self, table: MergeTable):
        self.by_id, self.state = table.by_id, codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids: Iterable[int]) -> str:
        return self.state.decode(b"".join(map(self.by_id.__getitem__, ids)))

    def finish(self) -> str:
        return self.state.decode(b"", True)


@lru_cache(maxsize=4)
def table_of(path: str) -> MergeTable:
    """One table for each Python worker and file."""
    return MergeTable(path)


@lru_cache(maxsize=2)
def encoder_of(path: str) -> Encoder:
    """One encoder for each Python worker and file: the words it remembers outlive a task."""
    return Encoder(table_of(path))


def _decoded(table: MergeTable, ids: bytes) -> str:
    decoder, tokens = Decoder(table), np.frombuffer(ids, "<u4")
    return "".join(decoder.feed(tokens[at : at + CHUNK].tolist()) for at in range(0, len(tokens), CHUNK)) + decoder.finish()


def bpe_codec(path: str, with_text: bool = True) -> Callable:
    """A column function: text to struct(ids, decoded), or struct(ids, decodes boolean) without the text.

    ids are little-endian unsigned 32-bit integers. Null counts as empty.
    """
    last = ("decoded", pa.string()) if with_text else ("decodes", pa.bool_())

    def run(texts: pa.Array) -> pa.Array:
        encoder, ids, back = encoder_of(path), [], []
        for t in texts:
            t = t.as_py() or ""
            ids.append(encoder.encode(t))
            text = _decoded(encoder.table, ids[-1])
            back.append(text if with_text else text == t)
        out = pa.StructArray.from_arrays([pa.array(ids, pa.binary()), pa.array(back, last[1])], names=["ids", last[0]])
        tidy()
        return out

    run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return lambda text: F.arrow_udf(run, f"struct<ids: binary, {last[0]}: {'string' if with_text else 'boolean'}>")(text)


def bpe_round_trip(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids binary, decoded string) of every row. Narrow; whole texts; null counts as empty, with no ids.

    path: a vocabulary file that every executor can read at that place. Special strings inside texts become their ids,
    as the public library has it by default. Repeated rows and null ids are rows like others.
    """
    return docs.select(F.col(id_col).alias("doc_id"), bpe_codec(path)(F.col(text_col).cast("string")).alias("c")).select("doc_id", "c.ids", "c.decoded")
