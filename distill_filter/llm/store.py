"""A content-addressed store of token ids.

A rolling hash over the last 16 ids cuts each document's ids into chunks, so equal passages give equal chunks wherever
they stand. A store is a folder of Parquet tables that Spark commits as a whole: `chunks` holds each unique chunk once
under its digest; `recipes` lists, in ascending order of document, the digests that rebuild it; `manifest` holds the
hashes of a Merkle tree over the recipes. Reading checks chunks against digests and recipes against the root.
"""

from __future__ import annotations

import hashlib
import json
import os
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .bpe import byte_alphabet
from .shared import remove, tidy

WINDOW, LEAST, MOST, MEAN_BITS = 16, 64, 2048, 8
FANOUT = 1024
#: Words of letters alone, and other pieces, that a Python worker remembers: about 200 bytes each.
PLAIN_KEPT, OTHER_KEPT = 800_000, 200_000
#: Bytes of text that are worked on at a time.
BITE = 1 << 22
ENCODED = "doc_id long, n_tokens long, digests array<binary>, data array<binary>"
RECIPES = "part int, pos long, doc_id long, rel_start long, n_tokens long, digests array<binary>, leaf string"


@lru_cache(maxsize=1)
def gear() -> np.ndarray:
    """A 64-bit value for each id below 2^16, by a mixing rule; larger ids take the value of their low bits."""
    x = (np.arange(1 << 16, dtype=np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ x >> np.uint64(30)) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ x >> np.uint64(27)) * np.uint64(0x94D049BB133111EB)
    return x ^ x >> np.uint64(31)


def cut_points(ids: np.ndarray, ends: np.ndarray) -> list[list[int]]:
    """For documents that lie end to end in ids: the ends of each one's chunks, all between LEAST and MOST long but the last."""
    g = gear()[ids & 0xFFFF]
    h = g.copy()
    for k in range(1, WINDOW):
        h[k:] += g[:-k] << np.uint64(k)
    found = np.flatnonzero(h >> np.uint64(64 - MEAN_BITS) == 0) + 1
    out, start = [], 0
    for end in ends.tolist():
        cuts, last = [], start
        for c in found[np.searchsorted(found, start + LEAST) : np.searchsorted(found, end)].tolist():
            while c - last > MOST:
                last += MOST
                cuts.append(last)
            if c - last >= LEAST:
                cuts.append(c)
                last = c
        while end - last > MOST:
            last += MOST
            cuts.append(last)
        out.append([*cuts, end])
        start = end
    return out


class Kept(dict):
    """A dictionary of two halves: when one is full, what was not used since the last time is forgotten."""

    def __init__(self, most: int):
        self.half, self.old = most // 2, {}

    def trim(self) -> None:
        if len(self) > self.half:
            self.old = dict(self)
            self.clear()


#: The normaliser and the split that let a text be taken apart at spaces.
NORMALISER = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORD_END = "</w>"
#: Letters of Latin-1, and marks that close a word, as parts of a pattern.
LATIN, CLOSING = "A-Za-z\u00aa\u00b5\u00ba\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff", ".,;:!?"


def takes_apart(spec: dict) -> bool:
    """Whether a tokenizer's file says what the encoder relies on: words end at spaces and each ends in a token of its own kind."""
    before = (spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}]
    normal = (spec.get("normalizer") or {}).get("normalizers")
    split = before[0].get("pattern") == {"Regex": SPLIT} and before[0].get("invert") and before[0].get("behavior") == "Removed"
    level = len(before) == 2 and before[1].get("type") == "ByteLevel" and not before[1].get("add_prefix_space") and not before[1].get("use_regex")
    plain = not any(spec.get(k) for k in ("post_processor", "truncation", "padding")) and spec["model"].get("end_of_word_suffix") == WORD_END
    return bool(normal == NORMALISER and split and level and plain)


class WordEncoder:
    """The public library's ids, by pieces between spaces: its rules never look across one. Pieces are remembered.

    A batch's texts are split and its distinct pieces found in Arrow; ids are put together by numpy. A piece that is a word
    and one closing mark is taken apart, and words in Latin letters are looked up in lower case, as the library would do
    itself, and by its model alone. A file with another normaliser or split is left to the library as a whole.
    """

    def __init__(self, path: str, plain_kept: int = PLAIN_KEPT, other_kept: int = OTHER_KEPT):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        vocabulary = self.library.get_vocab()
        self.dtype = np.dtype("<u2" if max(vocabulary.values()) < 1 << 16 else "<u4")
        with open(path, encoding="utf-8") as f:
            self.apart = takes_apart(json.load(f))
        self.alphabet = {b: ord(c) for c, b in byte_alphabet().items()}
        self.plain, self.other = Kept(plain_kept), Kept(other_kept)

    def encode(self, texts: list[str]) -> list[bytes]:
        """For each text its ids as little-endian integers of self.dtype."""
        ids, n = self.flat(pa.array(texts, pa.large_string()))
        data, at = ids.tobytes(), np.concatenate([[0], np.cumsum(n)]) * self.dtype.itemsize
        return [data[a:b] for a, b in zip(at, at[1:])]

    def flat(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts end to end, and how many each has; a null text has none."""
        if not len(texts):
            return np.zeros(0, self.dtype), np.zeros(0, np.int64)
        if not self.apart:
            coded = [e.ids for e in self.library.encode_batch_fast(["" if t is None else t for t in texts.to_pylist()], add_special_tokens=False)]
            return np.array([i for c in coded for i in c], self.dtype), np.array([len(c) for c in coded], np.int64)
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        parts = pc.split_pattern(pc.replace_substring(texts, "\n", " "), " ")
        pieces = pc.dictionary_encode(parts.flatten())
        which, piece = pieces.indices.to_numpy(), pieces.dictionary
        # only after a Latin-1 letter: others may gain marks of their own in lower case (as the dotted capital I does) or
        # in normal form, and those join with what follows
        marked = pc.match_substring_regex(piece, f"[{LATIN}][{CLOSING}]$")
        word = pc.if_else(marked, pc.utf8_slice_codeunits(piece, 0, -1), piece)
        mark = pc.if_else(marked, pc.utf8_slice_codeunits(piece, -1), "")
        plain = pc.match_substring_regex(word, f"^[{LATIN}]+$")
        words = pc.dictionary_encode(pc.if_else(plain, pc.utf8_lower(word), word))
        marks = pc.dictionary_encode(mark)
        coded = self._coded(words.dictionary) + [self._small(m) for m in marks.dictionary.to_pylist()]
        size = np.fromiter(map(len, coded), np.int64, len(coded)) // self.dtype.itemsize
        table, first = np.frombuffer(b"".join(coded), self.dtype), np.cumsum(size) - size
        pair = np.column_stack([words.indices.to_numpy(), marks.indices.to_numpy() + len(words.dictionary)])
        part = pair[which].ravel()
        n = size[part]
        upto = np.concatenate([[0], np.cumsum(n)])
        ids = table[np.repeat(first[part] - upto[:-1], n) + np.arange(upto[-1])]
        edges = 2 * (parts.offsets.to_numpy() - parts.offsets[0].as_py())
        return ids, np.diff(upto[edges])

    def _coded(self, words: pa.Array) -> list[bytes]:
        """The ids of distinct words, in their order: those of letters alone, in lower case, and all others."""
        plain = pc.match_substring_regex(words, f"^[{LATIN}]+$").to_numpy(zero_copy_only=False)
        out: list[bytes] = [b""] * len(words)
        for kept, mask, look_up in ((self.plain, plain, self._by_model), (self.other, ~plain, self._by_library)):
            at = np.flatnonzero(mask)
            some = words.take(pa.array(at)).to_pylist()
            kept.trim()
            found = list(map(kept.get, some))
            if None in found:
                old, missing = kept.old.get, []
                for i, known in enumerate(found):
                    if known is None:
                        if (known := old(some[i])) is None:
                            missing.append(i)
                        else:
                            found[i] = kept[some[i]] = known
                for i, ids in zip(missing, look_up([some[i] for i in missing]), strict=True):
                    found[i] = kept[some[i]] = ids
            for i, ids in zip(at.tolist(), found, strict=True):
                out[i] = ids
        return out

    def _small(self, mark: str) -> bytes:
        return self._by_library([mark])[0] if mark else b""

    def _by_model(self, words: list[str]) -> list[bytes]:
        """A plain word is one word of the split, in lower case and normal form: what is left to do is the model's."""
        coded, sizes, tokenize = [], [], self.library.model.tokenize
        for w in words:
            tokens = tokenize(w if w.isascii() else w.encode().decode("latin-1").translate(self.alphabet))
            coded += [t.id for t in tokens]
            sizes.append(len(tokens))
        data, ends = np.array(coded, dtype=self.dtype).tobytes(), np.cumsum([0, *sizes]) * self.dtype.itemsize
        return [data[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]

    def _by_library(self, words: list[str]) -> list[bytes]:
        return [np.array(e.ids, dtype=self.dtype).tobytes() for at in range(0, len(words), 4096) for e in self.library.encode_batch_fast(words[at : at + 4096], add_special_tokens=False)]


@lru_cache(maxsize=2)
def encoder_of(path: str) -> WordEncoder:
    """One encoder for each Python worker and file: what it remembers outlives a task."""
    return WordEncoder(path)


def digest(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=20).digest()


def _encode(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = encoder_of(path)
        width, seen = encoder.dtype.itemsize, set()

        def work(doc_ids: pa.Array, texts: pa.Array) -> pa.RecordBatch:
            plain, n = encoder.flat(texts)
            ids = np.insert(plain, np.cumsum(n), end_id)
            n = n + 1
            whole, at, digests, data = ids.tobytes(), 0, [], []
            for cuts in cut_points(ids, np.cumsum(n)):
                d, x = [], []
                for cut in cuts:
                    chunk = whole[at * width : cut * width]
                    d.append(digest(chunk))
                    x.append(None if d[-1] in seen else chunk)
                    seen.add(d[-1])
                    at = cut
                if len(seen) > 500_000:
                    seen.clear()
                digests.append(d)
                data.append(x)
            kind = pa.list_(pa.binary())
            return pa.RecordBatch.from_arrays([doc_ids, pa.array(n, pa.int64()), pa.array(digests, kind), pa.array(data, kind)], names=["doc_id", "n_tokens", "digests", "data"])

        for b in batches:
            upto = np.cumsum(pc.fill_null(pc.binary_length(b.column(1)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
            at = 0
            while at < b.num_rows:  # rows of BITE bytes together, or one that is longer
                end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + BITE, "right")))
                yield work(b.column(0).slice(at, end - at), b.column(1).slice(at, end - at))
                at = end
            tidy()

    return run


def id_width(path: str) -> int:
    """Bytes of an id of a tokenizer's file in a store: two where its vocabulary allows."""
    return encoder_of(path).dtype.itemsize


def leaf() -> Column:
    """A recipe's hash: over its document's id, its length and its digests in order."""
    named = F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.col("n_tokens").cast("string"))
    return F.sha2(F.concat_ws(":", named, F.array_join(F.transform("digests", F.hex), "")), 256)


def _lay_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    part, pos, at = TaskContext.get().partitionId(), 0, 0
    for b in batches:
        n = b.column(1).to_numpy()
        starts = at + np.cumsum(n) - n
        own = [pa.array(np.full(len(n), part, np.int32)), pa.array(np.arange(pos, pos + len(n))), b.column(0), pa.array(starts.astype(np.int64)), *(b.column(i) for i in (1, 2, 3))]
        yield pa.RecordBatch.from_arrays(own, names=["part", "pos", "doc_id", "rel_start", "n_tokens", "digests", "leaf"])
        pos, at = pos + len(n), at + int(n.sum())


def merkle_nodes(recipes: DataFrame) -> DataFrame:
    """(part, n_docs, n_tokens, node): a row for each part of the recipes; node is the top of the tree over its leaves.

    A node hashes FANOUT children at most, so no group grows with the data.
    """
    sums = recipes.groupBy("part").agg(F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
    level, tall = recipes.select("part", "pos", F.col("leaf").alias("hash")), 1
    most = sums.agg(F.max("n_docs")).first()[0] or 0
    while tall == 1 or most > 1:
        inside = F.array_sort(F.collect_list(F.struct("pos", "hash")))
        level = level.groupBy("part", F.floor(F.col("pos") / FANOUT).cast("long").alias("up")).agg(inside.alias("in"))
        level = level.select("part", F.col("up").alias("pos"), F.sha2(F.array_join(F.transform("in", lambda x: x["hash"]), ""), 256).alias("hash"))
        most, tall = -(-most // FANOUT), tall + 1
    return sums.join(level.select("part", F.col("hash").alias("node")), "part")


def merkle_root(manifest: DataFrame) -> str:
    """One hash over the parts' nodes in order; a row for each part of the recipes comes to the driver."""
    return hashlib.sha256("".join(r.node for r in sorted(manifest.select("part", "node").collect())).encode()).hexdigest()


def write_store(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> str:
    """Encode whole texts, append end_id to each, and write the store below path; returns the Merkle root.

    Null text: the end id alone. Null doc_id: first in order. Repeated ids: each row is a document of its own, in order
    of its digests. No rows: empty tables. Texts are encoded once, into one written table; of a chunk that several
    tasks found, one copy is left before the shuffle and one after.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    encoded = f"{path}/encoded"
    rows.mapInArrow(_encode(tokenizer, end_id), ENCODED).write.option("compression", "zstd").parquet(encoded)
    table = spark.read.schema(ENCODED).parquet(encoded)
    chunks = table.select(F.explode(F.arrays_zip("digests", "data")).alias("c")).select("c.digests", "c.data").where("data is not null").toDF("digest", "data")
    chunks.dropDuplicates(["digest"]).write.option("compression", "zstd").parquet(f"{path}/chunks")
    ordered = table.select("doc_id", "n_tokens", "digests", leaf().alias("leaf")).repartitionByRange(F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "digests")
    ordered.mapInArrow(_lay_out, RECIPES).write.option("compression", "zstd").parquet(f"{path}/recipes")
    remove(encoded, spark)
    width = id_width(tokenizer)
    merkle_nodes(spark.read.schema(RECIPES).parquet(f"{path}/recipes")).withColumn("id_bytes", F.lit(width)).coalesce(1).write.parquet(f"{path}/manifest")
    return merkle_root(spark.read.parquet(f"{path}/manifest"))


@lru_cache(maxsize=1)
def _zero_tables() -> list[np.ndarray]:
    """For each k: what appending 2^k zero bytes does to a CRC-32, as a table for each of its four bytes."""

    def step(crc: int) -> int:
        for _ in range(8):
            crc = crc >> 1 ^ (0xEDB88320 if crc & 1 else 0)
        return crc

    def tables(bits: np.ndarray) -> np.ndarray:
        return np.array([[np.bitwise_xor.reduce(bits[8 * i : 8 * i + 8][[j for j in range(8) if v >> j & 1]], initial=np.uint32(0)) for v in range(256)] for i in range(4)], dtype=np.uint32)

    bits, out = np.array([step(1 << b) for b in range(32)], dtype=np.uint32), []
    for _ in range(40):
        out.append(tables(bits))
        bits = _through(out[-1], bits)
    return out


def _through(table: np.ndarray, crc: np.ndarray) -> np.ndarray:
    return table[0][crc & 255] ^ table[1][crc >> 8 & 255] ^ table[2][crc >> 16 & 255] ^ table[3][crc >> 24]


def crc32_join(crc: np.ndarray, length: np.ndarray, first: np.ndarray) -> np.ndarray:
    """CRC-32 of strings that are joined from parts, from the parts' own and their lengths in bytes; first: where each
    string's parts begin. A part counts as itself with the bytes behind it as zeros, and those add up by exclusive or."""
    upto = np.cumsum(length)
    ends = upto[np.concatenate([first[1:], [len(length)]]) - 1]
    behind = np.repeat(ends, np.diff(np.concatenate([first, [len(length)]]))) - upto
    crc = crc.astype(np.uint32)
    for k, table in enumerate(_zero_tables()):
        if not (behind >> k).any():
            break
        crc = np.where(behind >> k & 1, _through(table, crc), crc)
    return np.bitwise_xor.reduceat(crc, first)


def _check_chunks(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names, data = b.column(0).to_pylist(), b.column(1).to_pylist()
            for d, x in zip(names, data, strict=True):
                if digest(x) != d:
                    raise ValueError(f"chunk {d.hex()} does not have its digest")
            crc = [zlib.crc32(np.frombuffer(x, f"<u{width}").astype("<u4").tobytes()) for x in data]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([len(x) // width for x in data], pa.int64()), pa.array(crc, pa.int64())], names=["digest", "n", "crc"])

    return run


def _combined(chunks: pa.Array) -> pa.Array:
    """Each list has a chunk at least: every document ends with an id of its own."""
    flat, first = chunks.flatten(), chunks.offsets.to_numpy()[:-1] - chunks.offsets.to_numpy()[0]
    n, crc = flat.field("n").to_numpy(), flat.field("crc").to_numpy()
    if not len(first):
        return pa.array([], pa.struct([("crc", pa.int64()), ("n", pa.int64())]))
    whole = crc32_join(crc, 4 * n, first)
    return pa.StructArray.from_arrays([pa.array(whole.astype(np.int64)), pa.array(np.add.reduceat(n, first))], names=["crc", "n"])


_combined.__annotations__ = {"chunks": pa.Array, "return": pa.Array}


def verify_store(spark: SparkSession, path: str, root: str) -> None:
    """Rebuild the Merkle tree from the recipes' contents; raises if it does not lead to root."""

    recipes = spark.read.schema(RECIPES).parquet(f"{path}/recipes")
    if merkle_root(merkle_nodes(recipes.select("part", "pos", "n_tokens", leaf().alias("leaf")))) != root:
        raise ValueError("the recipes do not lead to the Merkle root")


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document of a store, from its chunks and recipes.

    An empty store: no rows. How wide an id is the store's manifest says.
    Each unique chunk is read and checked once; what is joined to the recipes is its length and CRC, so no ids are
    shuffled. A document whose chunks are missing or do not add up to its length raises.
    """
    kept = spark.read.parquet(f"{path}/manifest").select("id_bytes").first()
    chunks = spark.read.parquet(f"{path}/chunks").select("digest", "data").mapInArrow(_check_chunks(kept.id_bytes if kept else 2), "digest binary, n long, crc long")
    recipes = spark.read.schema(RECIPES).parquet(f"{path}/recipes")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = spark.read.parquet(f"{path}/manifest").select("part", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)).cast("long").alias("offset"))
    uses = recipes.select("part", "pos", F.posexplode("digests").alias("k", "digest")).join(chunks, "digest")
    rebuilt = uses.groupBy("part", "pos").agg(F.array_sort(F.collect_list(F.struct("k", "n", "crc"))).alias("c"))
    rebuilt = rebuilt.select("part", "pos", F.arrow_udf(_combined, "struct<crc: long, n: long>")("c").alias("whole"))
    rows = recipes.drop("digests", "leaf").join(rebuilt, ["part", "pos"], "left").join(offsets, "part")
    good = F.coalesce(F.col("whole.n") == F.col("n_tokens"), F.lit(False))
    crc = F.when(good, F.col("whole.crc")).otherwise(F.raise_error(F.concat(F.lit("document not whole: "), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")))).cast("long"))
    return rows.select("doc_id", (F.col("offset") + F.col("rel_start")).alias("start"), "n_tokens", crc.alias("ids_crc32"))


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, ids binary): every document's ids, rebuilt; for those who want the ids themselves. An empty store: no rows."""
    chunks = spark.read.parquet(f"{path}/chunks").select("digest", "data")
    recipes = spark.read.schema(RECIPES).parquet(f"{path}/recipes").select("part", "pos", "doc_id", F.posexplode("digests").alias("k", "digest"))
    rows = recipes.join(chunks, "digest").groupBy("part", "pos").agg(F.first("doc_id").alias("doc_id"), F.array_sort(F.collect_list(F.struct("k", "data"))).alias("c"))
    return rows.select("doc_id", F.aggregate("c", F.lit(b"").cast("binary"), lambda a, x: F.concat(a, x["data"])).alias("ids"))


