"""Language by compression: the language whose dictionary packs the text smallest, with a margin to reject by."""

from __future__ import annotations

import re
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

UNKNOWN = "und"
#: A text is packed in blocks of so many bytes, so that the dictionary counts all the way through.
BLOCK = 1 << 14
NOT_LETTERS = re.compile(r"[\W\d_]+")


@dataclass(frozen=True)
class Settings:
    """The packing level, the bounded sample that a dictionary is made of, and whether only letters are packed.

    The values are the first of cross_validate over levels 1, 3, 6, 9, samples of 100, 200, 400 and both forms.
    """

    level: int = 6
    sample_docs: int = 400
    piece_chars: int = 500
    only_letters: bool = True


def letters(text: str, only_letters: bool = True) -> str:
    """What is packed: the text in lower case, every run of other than letters as a space; or the text as it is."""
    return f" {NOT_LETTERS.sub(' ', text.lower()).strip()} " if only_letters else text


def learn_dictionaries(docs: DataFrame, settings: Settings = Settings(), id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> dict[str, bytes]:
    """A raw-content dictionary for each language of docs, from a bounded sample.

    The sample: of each language settings.sample_docs texts whose ids hash lowest, settings.piece_chars code points of each. The ids
    are picked on narrow rows, with a limit per group before the shuffle, so a hot language costs no more than others.
    The driver gets sample_docs * piece_chars characters per language: languages are a small closed set of labels.
    Rows with a null id, text or language teach nothing. No such rows: no dictionaries.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(lang_col).cast("string").alias("lang"), F.col(text_col).cast("string").alias("text"))
    rows = rows.where("id is not null and lang is not null")
    order = Window.partitionBy("lang").orderBy("h", "id")
    ids = rows.where("text is not null").select("id", "lang").withColumn("h", F.xxhash64("id")).withColumn("r", F.row_number().over(order)).where(F.col("r") <= settings.sample_docs)
    picked = sorted((r.lang, r.r, r.id) for r in ids.collect())
    wanted = sorted({i for _, _, i in picked})
    texts: dict[tuple[str, int], str] = {}
    if wanted:
        for r in rows.where(F.col("id").isin(wanted)).select("id", "lang", F.substring("text", 1, settings.piece_chars).alias("t")).where("t is not null").collect():
            key = (r.lang, r.id)
            texts[key] = max(texts.get(key, ""), r.t)
    out: dict[str, list[str]] = {}
    for lang, _, i in picked:
        if piece := texts.get((lang, i)):
            out.setdefault(lang, []).append(piece)
    return {lang: "\n".join(letters(p, settings.only_letters) for p in pieces).encode() for lang, pieces in out.items()}


class Classifier:
    """Packs with each language's dictionary; built anew in each Python worker from the plain bytes."""

    def __init__(self, dictionaries: dict[str, bytes], settings: Settings = Settings(), narrow: float = 0.01):
        self.langs, self.settings, self.narrow, self.contents = sorted(dictionaries), settings, narrow, dictionaries
        self.packers = []
        for lang in self.langs:
            content = zstandard.ZstdCompressionDict(dictionaries[lang], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            content.precompute_compress(level=settings.level)
            self.packers.append(zstandard.ZstdCompressor(level=settings.level, dict_data=content, write_checksum=False, write_content_size=False, write_dict_id=False))

    def sizes(self, text: str) -> list[int]:
        data = letters(text, self.settings.only_letters).encode("utf-8", "surrogatepass")
        return [sum(len(p.compress(data[at : at + BLOCK])) for at in range(0, len(data), BLOCK)) for p in self.packers]

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """(language, score, accepted). Score: how much smaller the best is than the next, from 0 to 1; of equal ones the
        dictionary that holds more of the text's words goes first, then the first by name."""
        if text is None or not self.langs or not any(map(str.isalpha, text)):
            return UNKNOWN, 0.0, False
        sizes = self.sizes(text)
        held = dict.fromkeys(self.langs, 0)
        if sizes.count(min(sizes)) > 1:
            words = {f" {w} ".encode("utf-8", "surrogatepass") for w in letters(text).split()}
            held = {lang: -sum(w in self.contents[lang] for w in words) for lang in self.langs}
        order = [(n, lang) for n, _, lang in sorted((n, held[lang], lang) for n, lang in zip(sizes, self.langs, strict=True))]
        score = 1.0 if len(order) == 1 else (order[1][0] - order[0][0]) / order[1][0]
        return order[0][1], score, score >= self.narrow


PREDICTION = "struct<lang: string, score: double, accepted: boolean>"


def predictor(dictionaries: dict[str, bytes], settings: Settings = Settings(), narrow: float = 0.01):
    """A column function: text to struct(lang, score, accepted); accepted is false where the margin is narrow."""
    held: list[Classifier] = []

    def run(texts: pa.Array) -> pa.Array:
        if not held:
            held.append(Classifier(dictionaries, settings, narrow))
        found = [held[0].predict(t) for t in texts.to_pylist()]
        return pa.StructArray.from_arrays([pa.array([f[i] for f in found], k) for i, k in enumerate((pa.string(), pa.float64(), pa.bool_()))], names=["lang", "score", "accepted"])

    run.__annotations__ = {"texts": pa.Array, "return": pa.Array}
    return lambda text: F.arrow_udf(run, PREDICTION)(text)


def cross_validate(docs: DataFrame, choices: list[Settings], parts: tuple[int, ...] = (0, 1, 3), id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> list[tuple[Settings, int, int]]:
    """(settings, errors, rows) of each choice, inside the learning rows alone, fewest errors first.

    Each part, a remainder of the id, is predicted from the others; rows of no part, those held out among them,
    are neither learnt from nor predicted. Of choices with equal errors the cheaper goes first: level, then sample. Rows
    without text or language don't count; no such rows: no errors in no rows.
    """
    counts = dict.fromkeys(choices, (0, 0))
    known = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull())
    for part in parts:
        rest = known.where(remainder(F.col(id_col)).isin(*(p for p in parts if p != part)))
        tried = [predictor(learn_dictionaries(rest, c, id_col, text_col, lang_col), c) for c in choices]
        wrong = [F.sum((p(F.col(text_col).cast("string"))["lang"] != F.col(lang_col)).cast("long")).alias(f"w{k}") for k, p in enumerate(tried)]
        found = known.where(in_fold(F.col(id_col), part)).agg(F.count("*").alias("n"), *wrong).first()
        for k, c in enumerate(choices):
            counts[c] = (counts[c][0] + (found[f"w{k}"] or 0), counts[c][1] + found.n)
    return sorted(((c, *counts[c]) for c in choices), key=lambda x: (x[1], x[0].level, x[0].sample_docs * x[0].piece_chars, x[0].only_letters))


def remainder(doc_id: Column, folds: int = 4) -> Column:
    """crc32 of the id's decimal text, modulo folds; null for a null id."""
    return F.crc32(doc_id.cast("string").cast("binary")) % folds


def in_fold(doc_id: Column, fold: int = 2, folds: int = 4) -> Column:
    """Whether the id falls in the held-out fold; false for a null id."""
    return F.coalesce(remainder(doc_id, folds) == fold, F.lit(False))


def identify_languages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", settings: Settings = Settings()) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, accepted) of every row, learnt from the rows that are not held out.

    Null text or no letters: `und`, score 0, not accepted; so is everything where no row has a language. A narrow
    margin keeps the prediction and clears accepted. Rows with a null id are predicted and teach nothing; they count as
    not held out. Whole texts are packed; a repeated row gets the same answer. No rows: an empty result.
    """
    held_out = in_fold(F.col(id_col))
    model = learn_dictionaries(docs.where(~held_out), settings, id_col, text_col, lang_col)
    found = docs.select(F.col(id_col).alias("doc_id"), held_out.alias("held_out"), predictor(model, settings)(F.col(text_col).cast("string")).alias("p"))
    return found.select("doc_id", "held_out", F.col("p.lang").alias("lang_pred"), F.col("p.score").alias("score"), F.col("p.accepted").alias("accepted"))
