"""Personal data in texts: patterns propose spans, checksums confirm them, context words move the score."""

from __future__ import annotations

import re
from bisect import bisect_right
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import groupby

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import per_text

LOCAL, DOMAIN = re.compile(r"[A-Za-z0-9._%+-]+"), re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL_CHARS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DIGIT, SEPARATORS = re.compile("[0-9]"), re.compile(r"[\x20().-]")
ACCEPT = 0.5
#: Code points before a span in which a context word raises its score.
NEAR = 48


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def mod97(account: str) -> bool:
    """The check of an international bank account number."""
    turned = account[4:] + account[:4]
    return int("".join(str(int(c, 36)) for c in turned)) % 97 == 1


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches of local part, at sign, dotted domain; time in proportion to the text, whatever it holds."""
    done = at = 0
    while (at := text.find("@", at)) >= 0:
        start = at
        while start > done and text[start - 1] in LOCAL_CHARS:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            yield start, m.end()
            done = at = m.end()
        else:
            at += 1
            done = at


IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}(?![A-Za-z0-9])")


def ibans(text: str) -> Iterator[tuple[int, int]]:
    """Runs of account form; where the whole one fails its check, the longest that ends at a space before and passes."""
    at = 0
    while m := IBAN.search(text, at):
        start, end = m.span()
        at = end
        while end - start >= 15:
            if mod97(text[start:end].replace(" ", "")):
                yield start, end
                at = end
                break
            end = text.rfind(" ", start, end)


def _spans(pattern: str) -> Callable[[str], Iterator[tuple[int, int]]]:
    compiled = re.compile(pattern)
    return lambda text: (m.span() for m in compiled.finditer(text))


def _digits(s: str) -> str:
    return "".join(DIGIT.findall(s))


@dataclass(frozen=True)
class Recogniser:
    kind: str
    find: Callable[[str], Iterator[tuple[int, int]]]
    valid: Callable[[str], bool]
    score: float
    context: tuple[str, ...] = ()
    boost: float = 0.4


#: The patterns of the base kinds. A digit before a run's start can't begin another match: that keeps scans linear.
BASE = (
    Recogniser("email", emails, lambda s: True, 0.9),
    Recogniser("ip", _spans(r"(?<![0-9])[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)"), lambda s: all(len(p.lstrip("0")) <= 3 and int(p[-9:]) <= 255 for p in s.split(".")), 0.8),
    Recogniser("card", _spans(r"[0-9](?:[\x20-]?[0-9])+"), lambda s: 13 <= len(d := _digits(s)) <= 19 and luhn(d), 0.8),
    Recogniser("phone", _spans(r"\+[0-9][\x20().0-9-]+[0-9]"), lambda s: 9 <= len(_digits(s)) <= 15, 0.7),
)
MORE = (
    Recogniser("iban", ibans, lambda s: 15 <= len(s.replace(" ", "")) <= 34, 0.8, ("iban", "account", "konto", "compte", "cuenta"), 0.2),
    Recogniser("secret", _spans(r"(?<![A-Za-z0-9])[A-Fa-f0-9]{32,128}(?![A-Za-z0-9])"), lambda s: not s.isdigit(), 0.3, ("token", "secret", "key", "password", "passwd", "credential", "auth")),
    Recogniser("national_id", _spans(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"), lambda s: s[:3] not in ("000", "666") and s[0] != "9" and s[4:6] != "00" and s[7:] != "0000", 0.3, ("ssn", "social security", "tax id")),
    Recogniser("local_phone", _spans(r"(?<![0-9+().-])\(?[0-9]{2,5}\)?(?:[\x20.-][0-9]{2,4}){2,4}(?![0-9])"), lambda s: 9 <= len(_digits(s)) <= 15, 0.2, ("phone", "tel", "call", "mobile", "fax", "telefon", "téléphone", "teléfono")),
)
KINDS = tuple(r.kind for r in BASE + MORE)
WORD = re.compile(r"[^\W\d_]+")


def _score(text: str, r: Recogniser, start: int) -> float:
    if not r.context:
        return r.score
    before = text[max(0, start - NEAR) : start].lower()
    words = set(WORD.findall(before))
    return r.score + r.boost * any(c in before if " " in c else c in words for c in r.context)


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Sorted spans with those that overlap joined."""
    out: list[tuple[int, int]] = []
    for s, e in spans:
        if out and s < out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


def find_spans(text: str | None) -> list[tuple[str, int, int, float]]:
    """(kind, start, end, score) in code points, by kind as in KINDS and then start.

    Each base kind gives its leftmost matches that pass its check, whatever other kinds find. Any other kind gives
    matches that pass its check, reach ACCEPT with their context, and lie clear of base spans and of better ones. Time is
    that of sorting the spans found, however long the text. Null and empty texts have no spans.
    """
    if not text:
        return []
    digits = DIGIT.search(text) is not None
    found = [(r.kind, s, e, r.score) for r in BASE if digits or r.kind == "email" for s, e in r.find(text) if r.valid(text[s:e])]
    if digits:
        extra = [(-score, s, e, r.kind) for r in MORE for s, e in r.find(text) if r.valid(text[s:e]) and (score := _score(text, r, s)) >= ACCEPT]
        taken = _merged(sorted((s, e) for _, s, e, _ in found))
        for score, of_score in groupby(sorted(extra), key=lambda x: x[0]):  # a few scores; of equal ones the first in the text
            starts, last, new = [s for s, _ in taken], -1, []
            for _, s, e, kind in of_score:
                k = bisect_right(starts, s)
                if s >= last and (k == 0 or taken[k - 1][1] <= s) and (k == len(taken) or e <= taken[k][0]):
                    new.append((s, e))
                    found.append((kind, s, e, -score))
                    last = e
            taken = _merged(sorted([*taken, *new]))
    return sorted(found, key=lambda x: (KINDS.index(x[0]), x[1]))


def redact_text(text: str | None) -> str | None:
    """The text with every span replaced by its kind in angle brackets; overlapping spans become one."""
    spans = sorted((s, -e, k) for k, s, e, _ in find_spans(text))
    if not spans:
        return text
    out, at, end = [], 0, -1
    for s, e, kind in spans:
        if s < end:
            end = max(end, -e)
            continue
        out += [text[at if end < 0 else end : s], f"<{kind.upper()}>"]
        end = -e
    return "".join([*out, text[end:]])


SPAN_KIND = "array<struct<kind: string, start: int, end: int, score: double>>"
SPAN_ARROW = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64())]))
spans_of = per_text(lambda t: [dict(zip(("kind", "start", "end", "score"), s, strict=True)) for s in find_spans(t)], SPAN_KIND, SPAN_ARROW)
redacted = per_text(redact_text, "string", pa.string())


def pii_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, spans) of every row; null and empty texts have no spans. Nothing is shuffled; each text is scanned whole."""
    return docs.select(F.col(id_col).alias("doc_id"), spans_of(F.col(text_col).cast("string")).alias("spans"))


def redact(docs: DataFrame, text_col: str = "text", chars_col: str | None = "n_chars") -> DataFrame:
    """docs with personal data in its text replaced; a null text stays null, all other columns stay as they are.

    chars_col, where docs has it, is set to the new length of texts that changed.
    """
    out = docs.withColumn(text_col, redacted(F.col(text_col).cast("string")))
    if chars_col and chars_col in docs.columns:
        out = out.withColumn(chars_col, F.when(F.col(text_col).isNull(), F.col(chars_col)).otherwise(F.length(text_col)).cast(docs.schema[chars_col].dataType))
    return out


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def pii_digest(docs: DataFrame) -> DataFrame:
    """The counts and digests of the query contract, from pii_spans: a row for each of docs, repeated or without an id too;
    null and empty texts have counts of zero and the digest of nothing."""
    base = F.filter("spans", lambda s: s["kind"].isin(*(r.kind for r in BASE)))
    of_kind = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")
    counts = [of_kind(r.kind).alias(f"n_{r.kind}") for r in BASE]
    return pii_spans(docs).select("doc_id", *counts, F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))
