"""Tokens and student features, written so that SQL engines agree on them."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BLANK = r"[ \t\n\r]+"


def tokens(text: Column) -> Column:
    """White-space tokens; null and blank texts have none."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), BLANK), lambda t: t != "")


def letters_only(token: Column) -> Column:
    """Lower case, everything outside a-z removed."""
    return F.regexp_replace(F.lower(token), "[^a-z]", "")


def shape(text: Column) -> Column:
    """Each token's form: runs of capitals, small letters and digits become one mark each; other ASCII stays."""
    for pattern, mark in (("[^ -~]", ""), ("[A-Z]+", "^"), ("[a-z]+", "L"), ("[0-9]+", "D")):
        text = F.regexp_replace(text, pattern, mark)
    return text


def feature_line(text: Column) -> Column:
    """Words and shapes of a snippet as one space-separated line; a student sees the set of its pieces."""
    return F.concat(F.lower(text), F.lit(" "), shape(text))


def features(text: Column) -> Column:
    return F.filter(F.array_distinct(F.split(feature_line(text), " ")), lambda t: t != "")
