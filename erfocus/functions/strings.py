"""Text expressions of blocking and features."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def normal(text: Column) -> Column:
    return F.lower(F.trim(text))


def tokens(text: Column) -> Column:
    """Runs of lower-cased ASCII letters and digits, in order."""
    return F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda w: w != "")


def qgrams(text: Column, q: int = 3) -> Column:
    """Distinct q-grams of the normalised text, padded at both ends; null gives null."""
    padded = F.concat(F.lit("#" * (q - 1)), normal(text), F.lit("$" * (q - 1)))
    at = F.sequence(F.lit(1), F.char_length(padded) - F.lit(q - 1))
    return F.array_distinct(F.transform(at, lambda i: F.substring(padded, i, F.lit(q))))


def py_qgrams(text: str, q: int = 3) -> set[str]:
    padded = "#" * (q - 1) + text.strip(" ").lower() + "$" * (q - 1)
    return {padded[i : i + q] for i in range(len(padded) - q + 1)}


def py_tokens(text: str) -> list[str]:
    import re

    return [w for w in re.split("[^a-z0-9]+", text.lower()) if w]
