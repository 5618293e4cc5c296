"""Licence scans by the Dice coefficient of word bigrams, with DataFrame functions only.

A text is cut into pieces at line breaks and ends of sentences; its units are runs of consecutive pieces, so that a
notice is found also where it is wrapped over lines, stands inside a paragraph, or is a whole licence file.  A text
is compared only with templates of which it has enough bigrams, and a unit only if its size is one that the
coefficient allows: for a coefficient of t, a unit's distinct bigrams number between t / (2 - t) and (2 - t) / t
times the template's.
"""

from __future__ import annotations

import math
from fractions import Fraction

import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erfocus.llm.license_texts import TEMPLATES

THRESHOLD = 0.8
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: A unit's words are at most so many times the distinct bigrams that the bounds allow it.
REPEATS = 2


def bigrams_of(text: str) -> list[str]:
    words = "".join(c if c.isascii() and c.isalnum() else " " for c in text.lower()).split()
    return list(dict.fromkeys(f"{a} {b}" for a, b in zip(words, words[1:], strict=False)))


def _words(text: Column) -> Column:
    return F.filter(F.split(F.translate(text, UPPER, UPPER.lower()), "[^0-9a-z]+"), lambda w: w != "")


def _let(value: Column, use) -> Column:
    return F.element_at(F.transform(F.array(value), use), 1)


def _bounds(n: int, threshold: float) -> tuple[int, int]:
    """Least and most bigrams of a unit that may reach the threshold with n."""
    t = Fraction(str(threshold))
    return max(1, math.ceil(n * t / (2 - t))), math.floor(n * (2 - t) / t)


def _hashed(bigrams: list[str]) -> Column:
    """The hashes that _pairs gives bigrams, as one literal: xxhash64 takes the hash of a column as the next one's seed."""
    numbers = [xxhash.xxh64_intdigest(b.encode(), xxhash.xxh64_intdigest(a.encode(), 42)) for a, b in (x.split() for x in bigrams)]
    return F.expr("array(" + ", ".join(f"{n - (n >> 63 << 64)}L" for n in numbers) + ")")


def _pairs(words: Column) -> Column:
    """A hash of each two consecutive words."""
    return F.zip_with(F.slice(words, 1, F.greatest(F.size(words) - 1, F.lit(0))), F.slice(words, 2, F.size(words)), lambda a, b: F.xxhash64(a, b))


def _ends(pieces: Column) -> Column:
    """0, and the number of words up to the end of each piece that has any."""
    sizes = F.filter(F.transform(pieces, lambda p: F.size(_words(p))), lambda n: n > 0)
    return F.aggregate(sizes, F.array(F.lit(0)), lambda acc, n: F.concat(acc, F.array(F.element_at(acc, -1) + n)))


def _best(pairs: Column, ends: Column, grams: Column, n: int, threshold: float) -> Column:
    """The highest coefficient of a run of pieces with one template; null if none is of an allowed size.

    A run that begins with a piece without any of the template's bigrams is no better than without that piece.
    """
    low, high = _bounds(n, threshold)
    starts = F.filter(F.sequence(F.lit(1), F.size(ends) - 1), lambda i: F.arrays_overlap(F.slice(pairs, F.get(ends, i - 1) + 1, F.get(ends, i) - F.get(ends, i - 1)), grams))

    def dice(own: Column) -> Column:
        size = F.size(own)
        return F.when(size.between(low, high), 2 * F.size(F.array_intersect(own, grams)) / (size + n))

    def from_(i: Column) -> Column:
        first = F.get(ends, i - 1)
        stops = F.filter(F.slice(ends, i + 1, F.lit(REPEATS * high + 1)), lambda e: (e - first - 1).between(low, REPEATS * high))
        return F.array_max(F.transform(stops, lambda e: _let(F.array_distinct(F.slice(pairs, first + 1, e - first - 1)), dice)))

    return F.array_max(F.transform(starts, from_))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, n_licensed, license, dice) of every row: templates at or over the threshold, and the best.

    Words are runs of ASCII letters and digits, lower-cased.  Null, empty and unlicensed texts have zero
    and nulls; of equal coefficients the first template counts.  A text of one piece is one unit.  Repeated
    rows each give a row; null ids are kept; an empty table gives no row; extra columns are not read.
    """
    own = {name: bigrams_of(text) for name, text in templates.items()}
    known = list(dict.fromkeys(b for grams in own.values() for b in grams))
    need = {name: _bounds(len(grams), threshold)[0] for name, grams in own.items()}
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("__text"))
    rows = rows.select("doc_id", "__text", F.explode(F.array(_pairs(_words(F.col("__text"))))).alias("__pairs"))
    rows = rows.select("*", F.explode(F.array(F.array_intersect(_hashed(known), "__pairs"))).alias("__some"))
    some = F.col("__some")
    likely = F.when(F.size(some) >= min(need.values()), F.array(*[F.size(F.array_intersect(some, _hashed(own[name]))) >= need[name] for name in own]))
    rows = rows.select("*", F.explode(F.array(likely)).alias("__likely"))
    any_ = F.coalesce(F.array_contains("__likely", True), F.lit(False))
    pieces = F.split(F.regexp_replace("__text", r"([.;:!?])[\x20\x09-\x0D]+", "$1\n"), "\n")
    rows = rows.select("doc_id", "__pairs", "__likely", F.explode(F.array(F.when(any_, _ends(pieces)))).alias("__ends"))
    found = [
        F.when(F.get("__likely", F.lit(i)), F.struct(_best(F.col("__pairs"), F.col("__ends"), _hashed(grams), len(grams), threshold).alias("dice"), F.lit(-i).alias("order"), F.lit(name).alias("license")))
        for i, (name, grams) in enumerate(own.items())
    ]
    found = F.when(F.col("__ends").isNotNull(), F.filter(F.array(*found), lambda s: s["dice"] >= threshold))
    rows = rows.select("doc_id", F.explode(F.array(found)).alias("__found"))
    best = F.array_max("__found")
    return rows.select("doc_id", F.coalesce(F.when(F.col("__found").isNotNull(), F.size("__found")), F.lit(0)).cast("long").alias("n_licensed"), best["license"].alias("license"), F.round(best["dice"], 6).alias("dice"))


def scan_sql(templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> str:
    """The same in SQL, by brute force over all runs of pieces of texts that have enough of a template's bigrams."""
    rows = ", ".join("({}, '{}', [{}], {}, {})".format(i, name, ", ".join(f"'{b}'" for b in bigrams_of(text)), *_bounds(len(bigrams_of(text)), threshold)) for i, (name, text) in enumerate(templates.items()))
    lower = f"translate(coalesce(text, ''), '{UPPER}', '{UPPER.lower()}')"
    return rf"""
WITH t(k, license, grams, low, high) AS (VALUES {rows}),
u AS (SELECT row_number() OVER () AS r, doc_id, {lower} AS text FROM documents),
p AS (SELECT r, doc_id, list_filter(list_transform(string_split(regexp_replace(text, '([.;:!?])[ 	-
]+', '' || chr(10), 'g'), chr(10)),
      lambda x: list_filter(regexp_split_to_array(x, '[^0-9a-z]+'), lambda y: y <> '')), lambda x: len(x) > 0) AS pieces FROM u),
w AS (SELECT r, flatten(pieces) AS ws, list_transform(range(0, len(pieces) + 1), lambda i: coalesce(list_sum(list_transform(pieces[1:i], lambda x: len(x))), 0)::BIGINT) AS ends FROM p WHERE len(pieces) > 0),
b AS (SELECT r, ends, list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) AS grams FROM w),
c AS (SELECT r, ends, b.grams AS own, k, license, t.grams AS grams, low, high FROM b, t WHERE len(list_intersect(b.grams, t.grams)) >= low),
s AS (SELECT *, unnest(range(1, len(ends))) AS i FROM c),
e AS (SELECT *, unnest(range(i + 1, len(ends) + 1)) AS j FROM s),
n AS (SELECT r, k, license, grams, low, high, list_distinct(own[ends[i] + 1:ends[j] - 1]) AS run FROM e WHERE ends[j] - ends[i] - 1 BETWEEN low AND {REPEATS} * high),
d AS (SELECT r, k, license, max(2 * len(list_intersect(run, grams)) / (len(run) + len(grams))) AS dice FROM n WHERE len(run) BETWEEN low AND high GROUP BY r, k, license),
m AS (SELECT r, count(*) AS n, max(dice) AS dice, arg_max(license, (dice, -k)) AS license FROM d WHERE dice >= {threshold} GROUP BY r)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_licensed, license, round(dice, 6) AS dice FROM u LEFT JOIN m USING (r)
"""
