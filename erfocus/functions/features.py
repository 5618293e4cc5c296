"""Pairwise features as integer-weighted predicates on two prepared mentions.

A side is a struct with m (normal string), toks, ctx (distinct context words) and kw (keywords).  Weights are
integers, so scores do not depend on the order of summation.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from erfocus.functions.strings import normal, tokens

LEVELS = ("none", "paragraph", "document")


#: The weights of similarity from a tier on, highest first, and below the last.
TIERS = ((0.99, 120), (0.90, 105), (0.80, 80), (0.70, 55), (0.60, 35), (0.50, 15), (0.40, -5), (0.30, -50), (0.20, -80))
LOWEST_TIER = -100


@dataclass(frozen=True)
class FeatureSpec:
    name: str
    plus: int
    minus: int
    klass: str
    what: str
    tiers: tuple[tuple[float, int], ...] = TIERS
    lowest: int = LOWEST_TIER


#: Weights by feature (holds / does not).
SPECS = (
    FeatureSpec("f01", 20, -15, "token", "same string"),
    FeatureSpec("f02", 5, 0, "token", "same first character"),
    FeatureSpec("f03", 3, 0, "token", "same second character"),
    FeatureSpec("f04", 0, 0, "token", "same later character"),
    FeatureSpec("f05", 30, -150, "token", "one contains the other"),
    FeatureSpec("f06", 10, 0, "token", "same length"),
    FeatureSpec("f07", 90, -3, "token", "same first term"),
    FeatureSpec("f08", 0, 0, "pair", "similarity tier"),
    FeatureSpec("f09", 20, 0, "pair", "matching terms"),
    FeatureSpec("f10", 1, 0, "pair", "token in the other's context"),
    FeatureSpec("f11", 700, -10, "pair", "keyword in the context"),
    FeatureSpec("f12", 70, 0, "pair", "keyword in a token"),
    FeatureSpec("f13", 0, -500, "pair", "extra token on both sides"),
    FeatureSpec("f14", 10, 0, "pair", "common context word"),
    FeatureSpec("f15", 100, -5, "entity", "similar neighbour in the entity"),
    FeatureSpec("f16", 350, -15, "entity", "same document in the entity"),
)
#: The example of an entity-wide count: each equal string between two entities that become one; off unless asked for.
MATCHING_STRINGS = FeatureSpec("f17", 0, 0, "entity", "matching strings of two entities")

BY_NAME = {s.name: s for s in SPECS}
PAIRWISE = tuple(s for s in SPECS if s.klass != "entity")
#: For short names with initials, joined or dropped letters, where differing tokens say little.
SHORT_NAMES = tuple(BY_NAME[n] for n in ("f01", "f02", "f03", "f06", "f07", "f08", "f09", "f11", "f12", "f14"))


def weighted(specs: Iterable[FeatureSpec], **changes: tuple[int, int]) -> tuple[FeatureSpec, ...]:
    """Specs with other weights: weighted(SPECS, f07=(40, -3))."""
    return tuple(replace(s, plus=changes[s.name][0], minus=changes[s.name][1]) if s.name in changes else s for s in specs)


#: The same, hand-tuned for two-word names whose words each belong to many entities.
TWO_WORD_NAMES = weighted(SHORT_NAMES, f01=(60, -15), f07=(30, -3))

#: For the worked example: common context words count most, strings little.
CONTEXT_FIRST = weighted((s for s in SHORT_NAMES if s.name != "f08"), f14=(150, -120))


def weight_table(spark: SparkSession, specs: Iterable[FeatureSpec] = SPECS) -> DataFrame:
    return spark.createDataFrame([(s.name, s.plus, s.minus, s.klass, s.what) for s in specs], "feature string, w_pos int, w_neg int, klass string, what string")


def prepare(mentions: DataFrame, level: str = "document", name: str = "side") -> DataFrame:
    """mentions with a side struct; level none has no context words."""
    if level not in LEVELS:
        raise ValueError(f"level {level} is none of {LEVELS}")
    ctx = F.array().cast("array<string>") if level == "none" else F.coalesce(F.array_distinct(F.col(f"context.{level}")), F.array().cast("array<string>"))
    kw = F.coalesce(F.col("context.keywords"), F.array().cast("array<string>"))
    return mentions.withColumn(name, F.struct(normal(F.col("mention")).alias("m"), F.coalesce(tokens(F.col("mention")), F.array().cast("array<string>")).alias("toks"), ctx.alias("ctx"), kw.alias("kw")))


def _shared(x: Column, y: Column) -> Column:
    return F.arrays_overlap(x, y)


def _kw_match(a: Column, b: Column) -> Column:
    return _shared(b["kw"], a["ctx"]) | _shared(a["kw"], b["ctx"])


def _has_kw(a: Column, b: Column) -> Column:
    return (F.size(a["kw"]) > 0) | (F.size(b["kw"]) > 0)


def _second(x: Column) -> Column:
    return F.substring(x, 2, 1)


PREDICATES: dict[str, Callable[[Column, Column], Column]] = {
    "f01": lambda a, b: a["m"] == b["m"],
    "f02": lambda a, b: F.substring(a["m"], 1, 1) == F.substring(b["m"], 1, 1),
    "f03": lambda a, b: (_second(a["m"]) == _second(b["m"])) & (_second(a["m"]) != ""),
    "f04": lambda a, b: F.substring(a["m"], 3, 1) == F.substring(b["m"], 3, 1),
    "f05": lambda a, b: a["m"].contains(b["m"]) | b["m"].contains(a["m"]),
    "f06": lambda a, b: F.char_length(a["m"]) == F.char_length(b["m"]),
    "f07": lambda a, b: F.get(a["toks"], F.lit(0)) == F.get(b["toks"], F.lit(0)),
    "f09": lambda a, b: _shared(a["toks"], b["toks"]),
    "f10": lambda a, b: _shared(a["toks"], b["ctx"]) | _shared(b["toks"], a["ctx"]),
    "f12": lambda a, b: F.exists(b["kw"], lambda k: a["m"].contains(k)) | F.exists(a["kw"], lambda k: b["m"].contains(k)),
    "f13": lambda a, b: (F.size(F.array_except(a["toks"], b["toks"])) > 0) & (F.size(F.array_except(b["toks"], a["toks"])) > 0),
    "f14": lambda a, b: _shared(a["ctx"], b["ctx"]),
}


def tier(similarity: Column, tiers: tuple[tuple[float, int], ...] = TIERS, lowest: int = LOWEST_TIER) -> Column:
    """The weight of the highest tier reached; similarities are rounded first, so that engines agree at the edges.

    A null similarity, of a side without context, has no weight.
    """
    s = F.round(similarity, 9)
    out = F.when(s.isNull(), 0)
    for least, weight in tiers:
        out = out.when(s >= least, weight)
    return out.otherwise(lowest)


def value(spec: FeatureSpec, a: Column, b: Column, similarity: Column) -> Column:
    """A feature's weight for a pair; f13's stands for the predicate that holds."""
    if spec.name == "f08":
        return tier(similarity, spec.tiers, spec.lowest)
    if spec.name == "f11":
        return F.when(_has_kw(a, b), F.when(F.coalesce(_kw_match(a, b), F.lit(False)), spec.plus).otherwise(spec.minus)).otherwise(0)
    holds = F.coalesce(PREDICATES[spec.name](a, b), F.lit(False))
    if spec.name == "f13":
        return F.when(holds, spec.minus).otherwise(spec.plus)
    return F.when(holds, spec.plus).otherwise(spec.minus)


def total(specs: Iterable[FeatureSpec], a: Column, b: Column, similarity: Column) -> Column:
    """The pair's weight; features without weight, or that cannot hold, are left out of the expression."""
    out = F.lit(0)
    for s in specs:
        if s.klass != "entity" and (s.name == "f08" or s.plus or s.minus):
            out = out + value(s, a, b, similarity)
    return out.cast("long")


def text_similarity(a: Column, b: Column, q: int = 3) -> Column:
    """Jaccard of q-grams of the strings, for tiers without context statistics."""
    from erfocus.functions.strings import qgrams

    return gram_similarity(qgrams(a["m"], q), qgrams(b["m"], q))


def gram_similarity(x: Column, y: Column) -> Column:
    """Jaccard of two strings' q-grams: for joins, where a side's grams are worked out once and not for each pair."""
    common = F.size(F.array_intersect(x, y))
    return common / (F.size(x) + F.size(y) - common)
