"""Quality rules whose cutoffs are chosen with a bound on the good texts they reject.

All counts of a text are made in its own row with built-in functions; nothing but counts by stratum,
label and rules' candidate cutoffs leaves the executors.
"""

from __future__ import annotations

import math
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erfocus.llm.kinds import unused
from erfocus.operators.durable import cut, held

MIN_WORDS = 50
#: Share of good texts that all rules together may reject in a stratum, and the chance of an error there.
ALPHA = 0.01
DELTA = 0.05
#: Candidate cutoffs: a text fails a rule if its measure is over the cutoff.  Each rule's candidates go
#: from the strictest to the mildest; texts are labelled, so that the grids may be the same for all data.
RULES = {
    "symbol_share": (0.02, 0.05, 0.1, 0.2, 0.4),
    "dup_line_share": (0.1, 0.2, 0.3, 0.5, 0.7),
    "repeat_share": (0.1, 0.2, 0.3, 0.4),
    "word_length": (8.0, 10.0, 12.0, 16.0, 24.0),
    "short_words": (0.35, 0.45, 0.6, 0.8),
}
SPACE = r"[\x20\x09-\x0D]"
MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]


def let(value: Column, use) -> Column:
    """use(value), with value computed once also where use has it in a lambda."""
    return F.element_at(F.transform(F.array(value), use), 1)


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), SPACE + "+"), lambda x: x != "")


def _repeated(words: Column) -> Column:
    """Words inside three-word windows that are in the text twice or more."""
    n = F.size(words)

    def covered(at: Column) -> Column:
        step = F.zip_with(at, F.slice(at, 2, F.size(at)), lambda a, b: F.when(b.isNull(), F.lit(3)).otherwise(F.least(F.lit(3), b - a)))
        return F.aggregate(step, F.lit(0).cast("long"), lambda acc, x: acc + x)

    def twice(grams: Column) -> Column:
        """Of (hash, place) in order, the places of those that have the hash before or after them."""
        m = F.size(grams)
        same = F.filter(grams, lambda g, i: ((i > 0) & (F.get(grams, i - 1)["h"] == g["h"])) | ((i < m - 1) & (F.get(grams, i + 1)["h"] == g["h"])))
        return F.sort_array(F.transform(same, lambda g: g["i"]))

    grams = F.sort_array(F.transform(F.slice(words, 1, F.greatest(n - 2, F.lit(0))), lambda w, i: F.struct(F.xxhash64(w, F.get(words, i + 1), F.get(words, i + 2)).alias("h"), i.alias("i"))))
    return F.when(n < 4, F.lit(0).cast("long")).otherwise(let(let(grams, twice), covered))


def measures(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *keep: str) -> DataFrame:
    """(doc_id, kept columns, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_short_words, n_lines).

    Words are what lies between ASCII white space.  Null and empty texts have zeros; repeated rows
    each give a row.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    of_lines = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    of_words = let(
        words_of(F.col(text_col)),
        lambda w: F.struct(
            F.size(w).cast("long").alias("n_words"),
            F.aggregate(w, F.lit(0).cast("long"), lambda acc, x: acc + F.char_length(x)).alias("word_chars"),
            F.size(F.filter(w, lambda x: F.char_length(x) <= 2)).cast("long").alias("n_short_words"),
            _repeated(w).alias("n_repeat_words"),
        ),
    )
    n_symbols = (F.char_length(text) - F.char_length(F.translate(text, "#*$%&|<>", ""))).cast("long")
    # inline() keeps the optimiser from working out the measures again wherever they are used.
    rows = docs.select(F.col(id_col).alias("doc_id"), *keep, text_col, F.inline(F.array(of_words)))
    rows = rows.select("*", F.inline(F.array(of_lines)))
    return rows.select("*", F.explode(F.array(n_symbols)).alias("n_symbols")).select("doc_id", *keep, *MEASURES, "n_short_words", "n_lines")


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def _share(a: Column, b: Column) -> Column:
    return F.when(b > 0, a / b).otherwise(F.lit(0.0))


def rule_values() -> dict[str, Column]:
    n = F.col("n_words")
    return {
        "symbol_share": _share(F.col("n_symbols"), F.col("word_chars")),
        "dup_line_share": _share(F.col("n_dup_lines"), F.col("n_lines")),
        "repeat_share": _share(F.col("n_repeat_words"), n),
        "word_length": _share(F.col("word_chars"), n),
        "short_words": _share(F.col("n_short_words"), n),
    }


def tail(k: int, n: int, p: float) -> float:
    """P(X <= k) of the binomial distribution of n draws at p."""
    if k >= n:
        return 1.0
    log = [math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(p) + (n - i) * math.log1p(-p) for i in range(k + 1)]
    top = max(log)
    return min(1.0, math.exp(top) * math.fsum(math.exp(x - top) for x in log))


def steps(bad: Counter, rules: dict = RULES) -> list:
    """The sequence of (rule, cutoff) in which a stratum's rules are tightened, by its labelled bad texts alone.

    All rules are off at first; every rule takes its mildest cutoff, then every rule its next, those that reject
    most bad texts first.  A step that rejects no further bad text is left out.
    """
    grids, at, out = {r: sorted(g, reverse=True) for r, g in rules.items()}, dict.fromkeys(rules, 0), []
    gone = rejected(bad, at)
    for depth in range(1, max(map(len, grids.values()), default=0) + 1):
        open_ = [r for r, g in grids.items() if len(g) >= depth]
        for rule in sorted(open_, key=lambda r: -rejected(bad, dict.fromkeys(rules, 0) | {r: depth})):
            more = rejected(bad, at | {rule: depth})
            if more > gone:
                at[rule], gone = depth, more
                out.append((rule, grids[rule][depth - 1]))
    return out


def rejected(cells: Counter, at: dict) -> int:
    """Texts that a configuration rejects; cells: {the mildest step of each rule that rejects the text: texts}."""
    return sum(n for cell, n in cells.items() if any(step >= first for step, first in zip(at.values(), cell, strict=True)))


def choose(counts: dict, strata: list, alpha: float = ALPHA, delta: float = DELTA, rules: dict = RULES, order: dict | None = None) -> dict:
    """{(stratum, rule): cutoff} from {(stratum, rule, cutoff): (good texts rejected, good texts)}.

    Each stratum's steps are taken in its order (by default from each rule's mildest cutoff on), and the count of a
    step is of good texts that all rules together reject after it.  So each test is of the whole configuration against
    the whole of alpha, by the exact binomial tail at delta over the number of strata; tests end with the first that
    does not pass.  A fixed sequence needs no more correction, as the order does not depend on the good texts.
    """
    level, chosen = delta / max(1, len(strata)), {}
    for s in strata:
        for rule, cutoff in [(r, c) for r, g in rules.items() for c in sorted(g, reverse=True)] if order is None else order[s]:
            k, n = counts.get((s, rule, cutoff), (0, 0))
            if not n or tail(k, n, alpha) > level:
                break
            chosen[s, rule] = cutoff
    return chosen


def calibrate(measured: DataFrame, labels: DataFrame, stratum: str, id_col: str = "doc_id", good: str = "quality", alpha: float = ALPHA, delta: float = DELTA) -> dict:
    """Cutoffs from all labelled texts that pass the base rules.

    Labels with null ids or labels are not used; a document labelled twice is good if every label is good.
    What comes to the driver are counts by stratum, label and each rule's mildest rejecting cutoff.
    """
    marks = labels.select(F.col(id_col).alias("doc_id"), F.col(good).alias("__good")).where("doc_id IS NOT NULL AND __good IS NOT NULL").groupBy("doc_id").agg((F.min("__good") == 1).alias("__good"))
    held = measured.where(~base_failed()).join(marks, "doc_id")
    values = rule_values()
    first = [sum((F.when(values[r] > c, 0).otherwise(1) for c in grid), F.lit(1)).alias(f"__{r}") for r, grid in RULES.items()]
    cells: dict = {}
    for row in held.groupBy(F.col(stratum).alias("__s"), "__good", *first).count().toLocalIterator():
        cells.setdefault(row["__s"], (Counter(), Counter()))[row["__good"]][tuple(row[f"__{r}"] for r in RULES)] += row["count"]
    strata = [s for s, (_, fine) in cells.items() if fine]
    order = {s: steps(cells[s][0]) for s in strata}
    counts = {}
    for s in strata:
        at, fine = dict.fromkeys(RULES, 0), cells[s][1]
        for rule, cutoff in order[s]:
            at[rule] = sorted(RULES[rule], reverse=True).index(cutoff) + 1
            counts[s, rule, cutoff] = (rejected(fine, at), fine.total())
    return choose(counts, strata, alpha, delta, order=order)


def verdict(cutoffs: dict, stratum: str) -> Column:
    """True for texts that pass the base rules and every rule on in their stratum."""
    values, failed = rule_values(), F.lit(False)
    for (s, rule), cutoff in cutoffs.items():
        failed = failed | (F.col(stratum).eqNullSafe(F.lit(s)) & (values[rule] > cutoff))
    return ~base_failed() & ~failed


def judge(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum: str = "lang") -> DataFrame:
    """(doc_id, the measures, base_failed, kept) of every row.

    Without labelled good texts of a stratum (also the null one), or with too few of them for a bound, only the
    base rules act there: ALPHA, DELTA and four strata take 436 without a rejected one.  Extra columns of
    the texts are not read.
    """
    measured, cutoffs = _measured(docs, labels, id_col, text_col, stratum)
    return measured.select("doc_id", *MEASURES, base_failed().alias("base_failed"), verdict(cutoffs, "__stratum").alias("kept"))


def _measured(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, stratum: str) -> tuple[DataFrame, dict]:
    """Every row's measures, taken in one pass over the texts and kept, and the cutoffs that they give."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text"), F.col(stratum).alias("__stratum"), F.xxhash64(F.col(text_col)).alias("__key"))
    measured = cut(measures(rows, "doc_id", "__text", "__stratum", "__key"))
    return measured, calibrate(measured, labels, "__stratum")


def kept_documents(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", stratum: str = "lang") -> DataFrame:
    """The rows of docs whose texts pass, with all their columns.

    Texts are measured once; rows are then taken out by id, text hash and stratum of those that failed.  Null and
    empty texts fail the base rules; repeated rows fare alike; columns of any names are kept.
    """
    measured, cutoffs = _measured(docs, labels, id_col, text_col, stratum)
    own, key, part = unused(docs.columns, "__id", "__key", "__stratum")
    failed = measured.where(~verdict(cutoffs, "__stratum")).select(F.col("doc_id").alias(own), F.col("__key").alias(key), F.col("__stratum").alias(part)).distinct()
    here = F.col(id_col).eqNullSafe(F.col(own)) & F.xxhash64(F.col(text_col)).eqNullSafe(F.col(key)) & F.col(stratum).eqNullSafe(F.col(part))
    return docs.join(held(failed), here, "left_anti")


def judge_sql(rules: dict = RULES, alpha: float = ALPHA, delta: float = DELTA) -> str:
    """What judge() returns for documents and labels, by a recursion over each stratum's steps."""
    value = {
        "symbol_share": "CASE WHEN word_chars > 0 THEN n_symbols / word_chars ELSE 0 END",
        "dup_line_share": "CASE WHEN n_lines > 0 THEN n_dup_lines / n_lines ELSE 0 END",
        "repeat_share": "CASE WHEN n_words > 0 THEN n_repeat_words / n_words ELSE 0 END",
        "word_length": "CASE WHEN n_words > 0 THEN word_chars / n_words ELSE 0 END",
        "short_words": "CASE WHEN n_words > 0 THEN n_short_words / n_words ELSE 0 END",
    }
    grids = {r: sorted(g, reverse=True) for r, g in rules.items()}
    first = ", ".join(f"{len(g) + 1} - len(list_filter({g}, lambda c: v_{r} > c)) AS c_{r}" for r, g in grids.items())
    hit = lambda at: " OR ".join(f"{at[r]} >= x.c_{r}" for r in grids)
    lost = lambda cells, at: f"coalesce(list_sum(list_transform({cells}, lambda x: CASE WHEN {hit(at)} THEN x.n ELSE 0 END)), 0)::BIGINT"
    moved = {r: f"CASE WHEN q.rule = '{r}' THEN q.depth ELSE a_{r} END" for r in grids}
    ranks = " UNION ALL ".join(
        f"SELECT s, '{r}' AS rule, {i} AS place, {d} AS depth, coalesce(sum(n) FILTER (NOT good AND c_{r} <= {d}), 0) AS lost FROM cells GROUP BY s" for i, (r, g) in enumerate(grids.items()) for d in range(1, len(g) + 1)
    )
    cell = "{'n': n, " + ", ".join(f"'c_{r}': c_{r}" for r in grids) + "}"
    terms = f"list_transform(range(0, k + 1), lambda i: exp(lgamma(total + 1) - lgamma(i + 1) - lgamma(total - i + 1) + i * ln({alpha}) + (total - i) * ln(1 - {alpha})))"
    over = " OR ".join(f"(a_{r} > 0 AND v_{r} > {g}[greatest(a_{r}, 1)])" for r, g in grids.items())
    return rf"""
WITH RECURSIVE d AS (SELECT row_number() OVER () AS r, doc_id, lang, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, doc_id, lang, list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
      list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls, length(t) - length(translate(t, '#*$%&|<>', '')) AS n_symbols FROM d),
g AS (SELECT r, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS gram FROM (SELECT r, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
often AS (SELECT r, i FROM (SELECT *, count(*) OVER (PARTITION BY r, gram) AS n FROM g) WHERE n > 1),
rep AS (SELECT r, count(DISTINCT p) AS n FROM (SELECT r, unnest([i, i + 1, i + 2]) AS p FROM often) GROUP BY r),
m0 AS (SELECT w.r, doc_id, lang, len(ws)::BIGINT AS n_words, coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
      (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(n, 0)::BIGINT AS n_repeat_words, len(list_filter(ws, lambda x: length(x) <= 2)) AS n_short_words, len(ls) AS n_lines
      FROM w LEFT JOIN rep USING (r)),
m AS (SELECT *, n_words < {MIN_WORDS} OR 100 * n_repeat_words > 50 * n_words AS base_failed, {", ".join(f"({v})::DOUBLE AS v_{r}" for r, v in value.items())} FROM m0),
marks AS (SELECT doc_id, min(quality) = 1 AS good FROM labels WHERE doc_id IS NOT NULL AND quality IS NOT NULL GROUP BY doc_id),
cells AS (SELECT lang AS s, good, {", ".join(f"c_{r}" for r in grids)}, count(*)::BIGINT AS n FROM (SELECT lang, good, {first} FROM m JOIN marks USING (doc_id) WHERE NOT base_failed) GROUP BY ALL),
strata AS (SELECT s, list({cell}) FILTER (good) AS fine, list({cell}) FILTER (NOT good) AS bad, (sum(n) FILTER (good))::BIGINT AS total, {delta} / count(*) OVER () AS level FROM cells GROUP BY s HAVING count(*) FILTER (good) > 0),
seq AS (SELECT s, rule, depth, row_number() OVER (PARTITION BY s ORDER BY depth, lost DESC, place) AS t FROM ({ranks})),
walk AS (
SELECT s, 0::BIGINT AS t, {", ".join(f"0 AS a_{r}, 0 AS b_{r}" for r in grids)}, 0::BIGINT AS gone, true AS live FROM strata
UNION ALL SELECT s, next, {", ".join(f"CASE WHEN more > gone THEN n_{r} ELSE a_{r} END, CASE WHEN more > gone AND passes THEN n_{r} ELSE b_{r} END" for r in grids)}, greatest(more, gone), live AND (more <= gone OR passes)
FROM (SELECT *, live AND list_sum({terms}) <= level AND k < total AS passes FROM (SELECT *, {lost("fine", {r: f"n_{r}" for r in grids})} AS k, {lost("bad", {r: f"n_{r}" for r in grids})} AS more
      FROM (SELECT walk.*, q.t AS next, fine, bad, total, level, {", ".join(f"{v} AS n_{r}" for r, v in moved.items())}
            FROM walk JOIN seq q ON q.s IS NOT DISTINCT FROM walk.s AND q.t = walk.t + 1 JOIN strata ON strata.s IS NOT DISTINCT FROM walk.s)))),
cut AS (SELECT s, {", ".join(f"b_{r} AS a_{r}" for r in grids)} FROM walk WHERE t = (SELECT max(t) FROM walk))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT coalesce({over}, false) AS kept
FROM m LEFT JOIN cut ON cut.s IS NOT DISTINCT FROM m.lang
"""
