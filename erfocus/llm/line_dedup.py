"""Line dedup by distinct-site spread, with DataFrame functions only.

A line's spread is the number of sites it is on.  HyperLogLog sketches of sites merge by line hash;
lines whose estimate is near the threshold, within the sketch's error, get an exact distinct count.
Lines spread over the threshold are boilerplate and leave every text, except texts that consist of
such lines for the most part: those are copies, which whole-document dedup takes one by one.
line_report counts lines of MIN_CHARS characters and exempts texts by MAX_SHARE, as its SQL does;
without_boilerplate counts every line that isn't blank and exempts only texts without a line of their own.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erfocus.llm.kinds import unused
from erfocus.operators.durable import cut, sized

MIN_SITES = 10
MIN_CHARS = 20
MAX_SHARE = 0.5
LG_K = 10
#: Texts with boilerplate are broadcast with their lines' hashes up to this size, else joined by an exchange.
MAX_BROADCAST_BYTES = 16 << 20
#: Three standard errors of an HLL sketch with 2 ** LG_K bins.
MARGIN = 3 * 1.04 / 2 ** (LG_K / 2)


def _line_key(line: Column) -> Column:
    return F.xxhash64(F.trim(line))


def _counted(line: Column, every: bool) -> Column:
    return line.rlike(r"[^\x20\x09-\x0D]") if every else F.char_length(F.trim(line)) >= MIN_CHARS


def boilerplate(docs: DataFrame, text_col: str = "text", site_col: str = "source", min_sites: int = MIN_SITES, every: bool = False) -> DataFrame:
    """(line_key) of lines of at least MIN_CHARS characters, or of every line not blank, trimmed of spaces, on min_sites sites or more.

    A null site counts as one site of its own; null texts have no lines.
    """
    lines = docs.select(F.coalesce(F.col(site_col).cast("string"), F.lit("\0")).alias("__site"), F.explode(F.split(F.col(text_col), "\n")).alias("__line"))
    lines = lines.where(_counted(F.col("__line"), every)).select("__site", _line_key(F.col("__line")).alias("line_key"))
    spread = lines.groupBy("line_key").agg(F.hll_sketch_estimate(F.hll_sketch_agg("__site", F.lit(LG_K))).alias("sites"))
    spread = cut(spread.where(F.col("sites") >= min(min_sites - 1, int(min_sites / (1 + MARGIN)))))
    high = max(min_sites + 1, int(min_sites * (1 + MARGIN)) + 1)
    sure = spread.where(F.col("sites") > high).select("line_key")
    near = spread.where(F.col("sites") <= high).select("line_key")
    exact = lines.join(sized(near), "line_key").distinct().groupBy("line_key").count().where(F.col("count") >= min_sites)
    return sure.union(exact.select("line_key"))


def line_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """Every row's id, n_lines, n_boilerplate lines, n_removed of them and cleaned_text.

    Null texts have no lines and stay null; the empty text is one empty line.  Lines that repeat in a
    text count each time.  Repeated rows each give a row; a null id is kept, extra columns are not read.  A text
    whose boilerplate is over MAX_SHARE of its characters is left as it is.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(site_col).alias("site"))
    found, n = _with_lines(rows, "doc_id", "text", "site", min_sites)
    return found.select(
        "doc_id", F.col(n.lines).alias("n_lines"), F.col(n.hit).alias("n_boilerplate"), F.when(F.col(n.strip), F.col(n.hit)).otherwise(0).cast("long").alias("n_removed"), F.col(n.new).alias("cleaned_text")
    )


@dataclass(frozen=True)
class Names:
    """Columns beside the user's, of names that the user's don't have."""

    id: str
    key: str
    keys: str
    lines: str
    hit: str
    strip: str
    new: str


def _narrow(hits: DataFrame, keys: str) -> DataFrame:
    """Texts with boilerplate and its keys, broadcast only if their bytes are counted to be few."""
    size = hits.agg(F.sum(F.lit(64) + 8 * F.size(keys)).alias("n")).first()["n"] or 0
    return F.broadcast(hits) if size <= MAX_BROADCAST_BYTES else hits


def _with_lines(docs: DataFrame, id_col: str, text_col: str, site_col: str, min_sites: int, every: bool = False) -> tuple[DataFrame, Names]:
    n = Names(*unused(docs.columns, *Names.__annotations__))
    marks = cut(boilerplate(docs, text_col, site_col, min_sites, every).distinct())
    text, id_, key = F.col(text_col), F.col(id_col), F.xxhash64(F.col(text_col))
    lines = docs.select(id_.alias(n.id), key.alias(n.key), F.explode(F.split(text, "\n")).alias("__line")).where(_counted(F.col("__line"), every))
    hits = lines.select(n.id, n.key, _line_key(F.col("__line")).alias("line_key")).join(sized(marks), "line_key").groupBy(n.id, n.key).agg(F.collect_set("line_key").alias(n.keys))
    hits = _narrow(cut(hits), n.keys)
    joined = docs.join(hits, id_.eqNullSafe(F.col(n.id)) & (key == F.col(n.key)), "left")
    parts = F.split(text, "\n")
    hit = lambda x: F.coalesce(_counted(x, every) & F.array_contains(F.col(n.keys), _line_key(x)), F.lit(False))
    removed = F.filter(parts, hit)
    any_ = F.col(n.keys).isNotNull()
    joined = joined.withColumn(n.lines, F.when(text.isNull(), 0).otherwise(F.size(parts)).cast("long"))
    joined = joined.withColumn(n.hit, F.when(any_, F.size(removed)).otherwise(0).cast("long"))
    if every:
        strip = any_ & F.exists(parts, lambda x: _counted(x, True) & ~hit(x))
    else:
        strip = any_ & (F.char_length(F.array_join(removed, "")) <= MAX_SHARE * F.char_length(text))
    joined = joined.withColumn(n.strip, F.coalesce(strip, F.lit(False)))
    return joined.withColumn(n.new, F.when(F.col(n.strip), F.array_join(F.filter(parts, lambda x: ~hit(x)), "\n")).otherwise(text)), n


def without_boilerplate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", site_col: str = "source", min_sites: int = MIN_SITES) -> DataFrame:
    """docs with boilerplate lines of any length cut out of the text; every row and column is kept.

    A text that has only such lines, and blank ones, is left as it is, as are null and empty texts.  Repeated
    rows and null ids are kept; columns of any names are.
    """
    done, n = _with_lines(docs, id_col, text_col, site_col, min_sites, every=True)
    return done.select(*[F.col(n.new).alias(c) if c == text_col else F.col(f"`{c}`") for c in docs.columns])


#: What line_report returns, with the texts' digests in place of the texts.
REPORT_SQL = f"""
WITH l AS (SELECT coalesce(source, chr(1)) AS site, trim(unnest(string_split(text, chr(10))), ' ') AS line FROM documents),
b AS (SELECT line FROM l WHERE length(line) >= {MIN_CHARS} GROUP BY line HAVING count(DISTINCT site) >= {MIN_SITES}),
s AS (SELECT list(line) AS marks FROM b),
d AS (SELECT doc_id, text, CASE WHEN text IS NULL THEN [] ELSE string_split(text, chr(10)) END AS parts,
      list_transform(CASE WHEN text IS NULL THEN [] ELSE string_split(text, chr(10)) END, lambda x: coalesce(list_contains(marks, trim(x, ' ')), false)) AS hit FROM documents, s),
e AS (SELECT doc_id, text, parts, hit, len(list_filter(hit, lambda x: x)) AS n_b,
      list_aggregate(list_transform(parts, lambda x, i: CASE WHEN hit[i] THEN length(x) ELSE 0 END), 'sum') AS cut_chars FROM d)
SELECT doc_id, len(parts)::BIGINT AS n_lines, n_b::BIGINT AS n_boilerplate,
  (CASE WHEN n_b > 0 AND cut_chars <= {MAX_SHARE} * length(text) THEN n_b ELSE 0 END)::BIGINT AS n_removed,
  sha256(CASE WHEN n_b > 0 AND cut_chars <= {MAX_SHARE} * length(text)
    THEN array_to_string(list_filter(parts, lambda x, i: NOT hit[i]), chr(10)) ELSE text END) AS text_sha256
FROM e
"""
