"""URL rules by a Bloom filter cascade.

The first filter holds the listed keys; the second those keys of the corpus that the first takes for
listed by mistake; the third the listed keys that the second takes for mistakes, and so on until none
is left.  Membership is then exact for every key of the corpus, without a join and without the list.
Urls are split, and the keys of the rules that may fit them hashed to 128 bits, by built-in functions; the
filters are probed for whole batches at once.  A list over SHARD_KEYS keys is dealt by hash to cascades of
bounded size, one pass over the hashed keys each.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erfocus.llm import textarrays as ta
from erfocus.operators.durable import cut

SHARD_KEYS = 4 << 20
MAX_LEVELS = 40
#: The seeds of the two halves of a key's hash.
SEEDS = (11, 29)


class Bloom:
    """Keys are pairs of 64-bit hashes."""

    def __init__(self, keys: np.ndarray, error: float, salt: int):
        n = max(1, len(keys))
        self.salt = salt
        self.bits = max(64, math.ceil(-n * math.log(error) / math.log(2) ** 2))
        self.probes = min(30, max(1, round(self.bits / n * math.log(2)) if n > 1 else math.ceil(-math.log2(error))))
        on = np.zeros(self.bits, dtype=bool)
        for at in self._places(keys):
            on[at] = True
        self.words = np.packbits(on, bitorder="little")

    def _places(self, keys: np.ndarray):
        a, b = ta.mix(keys[:, 0], self.salt), ta.mix(keys[:, 1], self.salt) | ta.U(1)
        for _ in range(self.probes):
            yield (a % ta.U(self.bits)).astype(np.int64)
            a = a + b

    def holds(self, keys: np.ndarray) -> np.ndarray:
        found = np.ones(len(keys), dtype=bool)
        for at in self._places(keys):
            found &= (self.words[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
        return found


@dataclass
class Cascade:
    """levels[0] holds listed keys, levels[1] mistakes of it, by turns."""

    levels: list[Bloom] = field(default_factory=list)

    def holds(self, keys: np.ndarray) -> np.ndarray:
        """Which keys are listed: those that an odd number of levels in a row hold."""
        odd, asked = np.zeros(len(keys), dtype=bool), np.arange(len(keys))
        for i, level in enumerate(self.levels):
            asked = asked[level.holds(keys[asked])]
            odd[asked] = i % 2 == 0
        return odd


@dataclass(frozen=True)
class Rule:
    action: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


#: The stated rules.
RULES = (Rule("block", "net", "/"), Rule("allow", "example.net", "/en/"), Rule("block", "example.com", "/de/"), Rule("allow", "org", "/fr/"))


def rule_table(pages: DataFrame, rules: Iterable[Rule] | DataFrame) -> DataFrame:
    """(action, host, path) of rules."""
    if isinstance(rules, DataFrame):
        return rules.select("action", "host", "path").where("action IS NOT NULL AND host IS NOT NULL AND path IS NOT NULL").distinct()
    return pages.sparkSession.createDataFrame([(r.action, r.host, r.path) for r in set(rules)], "action string, host string, path string")


def _key(host: Column, path: Column, action: Column) -> Column:
    return F.array(*[F.xxhash64(F.lit(s), host, path, action) for s in SEEDS])


def _let(value: Column, use) -> Column:
    return F.element_at(F.transform(F.array(value), use), 1)


def parts(url: Column) -> Column:
    """(host, path) of a url: empty both for null and for text without ://."""
    start = F.instr(url, "://")
    rest = F.when(start > 0, F.substring(url, start + 3, F.char_length(url))).otherwise(F.lit(""))
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return _let(rest, lambda r: F.struct(F.translate(F.regexp_extract(r, "^([^/?#]*)", 1), upper, upper.lower()).alias("host"), F.regexp_extract(r, "^[^/?#]*([^?#]*)", 1).alias("path")))


@dataclass(frozen=True)
class Shape:
    """What the list says of keys that can fit: their host's most labels, their paths' lengths, the actions."""

    labels: int
    lengths: tuple[int, ...]
    actions: tuple[str, ...]
    listed: int


def shape(listed: DataFrame) -> Shape:
    row = listed.agg(
        F.max(F.size(F.split("host", r"\."))).alias("labels"), F.array_sort(F.collect_set(F.char_length("path"))).alias("lengths"), F.array_sort(F.collect_set("action")).alias("actions"), F.count(F.lit(1)).alias("n")
    ).first()
    return Shape(row["labels"] or 0, tuple(row["lengths"]), tuple(sorted(row["actions"], key=lambda a: a != "block")), row["n"])


def keyed(pages: DataFrame, s: Shape, id_col: str, url_col: str) -> DataFrame:
    """(page_id, host, path, hosts, paths, keys): of the rules that can fit a url the host's and path's lengths, and the
    keys' hashes for every action; longest first, of equals the longer host, a block before any other action."""
    rows = pages.select(F.col(id_col).alias("page_id"), F.inline(F.array(parts(F.col(url_col)))))
    host, path = F.col("host"), F.col("path")
    names = F.split(host, r"\.")
    ends = F.transform(F.sequence(F.greatest(F.lit(1), F.size(names) - s.labels + 1), F.size(names)), lambda i: F.array_join(F.slice(names, i, F.size(names)), "."))
    lengths = F.filter(F.array(*map(F.lit, s.lengths)), lambda n: n <= F.char_length(path))
    fits = F.flatten(
        F.transform(ends, lambda h: F.transform(lengths, lambda n: F.struct((-F.char_length(h) - n).alias("long"), (-F.char_length(h)).alias("wide"), h.alias("h"), F.substring(path, F.lit(1), n).alias("p"))))
    )
    rows = rows.select("page_id", "host", "path", F.explode(F.array(F.array_sort(fits))).alias("__fits"))
    return rows.select(
        "page_id",
        "host",
        "path",
        F.transform("__fits", lambda c: -c["wide"]).alias("hosts"),
        F.transform("__fits", lambda c: c["wide"] - c["long"]).alias("paths"),
        F.flatten(F.flatten(F.transform("__fits", lambda c: F.array(*[_key(c["h"], c["p"], F.lit(a)) for a in s.actions])))).alias("keys"),
    )


def _pairs(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(keys, number of each row's) of a column of flat lists."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.int64).view(ta.U).reshape(-1, 2)
    return flat, np.diff(column.offsets.to_numpy()) // 2


def _listed(keys: np.ndarray, known: np.ndarray) -> np.ndarray:
    """Which keys are among known ones, which are sorted by their first halves and then their second."""
    order = np.lexsort((keys[:, 1], keys[:, 0]))
    both = np.concatenate([known, keys[order]])
    rank = np.lexsort((np.arange(len(both)), both[:, 1], both[:, 0]))
    new = np.concatenate([[True], (both[rank[1:]] != both[rank[:-1]]).any(axis=1)])
    group = np.empty(len(both), dtype=np.int64)
    group[rank] = np.cumsum(new)
    out = np.empty(len(keys), dtype=bool)
    out[order] = np.isin(group[len(known) :], group[: len(known)])
    return out


def build(candidates: DataFrame, listed: DataFrame, shard: int, shards: int, n_keys: int) -> Cascade:
    """A cascade exact for every candidate key, of the listed keys of one shard.

    All actions are keys of the universe, so that a listed key of another action is told apart.  What comes to the
    driver are the shard's keys and the first level's mistakes: its error rate is set from the number of keys in
    the corpus so that they are about as many as the list.
    """
    own = listed.select(_key(F.col("host"), F.col("path"), F.col("action")).alias("k")).where(F.pmod(F.col("k")[0], F.lit(shards)) == shard)
    known = np.array([r["k"] for r in own.toLocalIterator()], dtype=np.int64).reshape(-1, 2).view(ta.U)
    if not len(known):
        return Cascade()
    known = known[np.lexsort((known[:, 1], known[:, 0]))]
    first = Bloom(known, min(0.5, max(1e-12, len(known) / (math.sqrt(2) * max(1, n_keys)))), 1)
    handle = candidates.sparkSession.sparkContext.broadcast((first, known))

    def mistakes(batches):
        level, mine = handle.value
        for batch in batches:
            keys, _ = _pairs(batch.column(0))
            keys = keys[(keys[:, 0].view(np.int64) % shards == shard) & level.holds(keys)]
            keys = np.unique(keys[~_listed(keys, mine)], axis=0) if len(keys) else keys
            if len(keys):
                yield pa.RecordBatch.from_arrays([pa.array(keys[:, 0].view(np.int64)), pa.array(keys[:, 1].view(np.int64))], names=["a", "b"])

    wrong = cut(candidates.select("keys").mapInArrow(mistakes, "a long, b long").distinct())
    now = np.array([(r["a"], r["b"]) for r in wrong.toLocalIterator()], dtype=np.int64).reshape(-1, 2).view(ta.U)
    cascade, other = Cascade([first]), known
    while len(now):
        if len(cascade.levels) >= MAX_LEVELS:
            raise RuntimeError("the cascade does not end")
        level = Bloom(now, 0.5, len(cascade.levels) + 1)
        cascade.levels.append(level)
        now, other = other[level.holds(other)], now
    return cascade


FOUND = "page_id {}, host string, path string, hosts array<int>, paths array<int>, keys array<long>, best int"


def _probed(candidates: DataFrame, cascade: Cascade, shard: int, shards: int) -> DataFrame:
    """candidates with best, the first listed key's number, taken on from the shards before."""
    handle = candidates.sparkSession.sparkContext.broadcast(cascade)

    def run(batches):
        known = handle.value
        for batch in batches:
            keys, n = _pairs(batch.column(5))
            mine = np.flatnonzero(keys[:, 0].view(np.int64) % shards == shard)
            hit = mine[known.holds(keys[mine])]
            row = np.repeat(np.arange(len(n)), n)[hit]
            best = batch.column(6).fill_null(1 << 30).to_numpy(zero_copy_only=False).astype(np.int64)
            np.minimum.at(best, row, hit - (np.cumsum(n) - n)[row])
            yield pa.RecordBatch.from_arrays([*batch.columns[:6], pa.array(best.astype(np.int32), mask=best == 1 << 30)], names=batch.schema.names)

    return candidates.mapInArrow(run, FOUND.format(candidates.schema["page_id"].dataType.simpleString()))


def judge(pages: DataFrame, rules: Iterable[Rule] | DataFrame = RULES, id_col: str = "page_id", url_col: str = "url", default: str = "allow", shard_keys: int = SHARD_KEYS) -> DataFrame:
    """(page_id, host, path, rule, verdict) of every row.

    rules: Rules, or a table (action, host, path) of any size.  A rule fits its host and its subdomains if the
    url's path starts with the rule's; the longest fits best, of equals that of the longer host.  A url that no rule
    fits is not listed and gets the default.  Null, empty urls and urls without :// have an empty host and path.  Of
    rules with the same host and path a block wins.  Repeated rows each give a row; null ids are kept; an empty
    table gives no row; extra columns are not read.
    """
    listed = rule_table(pages, rules)
    s = shape(listed)
    if not s.listed:
        rows = pages.select(F.col(id_col).alias("page_id"), F.inline(F.array(parts(F.col(url_col)))))
        return rows.select("page_id", "host", "path", F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    shards = -(-s.listed // shard_keys)
    rows = keyed(pages, s, id_col, url_col)
    if shards > 1:
        rows = cut(rows)
    n_keys = rows.agg(F.sum(F.size("keys"))).first()[0] or 0
    found = rows.withColumn("best", F.lit(None).cast("int"))
    for shard in range(shards):
        found = _probed(found, build(rows, listed, shard, shards, n_keys // 2), shard, shards)
        if shard + 1 < shards:
            found = cut(found)
    at, actions = F.floor(F.col("best") / len(s.actions)).cast("int"), F.array(*map(F.lit, s.actions))
    wide, long = F.get("hosts", at), F.get("paths", at)
    rule = F.concat(F.substring("host", F.char_length("host") - wide + 1, wide), F.substring("path", F.lit(1), long))
    return found.select(
        "page_id", "host", "path", F.when(F.col("best").isNotNull(), rule).alias("rule"), F.coalesce(F.get(actions, F.pmod("best", F.lit(len(s.actions)))), F.lit(default)).alias("verdict")
    )


#: The stated rules in SQL.
VERDICT_SQL = r"""
WITH u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
      regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
r AS (SELECT * FROM (VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')) AS t(action, rhost, rpath)),
f AS (SELECT page_id, host, path, action, rhost || rpath AS rule,
      row_number() OVER (PARTITION BY page_id ORDER BY length(rhost || rpath) DESC NULLS LAST, length(rhost) DESC) AS k
      FROM h LEFT JOIN r ON (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath))
SELECT page_id, host, path, rule, coalesce(action, 'allow') AS verdict FROM f WHERE k = 1
"""
