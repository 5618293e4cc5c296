"""Benchmark decontamination: a broadcast set of test n-grams against windows of training words."""

from __future__ import annotations

import bisect

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erfocus.llm import textarrays as ta
from erfocus.llm.kinds import arrow_kind, unused
from erfocus.operators.durable import cut, sized

WINDOW = 10
MAX_BLOCK_BYTES = 32 << 20
SPANS = "array<struct<start:int,end:int>>"


class NgramSet:
    """Windows of some items: sorted hashes by window length, the words for verification, the items."""

    def __init__(self, items: list[tuple], window: int):
        texts = pa.array([t for _, t in items], pa.large_string())
        found: dict[int, dict[tuple[int, bytes], list[int]]] = {}
        for row, _, data, offsets in ta.slices(texts):
            w = ta.words(data, offsets, ta.ALNUM)
            h = ta.word_hashes(w)
            sizes = np.minimum(w.counts, window)
            for n in np.unique(sizes[sizes > 0]):
                n = int(n)
                ok = ta.whole(w, n)
                ok &= sizes[w.text[: len(ok)]] == n
                grams = ta.gram_hashes(h, n)
                for i in np.flatnonzero(ok):
                    key = int(grams[i]), joined(w, i, n)
                    found.setdefault(n, {}).setdefault(key, []).append(row + int(w.text[i]))
        self.ids = [i for i, _ in items]
        self.by_length = []
        for n, entries in sorted(found.items()):
            keys = sorted(entries)
            hashes = np.array([k[0] for k in keys], dtype=ta.U)
            seen = np.zeros(1 << 16, dtype=bool)
            seen[(hashes >> ta.U(48)).astype(np.int64)] = True
            self.by_length.append((n, hashes, seen, [k[1] for k in keys], [sorted(set(entries[k])) for k in keys]))

    def hits(self, w: ta.Words, h: np.ndarray):
        """(window length, word index, items) of each verified window."""
        for n, hashes, seen, words, items in self.by_length:
            grams = ta.gram_hashes(h, n)
            at = np.flatnonzero(seen[(grams >> ta.U(48)).astype(np.int64)] & ta.whole(w, n))
            at = at[hashes[np.minimum(np.searchsorted(hashes, grams[at]), len(hashes) - 1)] == grams[at]]
            for i in at.tolist():
                text, k = joined(w, i, n), bisect.bisect_left(hashes, grams[i])
                while k < len(hashes) and hashes[k] == grams[i]:
                    if words[k] == text:
                        yield n, i, items[k]
                    k += 1


def joined(w: ta.Words, i: int, n: int) -> bytes:
    return b" ".join(w.data[s:e].tobytes() for s, e in zip(w.start[i : i + n], w.end[i : i + n], strict=True))


def _blocks(benchmark: DataFrame, id_col: str, text_col: str, limit: int) -> list[list[tuple]]:
    """The items in blocks of bounded size; one block for any usual benchmark suite."""
    items = benchmark.select(F.col(id_col).alias("item"), F.col(text_col).alias("text")).where(F.col("text").isNotNull())
    size = items.agg(F.sum(F.octet_length("text") + 64).alias("n")).first()["n"] or 0
    n = max(1, -(-size // limit))
    return [
        [tuple(r) for r in items.where(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == b).toLocalIterator()] for b in range(n)
    ]


def _scan(docs: DataFrame, block, keys: list[str], item_type: T.DataType) -> DataFrame:
    schema = T.StructType(
        [docs.schema[k] for k in keys]
        + [T.StructField("n_words", T.LongType()), T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))), T.StructField("items", T.ArrayType(item_type))]
    )
    handle = docs.sparkSession.sparkContext.broadcast(block)

    def scan(batches):
        grams = handle.value
        for batch in batches:
            text = batch.column(batch.schema.get_field_index("__text"))
            counts, spans, items = [], [], []
            for row, end, data, offsets in ta.slices(text):
                w = ta.words(data, offsets, ta.ALNUM)
                counts += w.counts.tolist()
                own: dict[int, tuple[list, set]] = {}
                for n, i, found in grams.hits(w, ta.word_hashes(w)):
                    r = int(w.text[i])
                    at = own.setdefault(r, ([], set()))
                    at[0].append((i - int(w.first[r]), i - int(w.first[r]) + n))
                    at[1].update(found)
                for r in range(end - row):
                    if r not in own:
                        spans.append([])
                        items.append([])
                        continue
                    spans.append([{"start": s, "end": e} for s, e in merged(own[r][0])])
                    items.append(list({grams.ids[k] for k in own[r][1] if grams.ids[k] is not None}))
            yield pa.RecordBatch.from_arrays(
                [batch.column(batch.schema.get_field_index(k)) for k in keys]
                + [pa.array(counts, pa.int64()), pa.array(spans, pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))), pa.array(items, pa.list_(arrow_kind(item_type)))],
                names=[*keys, "n_words", "spans", "items"],
            )

    return docs.mapInArrow(scan, schema)


def scan(
    docs: DataFrame,
    benchmark: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text: str = "text",
    window: int = WINDOW,
    max_block_bytes: int = MAX_BLOCK_BYTES,
) -> DataFrame:
    """Per row of docs: id, n_words, spans (half-open word ranges inside test windows) and items.

    Words are runs of digits, letters and non-ASCII characters after lower-casing A-Z.  An item of
    fewer words than the window is one window; one without words, or null, has none.  Null and empty
    texts have no words and no spans.  Repeated rows each give a row; a null item id marks words but
    is not listed.  Extra columns of either table are not read.  Every hit found by hash is compared
    word by word.  Items beyond max_block_bytes are taken in blocks, one pass over the texts each.
    """
    item_type = benchmark.schema[item_col].dataType
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text"))
    blocks = _blocks(benchmark, item_col, item_text, max_block_bytes)
    if len(blocks) == 1:
        return _scan(rows, NgramSet(blocks[0], window), ["doc_id"], item_type)
    rows = rows.withColumn("__key", F.sha2(F.coalesce("__text", F.lit("")), 256))
    parts = [_scan(rows, NgramSet(b, window), ["doc_id", "__key"], item_type) for b in blocks]
    found = parts[0]
    for p in parts[1:]:
        found = found.union(p)
    found = found.groupBy("doc_id", "__key").agg(
        F.first("n_words").alias("n_words"), F.flatten(F.collect_set("spans")).alias("spans"), F.array_distinct(F.flatten(F.collect_set("items"))).alias("items")
    )
    f = found.withColumn("spans", _united("spans")).alias("f")
    r = rows.select("doc_id", "__key").alias("r")
    return r.join(f, F.col("r.doc_id").eqNullSafe(F.col("f.doc_id")) & (F.col("r.__key") == F.col("f.__key"))).select("r.doc_id", "n_words", "spans", "items")


def _united(spans: str) -> Column:
    """Spans in order, with those that overlap or touch made one."""
    end = "(acc, s) -> named_struct('spans', if(s.start <= acc.last and size(acc.spans) > 0, concat(slice(acc.spans, 1, size(acc.spans) - 1), array(named_struct('start', acc.spans[size(acc.spans) - 1].start, 'end', greatest(acc.last, s.end)))), concat(acc.spans, array(s))), 'last', greatest(acc.last, s.end))"
    return F.expr(f"aggregate(array_sort({spans}), named_struct('spans', cast(array() as {SPANS}), 'last', -1), {end}).spans")


def merged(spans: list[tuple[int, int]]) -> list[list[int]]:
    """The same of one text's spans."""
    out: list[list[int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1][1] = max(e, out[-1][1])
        else:
            out.append([s, e])
    return out


def digest(found: DataFrame) -> DataFrame:
    """The report per document: counts, the items' digest and the verdict."""
    listed = F.array_sort(F.transform("items", lambda x: x.cast("string")))
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda acc, s: acc + (s["end"] - s["start"]))
    return found.select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", listed).cast("binary"), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
    )


def decontaminate(
    docs: DataFrame, benchmark: DataFrame, mode: str = "document", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", window: int = WINDOW, max_block_bytes: int = MAX_BLOCK_BYTES
) -> DataFrame:
    """docs without contaminated rows (mode 'document') or with the hit words cut out (mode 'span').

    All columns and clean rows are kept as they are, repeated rows each.  A cut takes a span's bytes from its
    first word to its last; spans are united over all items first, so that blocks of items give the same text
    as one.  Rows with null or empty text are clean, as is every row without items.  One block needs no shuffle.
    """
    blocks = _blocks(benchmark, item_col, item_text, max_block_bytes)
    if mode == "document" or len(blocks) == 1:
        for block in blocks:
            docs = _filtered(docs, NgramSet(block, window), mode, text_col)
        return docs
    key, spans = unused(docs.columns, "__key", "__spans")
    digest_ = F.sha2(F.col(text_col), 256)
    rows, found = docs.where(F.col(text_col).isNotNull()).select(digest_.alias("__key"), F.col(text_col).alias("__text")), None
    for block in blocks:
        part = _scan(rows, NgramSet(block, window), ["__key"], benchmark.schema[item_col].dataType).where(F.size("spans") > 0).select("__key", "spans")
        found = part if found is None else found.union(part)
    hit = found.groupBy("__key").agg(F.flatten(F.collect_set("spans")).alias("spans")).select(F.col("__key").alias(key), _united("spans").alias(spans))
    joined = docs.join(sized(cut(hit)), digest_ == F.col(key), "left")
    return _cut_out(joined.select(*docs.columns, spans), docs, text_col)


def _cut_out(joined: DataFrame, docs: DataFrame, text_col: str) -> DataFrame:
    """docs with the word spans of the last column cut out of the texts."""
    names = docs.columns

    def run(batches):
        for batch in batches:
            k = batch.schema.get_field_index(text_col)
            spans = batch.column(batch.num_columns - 1).to_pylist()
            gone = {}
            for row, end, data, offsets in ta.slices(batch.column(k)):
                if any(spans[row:end]):
                    w = ta.words(data, offsets, ta.ALNUM)
                    gone |= {row + r: _without(data, offsets, w, r, [(x["start"], x["end"]) for x in spans[row + r]]) for r in range(end - row) if spans[row + r]}
            yield pa.RecordBatch.from_arrays([_replaced(batch.column(i), gone if i == k else {}) for i in range(batch.num_columns - 1)], names=names)

    return joined.mapInArrow(run, docs.schema)


def _without(data: np.ndarray, offsets: np.ndarray, w: ta.Words, r: int, spans: list[tuple[int, int]]) -> bytes:
    """Text r's bytes without these word ranges, which neither overlap nor touch."""
    on = np.ones(int(offsets[r + 1] - offsets[r]), dtype=bool)
    first, base = int(w.first[r]), int(offsets[r])
    for s, e in spans:
        on[int(w.start[first + s]) - base : int(w.end[first + e - 1]) - base] = False
    return data[offsets[r] : offsets[r + 1]][on].tobytes()


def _replaced(column: pa.Array, texts: dict[int, bytes]) -> pa.Array:
    return pa.array([texts[i].decode() if i in texts else x.as_py() for i, x in enumerate(column)], column.type) if texts else column


def _filtered(docs: DataFrame, block: NgramSet, mode: str, text_col: str) -> DataFrame:
    handle = docs.sparkSession.sparkContext.broadcast(block)

    def run(batches):
        grams = handle.value
        for batch in batches:
            k = batch.schema.get_field_index(text_col)
            keep = np.ones(batch.num_rows, dtype=bool)
            gone: dict[int, bytes] = {}
            for row, _, data, offsets in ta.slices(batch.column(k)):
                w = ta.words(data, offsets, ta.ALNUM)
                own: dict[int, list[tuple[int, int]]] = {}
                for n, i, _items in grams.hits(w, ta.word_hashes(w)):
                    r = int(w.text[i])
                    own.setdefault(r, []).append((i - int(w.first[r]), i - int(w.first[r]) + n))
                for r, spans in own.items():
                    keep[row + r] = False
                    if mode == "span":
                        gone[row + r] = _without(data, offsets, w, r, merged(spans))
            if mode == "document":
                yield batch.filter(pa.array(keep))
            else:
                yield pa.RecordBatch.from_arrays([_replaced(batch.column(i), gone if i == k else {}) for i in range(batch.num_columns)], schema=batch.schema)

    return docs.mapInArrow(run, docs.schema)


DIGEST_SQL = rf"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS ws FROM benchmark),
g AS (SELECT DISTINCT item_id, least(len(ws), {WINDOW}) AS n, array_to_string(ws[i:i + least(len(ws), {WINDOW}) - 1], ' ') AS gram
      FROM (SELECT *, unnest(range(1, greatest(len(ws) - {WINDOW} + 1, 1) + 1)) AS i FROM b WHERE len(ws) > 0)),
sizes AS (SELECT DISTINCT n FROM g),
w AS (SELECT doc_id, n, i, array_to_string(ws[i:i + n - 1], ' ') AS gram FROM (SELECT d.*, n, unnest(range(1, len(ws) - n + 2)) AS i FROM d, sizes)),
h AS (SELECT doc_id, i, w.n, item_id FROM w JOIN g ON w.n = g.n AND w.gram = g.gram),
c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM h) GROUP BY doc_id),
t AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS items FROM h GROUP BY doc_id)
SELECT doc_id, len(ws)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
  sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN t USING (doc_id)
"""
