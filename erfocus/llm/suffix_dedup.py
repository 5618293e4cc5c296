"""Repeated passages by sparse suffix arrays.

Of a text's suffixes those are retained that begin at a minimiser: the place of the least anchor-gram hash in
a window of MIN_WORDS words.  Equal windows have their minimisers at the same places, so that every repeated
window holds a retained suffix with the same first words.  Suffixes whose first words are in one document alone
are dropped; the others come together with the words that a window may hold on either side.  They are sorted by
the words that follow and by the words before, read backwards; comparing neighbours gives how many words each
pair of neighbours shares, to the right and to the left, and so which suffixes share which extension of at least
MIN_WORDS words.  A retained suffix gives one row for each of its matches.  Words are compared by hashes, and words
of equal hashes byte by byte.

First words that begin more than GROUP suffixes would make a task too large.  For those every place is retained:
suffixes that begin anywhere are sorted by a 128-bit hash of their first MIN_WORDS words and compared with their
neighbours, first within a task that reads texts, then, a place from each such task, by ranges of hashes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.llm import textarrays as ta
from erfocus.llm.groups import by_group
from erfocus.llm.kinds import arrow_kind
from erfocus.operators.durable import cut

MIN_WORDS = 50
ANCHOR = 10
GROUP = 1024
#: Places that a task holds before it settles them.
FLUSH = 1 << 20
MAX_LIVE = 8 << 20


def minimisers(h: np.ndarray, w: ta.Words, min_words: int, anchor: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(window start, its minimiser's place, anchor-gram hashes) of each window of min_words words in one text."""
    start = np.flatnonzero(ta.whole(w, min_words))
    grams = ta.gram_hashes(h, anchor)
    if not len(start):
        return start, start, grams
    span = min_words - anchor + 1
    # Least of span values from each place on, by doubling; the leftmost of equals.
    place, size = np.arange(len(grams)), 1
    while 2 * size <= span:
        place = _less(grams, place[: len(place) - size], place[size:])
        size *= 2
    m = len(grams) - span + 1
    place = _less(grams, place[:m], place[span - size : span - size + m])
    return start, place[start], grams


def _less(grams: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.where(grams[b] < grams[a], b, a)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text")).where(F.col("doc_id").isNotNull() & F.col("__text").isNotNull())


def anchors(rows: DataFrame, min_words: int, anchor: int) -> DataFrame:
    """(gram, doc_id) of retained suffixes' first words."""
    kind = rows.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            docs = batch.column(0)
            for row, _, data, offsets in ta.slices(batch.column(1)):
                w = ta.words(data, offsets, ta.NOT_SPACE)
                _, place, grams = minimisers(ta.word_hashes(w), w, min_words, anchor)
                place = np.unique(place)
                yield pa.RecordBatch.from_arrays([pa.array(grams[place].view(np.int64)), docs.take(pa.array(row + w.text[place]))], names=["gram", "doc_id"])

    return rows.mapInArrow(run, f"gram long, doc_id {kind}")


def _shared(rows: DataFrame, *key: str) -> DataFrame:
    """(key, n) of keys of at least two documents."""
    return rows.groupBy(*key).agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b"), F.count(F.lit(1)).alias("n")).where("a < b").select(*key, "n")


def _known(batch: pa.RecordBatch, row: int, end: int, known: np.ndarray | None) -> np.ndarray:
    """The sorted grams asked for: those of all texts, or of the rows' own lists."""
    return known if known is not None else np.unique(batch.column(2).slice(row, end - row).flatten().to_numpy(zero_copy_only=False).astype(np.int64))


def _among(here: np.ndarray, key: np.ndarray) -> np.ndarray:
    return here[np.minimum(np.searchsorted(here, key), len(here) - 1)] == key if len(here) else np.zeros(len(key), dtype=bool)


def suffixes(rows: DataFrame, known: np.ndarray | None, min_words: int, anchor: int) -> DataFrame:
    """(gram, doc_id, place, before, words) of retained suffixes with known first words.

    words: up to min_words words from the place on, and the before words ahead of it.
    """
    kind = rows.schema["doc_id"].dataType.simpleString()
    handle = rows.sparkSession.sparkContext.broadcast(known)

    def run(batches):
        for batch in batches:
            docs = batch.column(0)
            for row, end, data, offsets in ta.slices(batch.column(1)):
                w = ta.words(data, offsets, ta.NOT_SPACE)
                _, place, grams = minimisers(ta.word_hashes(w), w, min_words, anchor)
                place = np.unique(place)
                place = place[_among(_known(batch, row, end, handle.value), grams[place].view(np.int64))]
                if not len(place):
                    continue
                text = w.text[place]
                before = np.minimum(place - w.first[text], min_words - anchor)
                after = np.minimum(w.first[text + 1] - place, min_words)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(grams[place].view(np.int64)),
                        docs.take(pa.array(row + text)),
                        pa.array((place - w.first[text]).astype(np.int32)),
                        pa.array(before.astype(np.int32)),
                        ta.passages(w, place - before, place + after),
                    ],
                    names=["gram", "doc_id", "place", "before", "words"],
                )

    return rows.mapInArrow(run, f"gram long, doc_id {kind}, place int, before int, words binary")


def neighbours(gram: np.ndarray, side: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, shared): rows sorted by gram and their side's words; words each shares with the one before it, -1 over grams."""
    m, width = side.shape
    keys = np.concatenate([gram[:, None], side], axis=1).astype(">u8")
    order = np.argsort(np.ascontiguousarray(keys).view(f"V{8 * (width + 1)}").ravel(), kind="stable")
    a, b = side[order[:-1]], side[order[1:]]
    same = (a == b) & (np.arange(width) < np.minimum(size[order[:-1]], size[order[1:]])[:, None])
    shared = np.full(m, -1, dtype=np.int64)
    shared[1:] = np.where(gram[order[:-1]] == gram[order[1:]], np.minimum.accumulate(same, axis=1).sum(axis=1), -1)
    return order, shared


def _classes(order: np.ndarray, shared: np.ndarray, words: int) -> np.ndarray:
    """A number for each row, the same for rows of a gram that share so many words of the sorted side."""
    out = np.empty(len(order), dtype=np.int64)
    out[order] = np.cumsum(shared < words)
    return out


def matches(gram: np.ndarray, doc: np.ndarray, before: np.ndarray, w: ta.Words, h: np.ndarray, min_words: int, anchor: int) -> np.ndarray:
    """(row, places from the suffix's back to the match's start, and on to its end) of maximal runs of shared windows."""
    m, reach = len(gram), min_words - anchor
    at, after = w.first[:-1] + before, w.counts - before

    def side(step: int, width: int, size: np.ndarray) -> np.ndarray:
        k = np.arange(width)
        inside = k < size[:, None]
        where = at[:, None] + (k if step > 0 else -1 - k)
        return np.where(inside, h[np.where(inside, where, 0)], ta.U(0))

    right = neighbours(gram, side(1, min_words, after), after)
    left = neighbours(gram, side(-1, reach, before), before)
    hit = np.zeros((m, reach + 1), dtype=bool)
    for back in range(reach + 1):
        rows = np.flatnonzero((before >= back) & (after >= min_words - back))
        if len(rows) < 2:
            continue
        key = _classes(*right, min_words - back)[rows] * (m + 1) + _classes(*left, back)[rows]
        order = np.argsort(key, kind="stable")
        first = np.flatnonzero(np.concatenate([[True], np.diff(key[order]) != 0]))
        own = doc[rows[order]]
        several = np.minimum.reduceat(own, first) < np.maximum.reduceat(own, first)
        hit[rows[order], back] = np.repeat(several, np.diff(np.append(first, len(rows))))
    edge = np.diff(np.pad(hit, ((0, 0), (1, 1))).astype(np.int8), axis=1)
    row, low = np.nonzero(edge == 1)
    _, high = np.nonzero(edge == -1)
    return np.stack([row, high - 1, min_words - low], axis=1)


def _spans_of(table: pa.Table, min_words: int, anchor: int):
    docs = table.column("doc_id").combine_chunks()
    code = docs.dictionary_encode().indices.to_numpy()
    before, place = table.column("before").to_numpy().astype(np.int64), table.column("place").to_numpy().astype(np.int64)
    words = table.column("words").combine_chunks()
    for row, end, data, offsets in ta.slices(words, 1 << 40):
        w = ta.words(data, offsets, ta.NOT_SPACE)
        h = ta.distinct_hashes(w)
        found = matches(table.column("gram").to_numpy()[row:end], code[row:end], before[row:end], w, h, min_words, anchor)
        at = row + found[:, 0]
        yield pa.RecordBatch.from_arrays([docs.take(pa.array(at)), pa.array((place[at] - found[:, 1]).astype(np.int32)), pa.array((place[at] + found[:, 2]).astype(np.int32))], names=["doc_id", "start", "end"])


def _runs(window: np.ndarray, check: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, first, several): rows sorted by window and document, where each window begins, whether two documents have it."""
    order = np.lexsort((code, check, window))
    w, c, d = window[order], check[order], code[order]
    first = np.flatnonzero(np.concatenate([[True], (w[1:] != w[:-1]) | (c[1:] != c[:-1])])) if len(w) else np.empty(0, dtype=np.int64)
    last = np.append(first[1:], len(w)) - 1
    return order, first, d[first] != d[last]


def _intervals(docs: pa.Array, code: np.ndarray, place: np.ndarray, min_words: int) -> tuple[pa.Array, pa.Array, pa.Array]:
    """(doc_id, start, end) of the unions of windows at these places, document by document."""
    order = np.lexsort((place, code))
    code, place = code[order], place[order].astype(np.int64)
    new = np.concatenate([[True], (code[1:] != code[:-1]) | (place[1:] > place[:-1] + min_words)]) if len(place) else np.empty(0, dtype=bool)
    first = np.flatnonzero(new)
    end = place[np.append(first[1:], len(place)) - 1] if len(first) else first
    return docs.take(pa.array(order[first])), pa.array(place[first], pa.int32()), pa.array(end + min_words, pa.int32())


def windows(rows: DataFrame, known: np.ndarray | None, min_words: int, anchor: int, buckets: int) -> DataFrame:
    """(bucket, window, check, doc_id, place, until): every place whose window's minimiser has known first words, by lists.

    A task settles what its own texts settle: windows that two of them have are spans, in a list of a bucket below 0, and one
    place of each (-1) goes on as a witness; places of windows that one document of the task has go on to the
    window's bucket.  So a window of many documents is at most a place from each task.
    """
    kind = rows.schema["doc_id"].dataType
    handle = rows.sparkSession.sparkContext.broadcast(known)

    def run(batches):
        held: list = []
        for batch in batches:
            docs = batch.column(0)
            for row, end, data, offsets in ta.slices(batch.column(1)):
                w = ta.words(data, offsets, ta.NOT_SPACE)
                h = ta.word_hashes(w)
                start, place, grams = minimisers(h, w, min_words, anchor)
                start = start[_among(_known(batch, row, end, handle.value), grams[place].view(np.int64))] if len(start) else start
                if len(start):
                    text = w.text[start]
                    held.append((ta.gram_hashes(h, min_words)[start].view(np.int64), ta.gram_hashes(ta.mix(h, 0x51ED27), min_words)[start].view(np.int64), docs.take(pa.array(row + text)), (start - w.first[text]).astype(np.int32)))
                if sum(len(x[0]) for x in held) >= FLUSH:
                    yield settle(held)
                    held = []
        if held:
            yield settle(held)

    def settle(held: list) -> pa.RecordBatch:
        window, check, place = (np.concatenate([x[k] for x in held]) for k in (0, 1, 3))
        docs = pa.chunked_array([x[2] for x in held]).combine_chunks()
        code = docs.dictionary_encode().indices.to_numpy()
        order, first, several = _runs(window, check, code)
        size = np.diff(np.append(first, len(order)))
        mine = order[np.repeat(several, size)]
        spans = _intervals(docs.take(pa.array(mine)), code[mine], place[mine], min_words)
        on = np.concatenate([order[first[several]], order[~np.repeat(several, size)]])
        at = np.where(np.arange(len(on)) < several.sum(), np.int32(-1), place[on])
        bucket = (window[on].view(ta.U) % ta.U(buckets)).astype(np.int64)
        by = np.argsort(bucket, kind="stable")
        on, at, bucket = on[by], at[by], bucket[by]
        cut_ = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]])) if len(on) else np.empty(0, dtype=np.int64)
        # The first list holds the spans; lists of places follow, one for each bucket.
        n = len(spans[0])
        none = np.zeros(n, dtype=np.int64)
        values = [
            pa.array(np.concatenate([none, window[on]])),
            pa.array(np.concatenate([none, check[on]])),
            pa.concat_arrays([spans[0], docs.take(pa.array(on))]),
            pa.concat_arrays([spans[1], pa.array(at)]),
            pa.concat_arrays([spans[2], pa.array(at + np.int32(min_words))]),
        ]
        offsets = pa.array(np.concatenate([[0], n + cut_, [n + len(on)]] if len(on) else [[0, n]]).astype(np.int32))
        lists = [pa.ListArray.from_arrays(offsets, x) for x in values]
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([[-1 - TaskContext.get().partitionId() % buckets], bucket[cut_]]), pa.int32()), *lists], names=["bucket", "window", "check", "doc_id", "place", "until"])

    return rows.mapInArrow(run, f"bucket int, window array<long>, check array<long>, doc_id array<{kind.simpleString()}>, place array<int>, until array<int>")


def _met(table: pa.Table, min_words: int):
    """(doc_id, start, end) from the lists of whole buckets."""
    flat = {c: table.column(c).combine_chunks().flatten() for c in ("window", "check", "doc_id", "place", "until")}
    size = np.diff(table.column("window").combine_chunks().offsets.to_numpy())
    settled = np.repeat(table.column("bucket").to_numpy() < 0, size)
    docs, done = flat["doc_id"], np.flatnonzero(settled)
    if len(done):
        yield pa.RecordBatch.from_arrays([docs.take(pa.array(done)), flat["place"].take(pa.array(done)), flat["until"].take(pa.array(done))], names=["doc_id", "start", "end"])
    open_ = np.flatnonzero(~settled)
    if not len(open_):
        return
    code, place = docs.dictionary_encode().indices.to_numpy()[open_], flat["place"].to_numpy()[open_]
    order, first, several = _runs(flat["window"].to_numpy()[open_], flat["check"].to_numpy()[open_], code)
    # A witness stands for at least two documents.
    several |= np.minimum.reduceat(place[order], first) < 0
    mine = order[np.repeat(several, np.diff(np.append(first, len(order)))) & (place[order] >= 0)]
    yield pa.RecordBatch.from_arrays([*_intervals(docs.take(pa.array(open_[mine])), code[mine], place[mine], min_words)], names=["doc_id", "start", "end"])


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_words: int = MIN_WORDS, anchor: int = ANCHOR, max_live: int = MAX_LIVE, group: int = GROUP) -> DataFrame:
    """(doc_id, start_word, end_word, n_words): maximal unions of windows of min_words words that another document has too.

    Words are what lies between ASCII white space, lower-cased (A-Z).  Documents without such a passage
    give no row, nor do null ids, null, empty and short texts; a passage that only rows of the same id share
    is not repeated.  Repeated rows of an id give its spans once; an empty table gives none.  Extra columns are
    not read.
    """
    rows = _rows(docs, id_col, text_col)
    first = anchors(rows, min_words, anchor)
    live = cut(_shared(first, "gram"))
    few, many = live.where(F.col("n") <= group).select("gram"), live.where(F.col("n") > group).select("gram")
    kind = docs.schema[id_col].dataType

    def over(grams: DataFrame, make) -> DataFrame:
        """make() over the texts with the grams: broadcast if they are few, else joined to their texts."""
        if grams.limit(max_live + 1).count() <= max_live:
            return make(rows, _sorted(grams), min_words, anchor)
        own = first.join(grams, "gram").groupBy("doc_id").agg(F.collect_set("gram").alias("__live"))
        return make(rows.join(own, "doc_id").select("doc_id", "__text", "__live"), None, min_words, anchor)

    sparse = over(few, suffixes).repartition("gram").sortWithinPartitions("gram")
    spans = sparse.mapInArrow(by_group(lambda table: _spans_of(table, min_words, anchor), "gram"), f"doc_id {kind.simpleString()}, start int, end int")
    if not many.isEmpty():
        buckets = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        every = over(many, lambda *given: windows(*given, buckets)).repartition("bucket").sortWithinPartitions("bucket")
        spans = spans.union(every.mapInArrow(by_group(lambda table: _met(table, min_words), "bucket"), f"doc_id {kind.simpleString()}, start int, end int"))
    return _merged(spans, kind)


def _sorted(live: DataFrame) -> np.ndarray:
    return np.sort(np.fromiter((r["gram"] for r in live.toLocalIterator()), dtype=np.int64))


def _merged(spans: DataFrame, kind) -> DataFrame:
    """Spans of a document that overlap or touch, as one."""

    def run(batches):
        held = None
        for batch in batches:
            out = []
            for doc, start, end in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if held and held[0] == doc and start <= held[2]:
                    held[2] = max(held[2], end)
                    continue
                if held:
                    out.append(held)
                held = [doc, start, end]
            if out:
                yield batch_of(out)
        if held:
            yield batch_of([held])

    def batch_of(out: list) -> pa.RecordBatch:
        doc, a, b = zip(*out, strict=True)
        long = pa.int64()
        return pa.RecordBatch.from_arrays([pa.array(doc, arrow_kind(kind)), pa.array(a, long), pa.array(b, long), pa.array([y - x for x, y in zip(a, b, strict=True)], long)], names=["doc_id", "start_word", "end_word", "n_words"])

    return spans.repartition("doc_id").sortWithinPartitions("doc_id", "start").mapInArrow(run, f"doc_id {kind.simpleString()}, start_word long, end_word long, n_words long")
