"""Language-model scores from a log-frequency Bloom filter.

A bigram's count c is stored as its level, one more than the logarithm of c, by inserting the bigram
with each level up to it; a probe asks for level after level until one is absent.  The filter consists
of segments by key range, each as large as its insertions need.  Segments are counted, merged and built
by one task each and gathered in blocks of bounded size; a corpus whose filter exceeds a block is
scored in one pass per block, as a text's score is a sum over its tokens.  Lower-order counts are kept
exactly beside the filter, by the same segments: the baseline needs them.

Probability of w after v: (c(vw) + STRENGTH * p(w)) / (c(v) + STRENGTH), with p(w) the smoothed share of
w among the training tokens.  For c(vw) the filter's level gives the least count it stands for, which is never
more than the true one; a false positive is held under the exact c(w) and, where v is of the same block, c(v).
So a probability is at most 1, and those of all words after v add up to at most 1 but for false positives.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.llm import textarrays as ta
from erfocus.operators.durable import cut

LOG_BASE = 1.5
PROBES = 4
BITS_PER_INSERT = 8
STRENGTH = 200.0
BLOCK_BYTES = 256 << 20
BIN_BITS = 6
FLUSH = 2 << 20
END = np.uint64(0x5851F42D4C957F2D)
PARTIAL = "seg int, kind int, n int, keys binary, counts binary"
SEGMENT = "seg int, bits binary, words binary, counts binary, n_words long, n_tokens long, bytes long"


def level(c: np.ndarray) -> np.ndarray:
    return 1 + np.floor(np.log(np.maximum(c, 1)) / math.log(LOG_BASE) + 1e-9).astype(np.int64)


#: The least count of each level; level zero is absence.
LEAST = np.array([0.0, *(float(math.ceil(LOG_BASE ** (q - 1) - 1e-6)) for q in range(1, 140))])


def sequence(w: ta.Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(token, token before it, text) with each text's end token; the end token also stands before a text."""
    h = ta.word_hashes(w)
    n = len(w.counts)
    token = np.insert(h, w.first[1:], END)
    text = np.insert(w.text, w.first[1:], np.arange(n))
    before = np.empty_like(token)
    before[1:] = token[:-1]
    before[:1] = END
    return token, before, text


def pair_keys(before: np.ndarray, token: np.ndarray) -> np.ndarray:
    """Bigrams' keys; the high bits are those of the second word, so that both are of one block."""
    low = ta.U(BIN_BITS)
    return (token >> ta.U(64 - BIN_BITS)) << ta.U(64 - BIN_BITS) | ta.mix(before * ta.U(0x9E3779B97F4A7C15) + token, 3) >> low


def _pack(keys: np.ndarray) -> bytes:
    """Differences of sorted numbers, byte plane by byte plane: the high planes compress away."""
    d = np.diff(keys, prepend=keys.dtype.type(0))
    return d.view(np.uint8).reshape(len(d), -1).T.tobytes()


def _unpack(blob: bytes, n: int, kind) -> np.ndarray:
    planes = np.frombuffer(blob, dtype=np.uint8).reshape(-1, n)
    return np.cumsum(np.ascontiguousarray(planes.T).view(kind).ravel(), dtype=kind)


def _plain(counts: np.ndarray) -> bytes:
    return counts.astype("<u4").view(np.uint8).reshape(len(counts), 4).T.tobytes()


def _counts(blob: bytes, n: int) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(blob, dtype=np.uint8).reshape(4, n).T).view("<u4").ravel().astype(np.int64)


def summed(keys: np.ndarray, counts: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order, and how often each occurs; keys without counts are sorted where they lie."""
    if counts is None:
        keys.sort()
    else:
        order = np.argsort(keys, kind="stable")
        keys, counts = keys[order], counts[order]
    at = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.empty(0, dtype=np.int64)
    total = np.diff(np.append(at, len(keys))) if counts is None else np.add.reduceat(counts, at) if len(at) else np.empty(0, dtype=np.int64)
    return keys[at], total


def _partials(parts: list, seg_bits: int, kind: int):
    if not parts:
        return
    keys = np.concatenate(parts)
    parts.clear()
    keys, counts = summed(keys)
    segs = (keys >> ta.U(64 - seg_bits)).astype(np.int64)
    starts = np.flatnonzero(np.concatenate([[True], segs[1:] != segs[:-1]]))
    ends = np.append(starts[1:], len(keys))
    yield pa.RecordBatch.from_arrays(
        [
            pa.array(segs[starts], pa.int32()),
            pa.array(np.full(len(starts), kind), pa.int32()),
            pa.array(ends - starts, pa.int32()),
            pa.array([_pack(keys[a:b]) for a, b in zip(starts, ends, strict=True)], pa.binary()),
            pa.array([_plain(counts[a:b]) for a, b in zip(starts, ends, strict=True)], pa.binary()),
        ],
        names=["seg", "kind", "n", "keys", "counts"],
    )


def _build(pdf: pd.DataFrame) -> pd.DataFrame:
    found = {}
    for kind in (1, 2):
        own = pdf[pdf["kind"] == kind]
        keys = [_unpack(b, n, "<u8") for b, n in zip(own["keys"], own["n"], strict=True)]
        counts = [_counts(b, n) for b, n in zip(own["counts"], own["n"], strict=True)]
        found[kind] = summed(np.concatenate(keys), np.concatenate(counts)) if keys else (np.empty(0, dtype=ta.U), np.empty(0, dtype=np.int64))
    bits = filter_bits(*found[2])
    words, counts = found[1]
    return pd.DataFrame({"seg": [pdf["seg"].iloc[0]], "bits": [bits.tobytes()], "words": [words.tobytes()], "counts": [counts.astype("<u4" if counts.max(initial=0) < 1 << 32 else "<i8").tobytes()], "n_words": [len(words)], "n_tokens": [int(counts.sum())], "bytes": [len(bits) + 12 * len(words)]})


def _seed(keys: np.ndarray, q: int) -> np.ndarray:
    """What the places of keys at a level are made from."""
    return ta.mix(keys + ta.U(q * 0x9E3779B97F4A7C15 & (1 << 64) - 1), 5)


def _next(a: np.ndarray) -> np.ndarray:
    return a * ta.U(0xD1342543DE82EF95) + (a >> ta.U(32) | ta.U(1))


def filter_bits(keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
    levels = level(counts)
    size = max(64, -(-int(levels.sum()) * BITS_PER_INSERT // 64) * 64)
    on = np.zeros(size, dtype=bool)
    for q in range(1, int(levels.max(initial=0)) + 1):
        a = _seed(keys[levels >= q], q)
        for _ in range(PROBES):
            on[(a % ta.U(size)).astype(np.int64)] = True
            a = _next(a)
    return np.packbits(on, bitorder="little")


@dataclass
class Block:
    """Segments first to last: their filters end to end, and their words' exact counts in order."""

    seg_bits: int
    first: int
    base: np.ndarray
    size: np.ndarray
    bits: np.ndarray
    words: np.ndarray
    counts: np.ndarray

    def has(self, keys: np.ndarray) -> np.ndarray:
        seg = (keys >> ta.U(64 - self.seg_bits)).astype(np.int64) - self.first
        return (seg >= 0) & (seg < len(self.size))

    def exact(self, words: np.ndarray) -> np.ndarray:
        """Counts of words of the block."""
        if not len(self.words):
            return np.zeros(len(words), dtype=np.int64)
        distinct, back = np.unique(words, return_inverse=True)
        at = np.minimum(np.searchsorted(self.words, distinct), len(self.words) - 1)
        return np.where(self.words[at] == distinct, self.counts[at], 0).astype(np.int64)[back]

    def counted(self, keys: np.ndarray) -> np.ndarray:
        """Least counts of bigrams of the block, by probes for level after level."""
        seg = (keys >> ta.U(64 - self.seg_bits)).astype(np.int64) - self.first
        base, size = self.base[seg], self.size[seg]
        found = np.zeros(len(keys), dtype=np.int64)
        asked = np.flatnonzero(size > 0)
        q = 1
        while len(asked) and q < len(LEAST):
            a = _seed(keys[asked], q)
            for _ in range(PROBES):  # of keys that passed the probes before
                at = base[asked] + (a % size[asked].astype(ta.U)).astype(np.int64)
                hit = (self.bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1
                asked, a = asked[hit], _next(a[hit])
            found[asked] = q
            q += 1
        return LEAST[found]


def held_out(id_col: str):
    """Documents whose id's text has a CRC-32 of remainder 1 modulo 5; a null id's text is empty."""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 1


def train(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Segments of the model of all texts: filter, words, exact counts.  Null is the empty text."""
    size = docs.agg(F.sum(F.octet_length(text_col)).alias("n")).first()["n"] or 0
    seg_bits = min(24, BIN_BITS + 2 + max(0, (size // (1 << 31)).bit_length()))

    def run(batches):
        pairs, singles, held = [], [], 0
        for batch in batches:
            for _, _, data, offsets in ta.slices(batch.column(0)):
                token, before, _ = sequence(ta.words(data, offsets, ta.NOT_SPACE))
                pairs.append(pair_keys(before, token))
                singles.append(token)
                held += len(token)
                if held >= FLUSH:
                    yield from _partials(pairs, seg_bits, 2)
                    yield from _partials(singles, seg_bits, 1)
                    held = 0
        yield from _partials(pairs, seg_bits, 2)
        yield from _partials(singles, seg_bits, 1)

    partial = docs.select(text_col).mapInArrow(run, PARTIAL)
    return cut(partial.groupBy("seg").applyInPandas(_build, SEGMENT).withColumn("seg_bits", F.lit(seg_bits)))


def blocks(model: DataFrame, limit: int = BLOCK_BYTES) -> list[tuple[int, int]]:
    """Ranges of segments, cut between bins, of at most limit bytes unless one bin has more."""
    bits = model.select("seg_bits").first()
    if bits is None:
        return []
    shift = bits["seg_bits"] - BIN_BITS
    sizes = {r["bin"]: r["n"] for r in model.groupBy(F.shiftright("seg", shift).alias("bin")).agg(F.sum("bytes").alias("n")).collect()}
    out, first, held = [], 0, 0
    for b in range(1 << BIN_BITS):
        n = sizes.get(b, 0)
        if held and held + n > limit:
            out.append((first << shift, b << shift))
            first, held = b, 0
        held += n
    return [*out, (first << shift, 1 << shift + BIN_BITS)]


def gather(model: DataFrame, first: int, last: int) -> Block:
    """A block, segment by segment, so that the driver holds little more than the block."""
    own = model.where((F.col("seg") >= first) & (F.col("seg") < last))
    total = own.agg(F.sum(F.octet_length("bits")).alias("b"), F.sum("n_words").alias("w"), F.max("seg_bits").alias("s")).first()
    base, size = np.zeros(last - first, dtype=np.int64), np.zeros(last - first, dtype=np.int64)
    bits, words, counts = np.zeros(total["b"] or 0, dtype=np.uint8), np.zeros(total["w"] or 0, dtype=ta.U), np.zeros(total["w"] or 0, dtype=np.uint32)
    starts = {r["seg"]: (r["b"], r["w"]) for r in own.select("seg", F.octet_length("bits").alias("b"), F.col("n_words").alias("w")).toLocalIterator()}
    at = w = 0
    where = {}
    for seg in sorted(starts):
        where[seg] = (at, w)
        at, w = at + starts[seg][0], w + starts[seg][1]
    for r in own.select("seg", "bits", "words", "counts", "n_words").toLocalIterator():
        at, w = where[r["seg"]]
        bits[at : at + len(r["bits"])] = np.frombuffer(r["bits"], dtype=np.uint8)
        base[r["seg"] - first], size[r["seg"] - first] = 8 * at, 8 * len(r["bits"])
        words[w : w + r["n_words"]] = np.frombuffer(r["words"], dtype=ta.U)
        own_counts = np.frombuffer(r["counts"], dtype="<u4" if len(r["counts"]) == 4 * r["n_words"] else "<i8")
        if own_counts.dtype.itemsize > counts.dtype.itemsize:
            counts = counts.astype(np.int64)
        counts[w : w + r["n_words"]] = own_counts
    return Block(total["s"] or BIN_BITS, first, base, size, bits, words, counts)


def _scored(rows: DataFrame, block: Block, keys: list[str], n_train: int, n_distinct: int, kinds: list[str]) -> DataFrame:
    handle = rows.sparkSession.sparkContext.broadcast(block)
    norm = n_train + 0.5 * (n_distinct + 1)

    def run(batches):
        own = handle.value
        for batch in batches:
            out = []
            for row, end, data, offsets in ta.slices(batch.column(batch.num_columns - 1)):
                token, before, text = sequence(ta.words(data, offsets, ta.NOT_SPACE))
                n, part = end - row, np.bincount(text, minlength=end - row)
                mine = own.has(token)
                c = own.exact(token[mine])
                share = (c + 0.5) / norm
                theirs = own.has(before)
                history = np.full(len(token), np.inf)
                history[theirs] = own.exact(before[theirs])
                c2 = np.minimum(np.minimum(own.counted(pair_keys(before[mine], token[mine])), c), history[mine])
                add = lambda v, t: np.bincount(t, weights=v, minlength=n)  # noqa: B023, E731
                score = add(np.log10(c2 + STRENGTH * share), text[mine])
                score -= add(np.log10(history[theirs] + STRENGTH), text[theirs])
                out.append((part, add(c > 0, text[mine]), add(np.log10(share), text[mine]), score))
            cols = [np.concatenate(x) for x in zip(*out, strict=True)] if out else [np.empty(0)] * 4
            yield pa.RecordBatch.from_arrays(
                [batch.column(i) for i in range(len(keys))] + [pa.array(cols[0].astype(np.int64)), pa.array(cols[1].astype(np.int64)), pa.array(cols[2].astype(float)), pa.array(cols[3].astype(float))],
                names=[*keys, "n_tokens", "n_known", "base_score", "score"],
            )

    schema = ", ".join(f"{k} {t}" for k, t in zip(keys, kinds, strict=True))
    return rows.mapInArrow(run, f"{schema}, n_tokens long, n_known long, base_score double, score double")


def score(docs: DataFrame, model: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row.

    Null and empty texts are the end token alone; an empty table gives no row.  Repeated rows each give a row; a
    null id counts as the empty text where the split asks for it; extra columns are not read.  Without training
    texts all counts are zero.
    """
    total = model.agg(F.sum("n_tokens").alias("n"), F.sum("n_words").alias("v")).first()
    n, v = total["n"] or 0, total["v"] or 0
    kind = docs.schema[id_col].dataType.simpleString()
    rows = docs.select(F.col(id_col).alias("doc_id"), held_out(id_col).alias("held_out"), F.col(text_col).alias("__text"))
    parts = blocks(model, block_bytes) or [(0, 1 << BIN_BITS)]
    if len(parts) == 1:
        found = _scored(rows, gather(model, *parts[0]) if v else empty_block(), ["doc_id", "held_out"], n, v, [kind, "boolean"])
    else:
        keyed = rows.select("doc_id", "held_out", F.sha2(F.coalesce("__text", F.lit("")), 256).alias("__key"), "__text")
        sums = None
        for i, (a, b) in enumerate(parts):
            p = _scored(keyed, gather(model, a, b), ["doc_id", "held_out", "__key"], n, v, [kind, "boolean", "string"]).withColumn("__block", F.lit(i))
            sums = p if sums is None else sums.union(p)
        one = sums.groupBy("doc_id", "held_out", "__key", "__block").agg(*[F.max(c).alias(c) for c in ("n_tokens", "n_known", "base_score", "score")], F.count(F.lit(1)).alias("copies"))
        summed_ = one.groupBy("doc_id", "held_out", "__key").agg(F.max("copies").alias("copies"), F.max("n_tokens").alias("n_tokens"), *[F.sum(c).alias(c) for c in ("n_known", "base_score", "score")])
        found = summed_.withColumn("__i", F.explode(F.sequence(F.lit(1).cast("long"), "copies")))
    return found.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", F.least("score", F.lit(0.0)).alias("score"))


def empty_block() -> Block:
    none = np.zeros(1 << BIN_BITS, dtype=np.int64)
    return Block(BIN_BITS, 0, none, none, np.zeros(0, dtype=np.uint8), np.zeros(0, dtype=ta.U), np.zeros(0, dtype=np.int64))
