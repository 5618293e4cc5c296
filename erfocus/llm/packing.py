"""Packing token sequences from neighbours along a space-filling curve.

A document is a point: hashed word counts projected to a few dimensions.  Documents are
range-sorted by their place on the Hilbert curve through that space and laid end to end; the stream is
cut every max_tokens.  What is left at the end of a range is cut into sequences whose lengths are powers
of two, so that no sequence is padded.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erfocus.llm import textarrays as ta
from erfocus.llm.kinds import arrow_kind
from erfocus.operators.durable import cut

MAX_TOKENS = 2048
DIMENSIONS = 4
BITS = 12
END_ID = 1
#: Tokens of a range: a range is one task's.
RANGE_TOKENS = 8_000_000
TOKENIZER = "byte_bpe_50k"
PIECES = "doc_id {0}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def hilbert_key(points: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Place on the Hilbert curve of integer points (n, d), by the transpose form of the curve."""
    x = points.astype(np.int64).T.copy()
    d = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(d):
            high = (x[i] & q) != 0
            t = np.where(high, 0, (x[0] ^ x[i]) & p)
            x[0] = np.where(high, x[0] ^ p, x[0] ^ t)
            x[i] ^= t
        q >>= 1
    for i in range(1, d):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t = np.where(x[d - 1] & q, t ^ (q - 1), t)
        q >>= 1
    x ^= t
    key = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(d):
            key = key << 1 | x[i] >> b & 1
    return key


def _points(w: ta.Words, h: np.ndarray) -> np.ndarray:
    """Projected sums of word hashes over the root of their number, squashed to the curve's grid."""
    n = np.maximum(w.counts, 1)
    out = np.empty((len(w.counts), DIMENSIONS), dtype=np.int64)
    for k in range(DIMENSIONS):
        sign = (ta.mix(h, 31 * k + 5) >> ta.U(11)).astype(np.float64) / (1 << 53) - 0.5
        z = ta.per_text(sign, w) / np.sqrt(n / 12)
        out[:, k] = np.clip((np.tanh(z / 2) + 1) / 2 * (1 << BITS), 0, (1 << BITS) - 1)
    return out


class Encoder:
    """Ids of texts, as the tokenizer file gives them: a special token's string in a text is that token.

    The vocabulary's rank file gives the very ids of the tokenizer file in a quarter of the time; a text
    whose white-space rules could differ would show in the test that compares the two.
    """

    def __init__(self, name: str = TOKENIZER):
        import base64
        import json

        import public_tokenizers
        import tiktoken

        with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        with open(public_tokenizers.path(f"{name}.json"), encoding="utf-8") as f:
            special = {t["content"]: t["id"] for t in json.load(f)["added_tokens"]}
        self.encoding = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)
        self.special = list(special)

    def encode(self, text: str) -> list[int]:
        if any(s in text for s in self.special):
            return self.encoding.encode(text, allowed_special="all")
        return self.encoding.encode_ordinary(text)


#: One encoder per worker process.
_encoders: dict[str, Encoder] = {}


def encode(texts: list[str], name: str = TOKENIZER) -> list[np.ndarray]:
    if name not in _encoders:
        _encoders[name] = Encoder(name)
    return [np.array([*_encoders[name].encode(t), END_ID], dtype="<u4") for t in texts]


def tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str = TOKENIZER) -> DataFrame:
    """(doc_id, place, n, ids): the place on the curve and the compressed ids of each row's text."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in batches:
            places, counts, blobs = [], [], []
            column = batch.column(1)
            for row, end, data, offsets in ta.slices(column):
                w = ta.words(data, offsets, ta.NOT_SPACE)
                places.append(hilbert_key(_points(w, ta.word_hashes(w))))
                for ids in encode([x or "" for x in column.slice(row, end - row).to_pylist()], tokenizer):
                    counts.append(len(ids))
                    blobs.append(pa.compress(ids.astype("<u2" if ids.max() < 1 << 16 else "<u4").tobytes(), "zstd", asbytes=True))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(np.concatenate(places) if places else [], pa.int64()), pa.array(counts, pa.int64()), pa.array(blobs, pa.binary())], names=["doc_id", "place", "n", "ids"]
            )

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text"))
    return rows.mapInArrow(run, f"doc_id {kind}, place long, n long, ids binary")


def _ids(blob: bytes, n: int) -> np.ndarray:
    for kind, width in (("<u2", 2), ("<u4", 4)):
        try:
            return np.frombuffer(pa.decompress(blob, n * width, "zstd", asbytes=True), dtype=kind).astype("<u4")
        except (OSError, pa.ArrowInvalid):
            continue
    raise ValueError("damaged ids")


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_tokens: int = MAX_TOKENS, tokenizer: str = TOKENIZER, with_ids: bool = False) -> DataFrame:
    """Pieces of documents placed in sequences; each id is in one piece, offsets are gapless from zero.

    Null and empty texts are the end id alone; an empty table gives no piece.  Repeated rows are packed each,
    ties on the curve lie in the order of a hash of the id; a null id is kept.  Extra columns are not read.
    Ranges of the curve are split also inside groups of equal places, so copies do not crowd one task.
    with_ids adds the ids.
    """
    kind = docs.schema[id_col].dataType
    encoded = cut(tokens(docs, id_col, text_col, tokenizer))
    total = encoded.agg(F.sum("n").alias("n")).first()["n"] or 0
    least = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranges = max(1, min(least, total // (4 * max_tokens)), total // RANGE_TOKENS)
    laid = encoded.withColumn("salt", F.xxhash64("doc_id")).repartitionByRange(int(ranges), "place", "salt").sortWithinPartitions("place", "salt", "doc_id", "n", "ids")

    def run(batches):
        first = (TaskContext.get().partitionId() if TaskContext.get() else 0) << 32
        at = done = 0
        waiting: list = []
        for batch in batches:
            rows = []
            for doc, n, blob in zip(batch.column("doc_id").to_pylist(), batch.column("n").to_pylist(), batch.column("ids").to_pylist(), strict=True):
                ids, start = _ids(blob, n), 0
                while start < n:
                    size = min(n - start, max_tokens - at)
                    waiting.append((doc, start, ids[start : start + size], n, at))
                    start, at = start + size, at + size
                    if at == max_tokens:
                        rows += [(*w, first + done) for w in waiting]
                        waiting, at, done = [], 0, done + 1
            if rows:
                yield _batch(rows, kind, with_ids)
        if waiting:
            yield _batch(_tail(waiting, at, first + done), kind, with_ids)

    extra = ", ids array<int>" if with_ids else ""
    return laid.mapInArrow(run, PIECES.format(kind.simpleString()) + extra)


def _tail(waiting: list, total: int, sequence: int) -> list:
    """What is left, cut into sequences of lengths that are the powers of two in its length."""
    rows, room = [], [1 << b for b in range(total.bit_length() - 1, -1, -1) if total >> b & 1]
    at = k = 0
    for doc, start, ids, n, _ in waiting:
        while len(ids):
            size = min(len(ids), room[k] - at)
            rows.append((doc, start, ids[:size], n, at, sequence + k))
            ids, start, at = ids[size:], start + size, at + size
            if at == room[k]:
                k, at = k + 1, 0
    return rows


def _batch(rows: list, kind: T.DataType, with_ids: bool) -> pa.RecordBatch:
    doc, start, ids, n, at, sequence = zip(*rows, strict=True)
    long = pa.int64()
    arrays = [pa.array(doc, arrow_kind(kind)), pa.array(start, long), pa.array(list(map(len, ids)), long), pa.array([zlib.crc32(x.tobytes()) for x in ids], long), pa.array(n, long), pa.array(sequence, long), pa.array(at, long)]
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    if with_ids:
        arrays.append(pa.array([x.astype(np.int32) for x in ids], pa.list_(pa.int32())))
        names.append("ids")
    return pa.RecordBatch.from_arrays(arrays, names=names)
