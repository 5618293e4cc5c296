"""SimHash near-duplicates: fingerprints, exact tiled comparison, components.

Distinct fingerprints are dealt to tiles by keys that documents to be linked must share, so that no
tile pair of the whole table is compared: bands of the fingerprint itself (for r differing bits r + 1
bands; no link is lost), or, for long fingerprints at a wide radius, least shingle hashes.  The fingerprints
of a key are laid out by population count and cut into tiles; each pair of tiles is a task of its own, and
pairs of tiles whose counts differ beyond the radius are skipped.  In a task numpy compares chunk by
chunk, again without those chunk pairs.  A task returns a star per group it found, never its pairs.  Links at a wide radius only
propose: the nodes of a group they make come together again and are compared by their sets of shingles.
"""

from __future__ import annotations

import itertools
from fractions import Fraction

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erfocus.llm import textarrays as ta
from erfocus.llm.groups import by_group, starts
from erfocus.llm.kinds import unused
from erfocus.operators.components import connected_components
from erfocus.operators.durable import cut, held, sized

TILE = 1024
CHUNK = 512
SMALL = 48
SET_BLOCK = 1 << 20
#: What a task is dealt by: a key, and a pair of its tiles.
TASK = ("key", "p", "q")
SCHEMA = "node long, fp binary, pop int, keys array<long>"


def majority(hashes: np.ndarray) -> np.ndarray:
    """Rows of 8-byte lanes -> bytes; a bit is set if more than half the rows have it."""
    n, lanes = hashes.shape
    total = np.zeros(lanes * 64, dtype=np.int64)
    rows = hashes.astype(">u8").view(np.uint8).reshape(n, lanes * 8)
    for i in range(0, n, 1 << 14):
        total += np.unpackbits(rows[i : i + (1 << 14)], axis=1).sum(axis=0, dtype=np.int32)
    return np.packbits(2 * total > n)


def band_keys(fp: int, bands: int) -> list[int]:
    """The fingerprint's bits in bands of about the same width, each with its band's number."""
    edges = [64 * k // bands for k in range(bands + 1)]
    return [k << 56 ^ (fp >> a & (1 << b - a) - 1) for k, (a, b) in enumerate(itertools.pairwise(edges))]


def fingerprint_64(text: str | None, width: int) -> int:
    """Of XXH64 (seed 42) of word shingles of the lower-cased (A-Z) text; zero without words."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(ta.LOWER_BYTES).split()
    if not words:
        return 0
    n = max(1, len(words) - width + 1)
    if n == 1:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)
    shingles = map(b" ".join, zip(*(words[k:] for k in range(width)), strict=False))
    hashes = np.fromiter(map(xxhash.xxh64_intdigest, shingles, itertools.repeat(42)), dtype=ta.U, count=n)
    return int.from_bytes(majority(hashes[:, None]).tobytes(), "big")


def banded_sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, radius: int = 2) -> DataFrame:
    """(doc_id, node, fp, pop, keys) by the 64-bit majority of XXH64 shingle hashes; pop: bits set."""
    id_field = docs.schema[id_col]

    def run(batches):
        for pdf in batches:
            fps = [fingerprint_64(t, width) for t in pdf["__text"]]
            yield pd.DataFrame(
                {
                    "doc_id": pdf["doc_id"],
                    "node": np.array(fps, dtype=ta.U).view(np.int64),
                    "fp": [f.to_bytes(8, "big") for f in fps],
                    "pop": np.array([f.bit_count() for f in fps], dtype=np.int32),
                    "keys": [band_keys(f, radius + 1) for f in fps],
                }
            )

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text"))
    rows = rows.withColumn("doc_id", F.col("doc_id").cast("string"))  # pandas would make floats of integers with nulls
    return rows.mapInPandas(run, f"doc_id string, {SCHEMA}").withColumn("doc_id", F.col("doc_id").cast(id_field.dataType))


def shingle_sets(w: ta.Words, width: int) -> list[np.ndarray]:
    """Each text's distinct shingle hashes in order; a text of fewer words than the width is one shingle."""
    h = ta.word_hashes(w)
    grams = ta.gram_hashes(h, width)
    out = []
    for n, a, b in zip(w.counts.tolist(), w.first[:-1].tolist(), w.first[1:].tolist(), strict=True):
        out.append(np.unique(grams[a : a + n - width + 1] if n >= width else ta.gram_hashes(h[a:b], n) if n else h[:0]))
    return out


def set_node(own: np.ndarray) -> int:
    """A 64-bit hash of a set of shingles; zero of the empty one."""
    return int((ta.mix(own, 5).sum(dtype=ta.U) ^ ta.mix(np.array([len(own)], dtype=ta.U), 9)).view(np.int64)[0]) if len(own) else 0


def minhash_sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, lanes: int = 4, n_keys: int = 8) -> DataFrame:
    """(doc_id, node, fp, pop, keys) by the majority of lanes * 64 hash bits; keys: least shingle hashes.

    Nodes are sets of shingles, so that only texts of the same set share one.  Documents of similarity s
    (shared shingles by all) miss a common key with a chance of (1 - s) ** n_keys.
    """
    id_field = docs.schema[id_col]

    def run(batches):
        salts = [ta.U(2 * k * 0x9E3779B97F4A7C15 + 1 & (1 << 64) - 1) for k in range(1, n_keys + 1)]
        for batch in batches:
            nodes, fps, pops, keys = [], [], [], []
            for _, _, data, offsets in ta.slices(batch.column(1)):
                for own in shingle_sets(ta.words(data, offsets, ta.NOT_SPACE), width):
                    if not len(own):
                        nodes.append(0)
                        fps.append(bytes(8 * lanes))
                        pops.append(0)
                        keys.append([0])
                        continue
                    fp = majority(np.stack([ta.mix(own, 77 * j) for j in range(lanes)], axis=1))
                    fps.append(fp.tobytes())
                    nodes.append(set_node(own))
                    pops.append(int.from_bytes(fps[-1], "big").bit_count())
                    keys.append([int(ta.mix((own * s) ^ (own >> ta.U(29))).min().view(np.int64)) for s in salts])
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(nodes, pa.int64()), pa.array(fps, pa.binary()), pa.array(pops, pa.int32()), pa.array(keys, pa.list_(pa.int64()))],
                names=["doc_id", "node", "fp", "pop", "keys"],
            )

    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text"))
    return rows.mapInArrow(run, f"doc_id {id_field.dataType.simpleString()}, {SCHEMA}")


def _near(fp: np.ndarray, pop: np.ndarray, i: np.ndarray, j: np.ndarray, radius: int) -> np.ndarray:
    """Which of the pairs are within the radius."""
    close = np.abs(pop[i] - pop[j]) <= radius
    out = np.zeros(len(i), dtype=bool)
    i, j = i[close], j[close]
    out[close] = np.bitwise_count(fp[i] ^ fp[j]).sum(axis=1, dtype=np.int32) <= radius
    return out


def tile_labels(fp: np.ndarray, bounds: np.ndarray, radius: int) -> np.ndarray:
    """Least row linked to each row, by rows' groups [bounds[g], bounds[g + 1]); groups by population count sorted."""
    n = len(fp)
    pop = np.bitwise_count(fp).sum(axis=1, dtype=np.int32)
    sizes = np.diff(bounds)
    group_end = np.repeat(bounds[1:], sizes)
    small = np.repeat(sizes <= SMALL, sizes)
    links_a, links_b = [], []
    rows = np.flatnonzero(small)
    for d in range(1, SMALL):
        rows = rows[rows + d < group_end[rows]]
        if not len(rows):
            break
        near = _near(fp, pop, rows, rows + d, radius)
        links_a.append(rows[near])
        links_b.append(rows[near] + d)
    label = ta.settled(n, np.concatenate(links_a), np.concatenate(links_b)) if links_a else np.arange(n)
    for g in np.flatnonzero(sizes > SMALL).tolist():
        a, b = int(bounds[g]), int(bounds[g + 1])
        label[a:b] = a + _chunked(fp[a:b], pop[a:b], radius)
    return label


def _chunked(fp: np.ndarray, pop: np.ndarray, radius: int) -> np.ndarray:
    n = len(fp)
    label = np.arange(n)
    for a in range(0, n, CHUNK):
        for b in range(a, n, CHUNK):
            if pop[b] - pop[min(a + CHUNK, n) - 1] > radius:
                break
            left, right = fp[a : a + CHUNK], fp[b : b + CHUNK]
            apart = np.zeros((len(left), len(right)), dtype=np.int16)
            for k in range(fp.shape[1]):
                apart += np.bitwise_count(left[:, k, None] ^ right[None, :, k])
            near = apart <= radius
            near &= label[a : a + CHUNK, None] != label[None, b : b + CHUNK]
            if near.any():
                i, j = np.nonzero(near)
                la, lb = label[a + i], label[b + j]
                links = np.unique(np.stack([la, lb], axis=1), axis=0)
                label = ta.settled(n, links[:, 0], links[:, 1])[label]
    return label


def linked(sketches: DataFrame, radius: int, tile: int = TILE) -> DataFrame:
    """(a, b): stars over nodes whose fingerprints share a key and differ in at most radius bits."""
    nodes = sketches.groupBy("node").agg(F.first("fp").alias("fp"), F.first("pop").alias("pop"), F.first("keys").alias("keys"))
    dealt = cut(nodes.select("node", "fp", "pop", F.explode("keys").alias("key")))
    placed = _placed(dealt, tile, radius).drop("pop").repartition(*TASK).sortWithinPartitions(*TASK)
    return placed.mapInArrow(by_group(lambda table: _stars(table, radius), *TASK), "a long, b long")


def _placed(dealt: DataFrame, tile: int, radius: int) -> DataFrame:
    """dealt's rows of keys of several nodes by (key, p, q): a tile pair is a task of its own.

    A key of up to tile rows is one tile.  A larger one is laid out in the order of population counts and cut
    every tile rows, also inside a count; a row goes only to the tile pairs whose counts differ by no more than the
    radius, so all others are skipped before anything is shipped.
    """
    rest = [c for c in dealt.columns if c not in ("key", "pop")]
    counts = dealt.groupBy("key").count()
    large = cut(counts.where(F.col("count") > tile).select("key"))
    if large.isEmpty():
        few = counts.where("count > 1").select("key")
        return dealt.join(few, "key").select("key", F.lit(0).alias("p"), F.lit(0).alias("q"), "pop", *rest)
    large = sized(large)
    others = dealt.join(large, "key", "left_anti")
    few = others.groupBy("key").count().where("count > 1").select("key")
    small = others.join(few, "key").select("key", F.lit(0).alias("p"), F.lit(0).alias("q"), "pop", *rest)
    mine = dealt.join(large, "key")
    cells = cut(_cells(mine))
    reach = held(tile_reach(cells, tile, radius))
    at = F.col("before") + F.pmod(F.xxhash64("node", "key"), F.col("n"))
    placed = mine.join(sized(cells), ["key", "pop"]).withColumn("part", F.floor(at / tile).cast("int")).join(reach, ["key", "part"])
    placed = placed.withColumn("other", F.explode(F.sequence("low", "high")))
    return small.union(placed.select("key", F.least("part", "other").alias("p"), F.greatest("part", "other").alias("q"), "pop", *rest))


def _cells(rows: DataFrame) -> DataFrame:
    """(key, pop, n, before): rows of each population count, and those of lower ones."""
    cells = rows.groupBy("key", "pop").agg(F.count(F.lit(1)).alias("n"))
    return cells.withColumn("before", F.sum("n").over(Window.partitionBy("key").orderBy("pop")) - F.col("n"))


def tile_reach(cells: DataFrame, tile: int, radius: int) -> DataFrame:
    """(key, part, low, high): the tiles from low to high may hold a fingerprint within the radius of one in part."""
    first, last = F.floor(F.col("before") / tile).cast("int"), F.floor((F.col("before") + F.col("n") - 1) / tile).cast("int")
    ends = cells.select("key", "pop", first.alias("first"), last.alias("last"))
    parts = ends.select("key", "pop", F.explode(F.sequence("first", "last")).alias("part")).groupBy("key", "part").agg(F.min("pop").alias("least"), F.max("pop").alias("most"))
    near = parts.join(ends, "key").where((F.col("pop") <= F.col("most") + radius) & (F.col("pop") >= F.col("least") - radius))
    return near.groupBy("key", "part").agg(F.min("first").alias("low"), F.max("last").alias("high"))


def _stars(table: pa.Table, radius: int):
    first = starts(table, TASK)
    fp = table.column("fp").combine_chunks()
    fp = fp.cast(pa.large_binary())
    where = np.frombuffer(fp.buffers()[1], dtype=np.int64)[fp.offset : fp.offset + len(fp) + 1]
    fp = np.frombuffer(fp.buffers()[2], dtype=np.uint8)[where[0] : where[-1]].copy().view(ta.U).reshape(table.num_rows, -1)
    pop = np.bitwise_count(fp).sum(axis=1, dtype=np.int32)
    group = np.repeat(np.arange(len(first)), np.diff(np.append(first, table.num_rows)))
    order = np.lexsort((pop, group))
    node = table.column("node").to_numpy()[order]
    label = tile_labels(fp[order], np.append(first, table.num_rows), radius)
    mine = np.flatnonzero((label != np.arange(len(label))) & (node != node[label]))
    yield pa.RecordBatch.from_arrays([pa.array(node[mine]), pa.array(node[label[mine]])], names=["a", "b"])


def exact_labels(fp: np.ndarray, sets: list[np.ndarray], radius: int, similarity: float) -> np.ndarray:
    """Least row reachable from each row by pairs within the radius whose sets are of the similarity (Jaccard) at least."""
    n, size = len(sets), np.array([len(s) for s in sets])
    least = Fraction(str(similarity))
    up, down = least.numerator, least.denominator
    label = np.full(n, -1)
    for seed in range(n):
        if label[seed] >= 0:
            continue
        label[seed], todo = seed, [seed]
        while todo:
            x = todo.pop()
            near = np.flatnonzero((label < 0) & (np.minimum(size, size[x]) * down >= np.maximum(size, size[x]) * up))
            near = near[np.bitwise_count(fp[near] ^ fp[x]).sum(axis=1, dtype=np.int32) <= radius]
            block = np.cumsum(size[near]) // SET_BLOCK
            for k in np.unique(block):
                some = near[block == k]
                joined = np.concatenate([sets[i] for i in some])
                at = np.minimum(np.searchsorted(sets[x], joined), size[x] - 1)
                common = np.add.reduceat(sets[x][at] == joined, np.cumsum(size[some]) - size[some], dtype=np.int64)
                some = some[common * down >= (size[some] + size[x] - common) * up]
                label[some] = seed
                todo.extend(some.tolist())
    return label


def _exact_stars(table: pa.Table, radius: int, similarity: float):
    bounds = np.append(starts(table, TASK), table.num_rows)
    node = table.column("node").to_numpy()
    for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        part = table.slice(a, b - a)
        fp = np.frombuffer(b"".join(part.column("fp").to_pylist()), dtype=ta.U).reshape(b - a, -1)
        sets = [np.frombuffer(s, dtype=ta.U) for s in part.column("shingles").to_pylist()]
        label = a + exact_labels(fp, sets, radius, similarity)
        mine = a + np.flatnonzero(node[a:b] != node[label])
        yield pa.RecordBatch.from_arrays([pa.array(node[mine]), pa.array(node[label[mine - a]])], names=["a", "b"])


def verified(rows: DataFrame, sketches: DataFrame, candidates: DataFrame, id_col: str, text_col: str, width: int, radius: int, similarity: float, tile: int = TILE) -> DataFrame:
    """(a, b): stars over nodes whose shingle sets are of the similarity at least, within groups of candidate links.

    A group's nodes come together once with their shingles; a group over the tile comes in parts, each pair of
    which is a task's.
    """
    nodes = sketches.groupBy("node").agg(F.first("fp").alias("fp"), F.first("pop").alias("pop"), F.min("doc_id").alias("__id"))
    dealt = connected_components(candidates).withColumnRenamed("component", "key").join(nodes, "node")
    placed = cut(_placed(cut(dealt), tile, radius))
    texts = rows.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("__text"))
    members = texts.join(sized(placed, 200_000), F.col("doc_id") == F.col("__id")).select("__text", "key", "p", "q", "node", "fp")

    def run(batches):
        for batch in batches:
            nodes = batch.column(4).to_numpy()
            for row, end, data, offsets in ta.slices(batch.column(0)):
                sets = shingle_sets(ta.words(data, offsets, ta.NOT_SPACE), width)
                # Rows of the same id may have other texts.
                mine = np.flatnonzero([set_node(s) == n for s, n in zip(sets, nodes[row:end].tolist(), strict=True)])
                out = batch.slice(row, end - row).take(pa.array(mine))
                yield pa.RecordBatch.from_arrays([*out.columns[1:], pa.array([sets[k].tobytes() for k in mine], pa.binary())], names=["key", "p", "q", "node", "fp", "shingles"])

    shingled = members.mapInArrow(run, "key long, p int, q int, node long, fp binary, shingles binary")
    return shingled.repartition(*TASK).sortWithinPartitions(*TASK).mapInArrow(by_group(lambda table: _exact_stars(table, radius, similarity), *TASK), "a long, b long")


def components(sketches: DataFrame, radius: int) -> DataFrame:
    """(doc_id, fp, component_id): the smallest id among documents reachable by links."""
    sketches = cut(sketches)
    return labelled(sketches, cut(linked(sketches, radius)))


def labelled(sketches: DataFrame, links: DataFrame) -> DataFrame:
    roots = connected_components(links)
    nodes = sketches.groupBy("node").agg(F.min("doc_id").alias("least"))
    placed = nodes.join(roots, "node", "left").select("node", "least", F.coalesce("component", "node").alias("root"))
    least = placed.groupBy("root").agg(F.min("least").alias("component_id"))
    named = placed.select("node", "root").join(least, "root").select("node", "component_id")
    return sketches.select("doc_id", "node", "fp").join(named, "node").select("doc_id", "fp", "component_id")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, radius: int = 2) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row; links: fingerprints of at most radius differing bits.

    Null and empty texts have the fingerprint zero, linked like any other; texts of fewer words than
    the width are one shingle.  Repeated rows each give a row; a null id gets a component but never
    names one (a component of null ids alone has a null id).  Extra columns are not read.
    """
    found = components(banded_sketches(docs, id_col, text_col, width, radius), radius)
    return found.select("doc_id", F.lower(F.hex("fp")).alias("fingerprint"), "component_id")


#: Of 256 bits: a word-shingle similarity of 0.8 makes 39 bits differ on average, with a deviation of 6.
WIDE_RADIUS = 64
SIMILARITY = 0.8


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, radius: int = WIDE_RADIUS, similarity: float = SIMILARITY) -> DataFrame:
    """docs with only one row of each group of near copies: that of the smallest id.

    Groups are components of pairs whose sets of five-word shingles are of the similarity (Jaccard) at least.
    256-bit fingerprints within the radius only propose pairs.  Rows with a null id and texts without words
    are kept as they are; of rows that share the kept id, one stays.  All columns are kept.
    """
    (key,) = unused(docs.columns, "__row")
    rows = docs.where(F.col(id_col).isNotNull() & F.coalesce(F.col(text_col).rlike(r"[^\x20\x09-\x0D]"), F.lit(False)))
    sketches = cut(minhash_sketches(rows, id_col, text_col, width))
    links = verified(rows, sketches, cut(linked(sketches, radius)), id_col, text_col, width, radius, similarity)
    found = labelled(sketches, cut(links))
    gone = cut(found.where("doc_id <> component_id").select(F.col("doc_id").alias(key)).distinct())
    kept = docs.join(sized(gone), F.col(id_col) == F.col(key), "left_anti")
    repeated = found.groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias(key))
    if not repeated.isEmpty():
        again = kept.join(repeated, F.col(id_col) == F.col(key), "left_semi").dropDuplicates([id_col])
        kept = kept.join(repeated, F.col(id_col) == F.col(key), "left_anti").unionByName(again)
    return kept
