"""Texts and their words are not sent about: what canopies, chains and passages exchange is numbers and ids."""

import pickle

import numpy as np
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.operators import extract, samplers
from erfocus.operators.pairs import PairModel, Sides, expanded, squeezed
from erfocus.sources import fixtures


def exchanged(df):
    """What the plan's exchanges, but broadcasts, send: a line of columns each."""

    def walk(node):
        if node.nodeName() == "AdaptiveSparkPlan":
            node = node.inputPlan()
        if node.nodeName() == "Exchange":
            yield node.output().mkString(" ")
        for k in range(node.children().size()):
            yield from walk(node.children().apply(k))

    return list(walk(df._jdf.queryExecution().executedPlan()))


def _canopies(spark, small):
    """Documents in canopies that overlap, three queries, one of which is in no canopy; some words are others' tokens."""
    m = fixtures.document_mentions(spark, small).withColumn("mention", F.concat_ws(" ", "mention", F.get("context.document", F.lit(5)))).localCheckpoint()
    ids = [r[0] for r in m.select("mention_id").orderBy("mention_id").limit(60).collect()]
    rows = [(1, i) for i in ids[:40]] + [(2, i) for i in ids[20:]] + [(1, ids[3]), (3, ids[5])]
    canopy = spark.createDataFrame(rows, "query_id long, mention_id long")
    queries = spark.createDataFrame([(1, ids[0]), (2, ids[30]), (3, ids[7])], "query_id long, own long").join(m, F.col("own") == F.col("mention_id")).drop("own")
    return m, ids, canopy, queries


def test_packed_canopies_hold_all_and_no_text_is_exchanged_for_them(spark, small):
    m, ids, canopy, queries = _canopies(spark, small)
    packed = samplers.pack(canopy, m, queries)
    sent = exchanged(packed)
    assert any("slab" in x for x in sent) and not [x for x in sent if "ctx" in x]
    rows = {r.component: samplers.unpacked(r.model) for r in packed.collect()}
    want = {r.mention_id: r for r in features.prepare(m, "document").select("mention_id", "doc_id", "side").collect()}
    for q, (mine, own) in {1: (ids[:40], 0), 2: (ids[20:], 10), 3: ([ids[5]], None)}.items():
        whole = rows[q]
        sides = [want[i].side for i in mine]
        plain = Sides.of(mine, [want[i].doc_id for i in mine], [s.m for s in sides], [s.toks for s in sides], [s.ctx for s in sides], [s.kw for s in sides])
        assert whole.sides.ids.tolist() == mine and len(whole.sides.terms) > 0 and whole.sides.n_terms == plain.n_terms
        assert [(k, at, p.tolist()) for k, at, p in whole.queries] == [(q, own, list(range(len(mine))))]
        got, expected = PairModel(features.PAIRWISE, whole.sides), PairModel(features.PAIRWISE, plain)
        for i in range(len(mine)):
            assert got.row(i).tolist() == expected.row(i).tolist()


def test_merged_canopies_hold_each_querys_own_members(spark, small):
    m, ids, canopy, queries = _canopies(spark, small)
    one = queries.select("query_id", F.lit(9).cast("long").alias("component"))
    whole = samplers.unpacked(samplers.pack(canopy, m, queries, one).first()["model"])
    assert whole.sides.ids.tolist() == ids
    assert [(k, at, p.tolist()) for k, at, p in whole.queries] == [(1, 0, list(range(40))), (2, 30, list(range(20, 60))), (3, 7, [5])]


def test_batches_of_a_component_are_joined_and_repeated_words_count_once(spark, small):
    m, ids, canopy, queries = _canopies(spark, small)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        apart = {r.component: samplers.unpacked(r.model).sides for r in samplers.pack(canopy, m.orderBy(F.desc("mention_id")), queries).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    at_once = {r.component: samplers.unpacked(r.model).sides for r in samplers.pack(canopy, m, queries).collect()}
    for q, sides in at_once.items():
        a, b = PairModel(features.PAIRWISE, sides), PairModel(features.PAIRWISE, apart[q])
        assert all(a.row(i).tolist() == b.row(i).tolist() for i in range(len(sides)))


def test_numbers_of_words_are_pickled_by_their_differences():
    rng = np.random.default_rng(1)
    lists = [np.unique(rng.integers(0, 50_000, k)) for k in (0, 300, 1, 0, 0, 250, 280, 0)] + [np.array([0]), np.array([0, 2**31 - 1])]
    ptr = np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int64)
    cid = np.concatenate(lists).astype(np.int32)
    assert expanded(squeezed(cid, ptr), ptr).tolist() == cid.tolist()
    none = np.zeros(3, dtype=np.int64)
    assert len(expanded(squeezed(cid[:0], none), none)) == 0
    sides = Sides(np.arange(10), np.arange(10), ["a"], np.zeros(10, dtype=np.int64), [("a",)], 2**31, {}, ptr, cid, {})
    assert pickle.loads(pickle.dumps(sides)).cid.tolist() == cid.tolist()
    assert len(pickle.dumps(sides)) < 3 * len(cid) + 1000


def test_postings_do_not_depend_on_how_many_words_are_dealt_at_once(monkeypatch):
    rng = np.random.default_rng(2)
    ctx = [[f"w{x}" for x in rng.integers(0, 30, k)] for k in rng.integers(0, 12, 50)]
    sides = Sides.of(range(50), range(50), ["a"] * 50, [("a",)] * 50, ctx, [()] * 50)
    whole = PairModel(features.PAIRWISE, sides)
    monkeypatch.setattr(PairModel, "DEAL", 9)
    parts = PairModel(features.PAIRWISE, sides)
    assert parts.post.tolist() == whole.post.tolist() and parts.norm.tolist() == whole.norm.tolist()
    assert whole.post[whole.post_at[3] : whole.post_at[4]].tolist() == [i for i in range(50) if 3 in sides.cid[sides.ptr[i] : sides.ptr[i + 1]]]


def test_a_single_run_of_chains_sends_no_canopy_once_more(spark, small):
    m, _, canopy, queries = _canopies(spark, small)
    packed = samplers.pack(canopy, m, queries).localCheckpoint()
    chains = samplers.chains(packed, samplers.Settings(samples=20))
    assert "Exchange" not in chains._jdf.queryExecution().executedPlan().toString()


def test_passages_are_found_without_an_exchange_of_texts(spark):
    texts = [(1, "the red fox and the blue lantern"), (2, "a red foxglove"), (3, None), (1, "blue lantern again the red fox and so"), (4, "")]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    asked = [(10, "red fox and the blue"), (11, "fox"), (12, "the red fox and"), (12, "the red fox and"), (12, "blue lantern again the"), (13, None), (14, "")]
    found = extract.passages(docs, spark.createDataFrame(asked, "item_id long, text string"))
    assert not [x for x in exchanged(found) if "text" in x]
    whole = [t for _, t in texts if t]
    # A document's number that occurs twice is met by the words of each of its rows.
    assert (10, 1) in {tuple(r) for r in found.collect()} and {tuple(r) for r in found.collect()} == {(i, d) for i, p in asked if p for d, t in texts if t in whole and p in t}


def test_shuffle_files_of_a_table_that_is_written_down_are_removed(spark):
    import time

    from erfocus.operators.durable import cut, freed

    master = spark._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker()
    known = lambda: {x for x in master.shuffleStatuses().keys().mkString(",").split(",") if x}
    before = known()
    out = cut(spark.range(200_000, numPartitions=4).withColumn("k", F.col("id") % 7).repartition(4, "id"))
    made = known() - before
    freed(out)
    time.sleep(1)
    assert made and not made & known() and out.count() == 200_000
