"""What larger tables asked for: the whole job by classes, larger canopies, lean tables."""

from pyspark.sql import functions as F

from erfocus.operators import baselines, score
from erfocus.plans import queries


def _copied(spark, small, copies=3):
    """A canopy with copies of its mentions, their random state of five entities."""
    p = queries.Part(spark, small)
    members = p.members(p.one)
    k = spark.range(copies).withColumnRenamed("id", "k")
    m = p.mentions.join(members.select("mention_id"), "mention_id", "left_semi").crossJoin(k).withColumn("mention_id", F.col("mention_id") + 10_000 * F.col("k")).drop("k")
    mentions = m.localCheckpoint()
    members = mentions.select(F.lit(0).cast("long").alias("query_id"), "mention_id")
    state = mentions.select(F.lit(0).alias("run_id"), "mention_id", (F.col("mention_id") % 5).alias("entity_id"))
    return p, mentions, members, state


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_scores_by_class_equal_those_of_all_pairs_and_copies_add_no_pair(spark, small):
    p, mentions, members, state = _copied(spark, small)
    of = score.classes(members, mentions)
    by_class = score.class_edges(of, mentions).drop("query_id").localCheckpoint()
    every = score.pair_edges(members, mentions).drop("query_id").localCheckpoint()
    once = members.where("mention_id < 10000")
    assert by_class.where("i < j").count() == score.class_edges(score.classes(once, mentions), mentions).where("i < j").count() < every.count() / 8
    assert rows(score.config_score(state, by_class, of)) == rows(score.config_score(state, every))
    similar = lambda e: e.where("w > 0").select("i", "j")
    assert rows(score.entity_score(state, mentions, similar(by_class), of=of)) == rows(score.entity_score(state, mentions, similar(every)))
    moves = state.select("run_id", "mention_id").crossJoin(state.select(F.col("entity_id").alias("entity_to")).distinct())
    assert rows(score.move_delta(state, by_class, moves, of)) == rows(score.move_delta(state, every, moves))
    assert rows(baselines.pairwise(by_class, 60, members, of=of)) == rows(baselines.pairwise(every, 60, members))


def _many(spark, n):
    """Mentions of a few strings, one of them the query's."""
    from erfocus.sources.fixtures import with_context

    word = F.array(F.concat(F.lit("topic_"), (F.col("id") % 7).cast("string")))
    flat = spark.range(n).select(F.col("id").alias("mention_id"), F.col("id").alias("doc_id"), F.lit(0).alias("startpos"), F.concat(F.lit("red plate "), (F.col("id") % 5).cast("string")).alias("mention"), word.alias("paragraph"), word.alias("document"), F.lit("x").alias("gold"))
    return with_context(flat)


def test_a_canopy_of_over_a_hundred_thousand_is_packed_and_sampled(spark):
    from erfocus.operators import samplers

    m = _many(spark, 120_000)
    q = m.where("mention_id = 0").withColumn("query_id", F.col("mention_id"))
    packed = samplers.pack(m.select(F.lit(0).cast("long").alias("query_id"), "mention_id"), m, q, None, "paragraph")
    both = samplers.chains(packed, samplers.Settings(samples=20, draw="cdf", cosines=False)).localCheckpoint()
    assert samplers.states(both).count() == 120_000
    assert samplers.traces(both).count() == 20


def test_the_table_function_takes_partitions_of_over_five_thousand(spark):
    from erfocus.plans import udtf

    udtf.register(spark)
    _many(spark, 6_000).createOrReplaceTempView("many_mentions")
    found = spark.sql("SELECT * FROM er_select(TABLE(SELECT mention_id, mention, context FROM many_mentions) WITH SINGLE PARTITION, 'red plate 1', array('topic_1'), 50)")
    assert found.count() > 0


def test_near_copies_write_no_text_and_no_shingles_of_a_text_down(spark, small, monkeypatch):
    from erfocus.plans import workloads

    written, cut = [], workloads.cut
    monkeypatch.setattr(workloads, "cut", lambda df: (written.extend(t for _, t in df.dtypes), cut(df))[1])
    assert workloads.near_copy_gold(spark.read.parquet(f"{small}/documents.parquet")).count() == 200
    assert written and not [t for t in written if t.startswith("array")]


def test_whole_blocks_end_where_traced_chains_end_with_few_sums_and_no_trace(spark, small, monkeypatch):
    from erfocus.functions import features
    from erfocus.operators import kernel, samplers
    from erfocus.plans import session, workloads
    from erfocus.sources import fixtures

    m = fixtures.customer_mentions(spark, small).localCheckpoint()
    er = session.EntityResolution(m, features.SHORT_NAMES, "paragraph")
    packed = er.packed_blocks(workloads.CUSTOMER_BLOCK)
    s = samplers.Settings(sampler="uniform", samples=5000, idle=400, seed=3)
    traced = samplers.states(samplers.chains(packed, s, 2, features.SHORT_NAMES))
    assert rows(samplers.resolved(packed, s, 2, features.SHORT_NAMES)) == rows(traced)
    whole = samplers.unpacked(packed.first()["model"])
    chain = samplers._chain(whole, 0, s, features.SHORT_NAMES, traced=False)
    assert isinstance(chain, kernel.ClassChain) and len(chain.own) < len(chain.ids)
    same = samplers._chain(whole, 0, s, features.SHORT_NAMES)
    for c in (chain, same):
        kernel.Budget(5000, idle=400).spend(c, samplers.Turns(c.queries, "round_robin", 5000))
    assert chain.step == same.step and chain.last == same.last and not chain.trace and chain.labels().tolist() == same.labels().tolist()


def test_mentions_without_a_block_or_alone_in_it_are_kept(spark):
    from erfocus.plans import session

    m = _many(spark, 12)
    er = session.EntityResolution(m, level="paragraph")
    found = er.resolve_all("CASE WHEN mention_id = 5 THEN 'own' WHEN mention_id % 4 > 0 THEN mention END", runs=2, samples=50)
    assert sorted((r.run_id, r.mention_id) for r in found.collect()) == [(k, i) for k in (0, 1) for i in range(12)]
    assert {r.mention_id: r.entity_id for r in found.where("run_id = 1 AND mention_id IN (0, 4, 5, 8)").collect()} == {i: i for i in (0, 4, 5, 8)}


def test_draws_ahead_over_classes_are_those_of_tables_over_mentions(spark, small):
    from erfocus.functions.features import TWO_WORD_NAMES
    from erfocus.operators import alias, influence, parallel, state
    from erfocus.operators.durable import cut

    p, mentions, members, _ = _copied(spark, small)
    q = cut(p.one.withColumn("query_id", F.lit(0).cast("long")))
    infl = cut(influence.score(members, mentions, q, TWO_WORD_NAMES, None, "paragraph"))
    start = cut(state.init(mentions.select("mention_id")))
    tables = cut(alias.build(influence.decay(infl)))
    of = cut(mentions.select("mention_id", (F.col("mention_id") % 10_000).alias("rep")))
    scores = infl.where("mention_id < 10000").withColumnRenamed("mention_id", "rep")
    ahead = cut(parallel.draws_ahead(scores, of, q, 2, 40))
    for step in (0, 1):
        drawn = ahead.where(F.col("step") == step).drop("step")
        assert rows(parallel.propose(start, None, q, step, workers=40, drawn=drawn)) == rows(parallel.propose(start, tables, q, step, workers=40))


def _replayed(n, between, sampler, steps, temperature=None, tau=0.9):
    """The trace of a chain over _many(n) from singletons for mention 0, by a plain replay; between: weights of classes of ids."""
    import math
    from bisect import bisect_left, bisect_right, insort

    import numpy as np

    from erfocus.functions.rand import py_h32

    w = lambda i, j: between[i % 35, j % 35] if i != j else 0
    infl = np.array([between[0, i % 35] for i in range(n)])
    p = min(0.05, 5 / n)
    decay = np.empty(n)
    decay[np.lexsort((np.arange(n), -infl))] = p * (1 - p) ** np.arange(n)
    whole = np.floor(decay * 1_000_000 + 0.5).astype(np.int64)
    cum = np.cumsum(whole).tolist()
    chance = lambda xs: sum(int(whole[x]) for x in xs) / cum[-1]
    label, groups, ent, out, mh = list(range(n)), {i: [i] for i in range(n)}, list(range(n)), [], temperature is not None
    for t in range(steps):
        u = lambda slot: py_h32(f"1|0|{t}|{slot}")  # noqa: E731, B023
        own = label[0]
        if sampler == "uniform" or u(0) >= int(tau * 2**32):
            source, k = ent[u(1) * len(ent) >> 32], u(3) * (len(ent) + mh) >> 32
            target = ent[k] if k < len(ent) else -1
            m = groups[source][u(2) * len(groups[source]) >> 32]
        else:
            drawn = [bisect_right(cum, u(slot) * cum[-1] >> 32) for slot in (5, 9, 11, 13, 15)]
            m = next((x for x in drawn if label[x] != own), drawn[-1])
            source, target = label[m], own
        nothing = source == target or (sampler != "uniform" and m == 0) or (target == -1 and len(groups[source]) == 1)
        delta, ok = 0, False
        if not nothing:
            left, joined = [x for x in groups[source] if x != m], sorted(groups.get(target, []) + [m])
            delta = sum(w(m, x) for x in joined) - sum(w(m, x) for x in left)
            ok = delta > 0
            if mh:
                after = next((g for g in (left, joined) if 0 in g), groups[own])
                uniform = lambda entities, size: (1 - tau) / entities / size / (entities + 1)
                forward = (tau * chance([m]) / (1 - chance(groups[own])) if target == own else 0) + uniform(len(ent), len(groups[source]))
                back = (tau * chance([m]) / (1 - chance(after)) if source == own else 0) + uniform(len(ent) - (not left) + (target == -1), len(joined))
                ratio = delta / temperature + math.log(back) - math.log(forward)
                ok = ratio >= 0 or math.log(max(u(4) / 2**32, 1e-300)) < ratio
        out.append((t, m, source, target, delta, ok))
        if ok:
            for e in (source, target):
                if e != -1:
                    del groups[e], ent[bisect_left(ent, e)]
            for g in filter(None, (left, joined)):
                groups[g[0]] = g
                insort(ent, g[0])
                for x in g:
                    label[x] = g[0]
    return out


MANY = 120_000


def _over_many(spark, sampler, steps, **changes):
    """Spark's trace of a chain over a canopy of over a hundred thousand, and that of the replay."""
    import numpy as np

    from erfocus.functions.features import TWO_WORD_NAMES
    from erfocus.operators import samplers

    m = _many(spark, MANY)
    few = m.where("mention_id < 70").localCheckpoint()
    between = np.zeros((35, 35), dtype=np.int64)
    for r in score.pair_edges(few.select(F.lit(0).cast("long").alias("query_id"), "mention_id"), few, TWO_WORD_NAMES, None, "paragraph").collect():
        between[r.i % 35, r.j % 35] = between[r.j % 35, r.i % 35] = r.w
    q = m.where("mention_id = 0").withColumn("query_id", F.col("mention_id"))
    packed = samplers.pack(m.select(F.lit(0).cast("long").alias("query_id"), "mention_id"), m, q, None, "paragraph")
    both = samplers.chains(packed, samplers.Settings(sampler=sampler, samples=steps, draw="cdf", cosines=False, **changes), 1, TWO_WORD_NAMES)
    trace = samplers.traces(both).localCheckpoint()
    return trace, _replayed(MANY, between, sampler, steps, changes.get("temperature")), m, q


def _steps(trace):
    return rows(trace.select("step", "m", "e_from", "e_to", "delta", "accepted"))


def test_metropolis_hastings_over_a_large_canopy_is_that_of_a_plain_replay(spark):
    trace, want, *_ = _over_many(spark, "influence_to_query", 120, accept="mh", temperature=30.0)
    assert _steps(trace) == want and any(r[5] for r in want)


def test_a_canopy_is_refused_only_beyond_a_limit_that_is_given(spark):
    import inspect

    import pytest

    from erfocus.operators import samplers

    assert {inspect.signature(f).parameters["max_canopy"].default for f in (samplers.pack, samplers.pack_blocks)} == {None}
    m = _many(spark, 30)
    q = m.where("mention_id = 0").withColumn("query_id", F.col("mention_id"))
    canopy = m.select(F.lit(0).cast("long").alias("query_id"), "mention_id")
    assert samplers.pack(canopy, m, q, max_canopy=30).count() == 1
    with pytest.raises(Exception, match="30 mentions"):
        samplers.pack(canopy, m, q, max_canopy=29).collect()


def test_draws_of_guided_chains_over_a_large_canopy_are_those_of_a_plain_replay(spark):
    trace, want, *_ = _over_many(spark, "influence_to_query", 120)
    assert _steps(trace) == want and any(r[5] for r in want)


def test_weights_that_all_round_to_nothing_are_no_draw():
    import numpy as np
    import pytest

    from erfocus.operators import samplers

    weights = np.full(4, 1e-8)
    with pytest.raises(ValueError, match="alias"):
        samplers.biased(weights, "cdf")
    assert samplers.biased(weights, "alias").prob.tolist() == [1.0] * 4


def test_uniform_chains_over_a_large_canopy_are_those_of_a_plain_replay(spark):
    trace, want, *_ = _over_many(spark, "uniform", 200)
    assert _steps(trace) == want and any(r[5] for r in want)


def test_the_first_correct_proposal_over_a_large_canopy_is_that_of_a_plain_replay(spark):
    from erfocus.operators import metrics

    trace, want, m, q = _over_many(spark, "uniform", 200)
    gold = m.select("mention_id", F.when(F.col("mention_id") % 3 == 0, "x").otherwise("y").alias("gold"))
    first = min(r[0] for r in want if r[5] and r[1] % 3 == 0)
    assert [tuple(r) for r in metrics.first_correct(trace, gold, q).select("query_id", "step").collect()] == [(0, first)]


def test_counts_of_proposals_over_a_large_canopy_are_those_of_a_plain_replay(spark):
    from erfocus.operators import metrics

    trace, want, *_ = _over_many(spark, "uniform", 200)
    hits = [r[0] for r in want if r[5]]
    found = metrics.proposals(trace).select("proposals", "accepted", F.round("rate", 9), "first_accepted").collect()
    assert [tuple(r) for r in found] == [(200, len(hits), round(len(hits) / 200, 9), hits[0])]
