"""Properties of chains, draws, exact inference, rounds and plans."""

import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.functions.rand import h32, py_h32
from erfocus.operators import accept, alias, blocking, context, converge, exact, metrics, parallel, samplers, schedule, score, state
from erfocus.operators.alias import vose
from erfocus.operators.components import connected_components
from erfocus.operators.kernel import HOLDING, SAMPLERS, Biased, Budget, Chain, EntityFeatures, Query
from erfocus.operators.pairs import Dense, PairModel
from erfocus.plans import session, workloads
from erfocus.sources import fixtures
from erfocus.sources.schema import MentionSchema, QueryNode, as_queries


def weights(n, seed=1):
    rng = np.random.default_rng(seed)
    w = rng.integers(-30, 40, (n, n)).astype(np.int32)
    w = np.triu(w, 1)
    return w + w.T


def chain(sampler, n=9, seed=1, run=0, steps=300, **options):
    w = weights(n, seed)
    p = np.arange(1, n + 1, dtype=float)
    q = Query(0, 0, Biased(*vose(p)), Biased(*vose(p[::-1].copy())))
    c = Chain(np.arange(n) * 10, Dense(w), [q], sampler, seed=seed, run=run, **options)
    Budget(steps).spend(c, lambda c: (c.queries[0], steps))
    return c, w


def partition(c):
    out = {}
    for i, e in enumerate(c.entity.tolist()):
        out.setdefault(e, []).append(i)
    return out


@pytest.mark.parametrize("sampler", SAMPLERS)
@pytest.mark.parametrize("mode", ["greedy", "mh"])
def test_invariants(sampler, mode):
    for seed in range(4):
        c, w = chain(sampler, seed=seed, accept=mode, temperature=20.0)
        own = partition(c)
        assert {k: sorted(v) for k, v in c.members.items()} == own and all(min(v) == k for k, v in own.items())
        assert c.listed == sorted(own) and len(c.trace) == 300
        start = Chain(c.ids, c.edges, c.queries, sampler)
        assert start.score() + sum(r[7] for r in c.trace if r[8]) == c.score()
        assert sampler not in HOLDING or not any(r[4] == 0 for r in c.trace if r[8])
        if mode == "greedy":
            assert all(r[7] > 0 for r in c.trace if r[8])


def test_chains_repeat_and_runs_differ():
    a, b, other = chain("influence_to_query")[0], chain("influence_to_query")[0], chain("influence_to_query", run=1)[0]
    assert a.trace == b.trace and a.trace != other.trace


def test_no_guidance_is_the_baseline():
    a, b = chain("influence_to_query", tau=0.0)[0], chain("uniform", hold=True)[0]
    assert [r[4:] for r in a.trace] == [r[4:] for r in b.trace]


def test_cold_mh_is_greedy_but_for_moves_that_cannot_be_taken_back():
    a, b = chain("uniform", allow_new_target=True, accept="mh", temperature=0.0)[0], chain("uniform", allow_new_target=True)[0]
    assert [r[4:] for r in a.trace] == [r[4:] for r in b.trace]
    assert accept.mh(-5, 0, 0, 10, 0.6) and not accept.mh(-5, 0, 0, 10, 0.7) and not accept.mh(5, 0, -float("inf"), 1, 0.0)


def test_mh_visits_follow_the_posterior():
    n, t = 4, 25.0
    w = weights(n, 5)
    w[0, 1:] = w[1:, 0] = [10, -12, 8]
    counts = {}
    c = Chain(np.arange(n), Dense(w), [Query(0, 0)], "uniform", accept="mh", temperature=t, allow_new_target=True)
    c.pinned = set()
    for _ in range(20000):
        c.advance(c.queries[0], 1)
        key = tuple(c.entity.tolist())
        counts[key] = counts.get(key, 0) + 1
    z = {}
    for labels in itertools.product(range(n), repeat=n):
        first = {}
        key = tuple(first.setdefault(x, i) for i, x in enumerate(labels))
        z[key] = np.exp(sum(w[i, j] for i in range(n) for j in range(i) if key[i] == key[j]) / t)
    total = sum(z.values())
    assert max(abs(counts.get(k, 0) / 20000 - v / total) for k, v in z.items()) < 0.03


def test_hybrid_merges_under_mh_where_new_entities_are_targets():
    assert any(r[8] for r in chain("influence_to_query", accept="mh", temperature=5.0, allow_new_target=True)[0].trace)
    assert not any(r[8] for r in chain("influence_to_query", accept="mh", temperature=5.0)[0].trace)


def test_entity_features_are_rescored_locally():
    w = weights(8, 3)
    for matching in (0, 7):
        wide = EntityFeatures(np.array([0, 0, 1, 1, 2, 2, 3, 3]), lambda i: w[i] > 0, (10, -5), (20, -3), np.array([0, 1, 0, 2, 0, 1, 1, 2]), matching)
        for single, mode in ((False, "greedy"), (True, "greedy"), (False, "mh")):
            c = Chain(np.arange(8), Dense(w), [Query(0, 0)], "uniform", entity_features=wide, single=single, accept=mode, temperature=20.0, allow_new_target=True)
            before = c.score()
            Budget(400).spend(c, lambda c: (c.queries[0], 400))
            assert before + sum(r[7] for r in c.trace if r[8]) == c.score()
            rows = {e: np.asarray(own) for e, own in c.members.items()}
            assert all(c.totals.near[x] == (w[x][rows[e]] > 0).sum() for e, own in rows.items() for x in own)


def test_idle_budgets_leave_schedules_as_they_are():
    qs = [Query(i, i, Biased(*vose(np.ones(9)))) for i in range(3)]
    shares = []
    for idle in (None, 100_000):
        c = Chain(np.arange(9), Dense(weights(9)), qs, "influence_to_query")
        Budget(6000, idle=idle).spend(c, schedule.Turns(qs, "by_selectivity", 6000, 500, {0: 10, 1: 1, 2: 1}))
        shares.append([sum(r[2] == q for r in c.trace) for q in range(3)])
    assert shares[0] == shares[1] == [5000, 500, 500]


def test_the_querys_mention_moves_where_the_sampler_does_not_hold_it():
    for sampler in SAMPLERS:
        moved = {r[4] for s in range(6) for r in chain(sampler, seed=s, steps=500)[0].trace if r[8]}
        assert (0 in moved) == (sampler not in HOLDING)


def test_budget_ends_on_a_function_or_idleness():
    c, _ = chain("uniform", steps=0)
    Budget(1000, fn=lambda tail: True, every=50).spend(c, lambda c: (c.queries[0], 500))
    assert c.step == 50
    c, _ = chain("uniform", steps=0)
    Budget(100_000, idle=300).spend(c, lambda c: (c.queries[0], 100))
    assert c.step < 100_000


def test_alias_table_keeps_its_weights():
    rng = random.Random(2)
    for n in (1, 2, 7, 50):
        p = np.array([rng.random() ** 4 for _ in range(n)])
        prob, al = vose(p)
        got = prob / n
        np.add.at(got, al, (1 - prob) / n)
        assert np.allclose(got, p / p.sum(), atol=1e-12)
    draws = Biased(*vose(np.array([1.0, 2.0, 5.0])))
    seen = np.bincount([draws.draw(py_h32(f"{i}|a"), py_h32(f"{i}|b")) for i in range(40000)]) / 40000
    assert np.allclose(seen, [0.125, 0.25, 0.625], atol=0.01)


def test_alias_and_cdf_draws(spark):
    w = spark.createDataFrame([(1, i, float(i + 1)) for i in range(5)], "query_id long, mention_id long, weight double")
    u = spark.createDataFrame([(1, k, k / 200) for k in range(200)], "query_id long, draw int, u double")
    got = {r.mention_id: r["count"] for r in alias.cdf_draw(w, u).groupBy("mention_id").count().collect()}
    assert sum(got.values()) == 200 and all(abs(got[i] / 200 - (i + 1) / 15) < 0.02 for i in range(5))
    one = alias.presample(alias.build(w), 4000).groupBy("mention_id").count().collect()
    assert all(abs(r["count"] / 4000 - (r.mention_id + 1) / 15) < 0.03 for r in one)


def test_hash_is_the_same_everywhere(spark):
    assert spark.range(1).select(h32(F.lit("a"))).first()[0] == py_h32("a") == 214005177


def keyworded(m):
    return m.withColumn("context", F.col("context").withField("keywords", F.when(F.col("mention_id") == 3, F.array(F.lit("topic_red_plate"), F.lit("rod"))).otherwise(F.array().cast("array<string>"))))


@pytest.mark.parametrize("cosines", [False, True])
def test_rows_of_weights_equal_the_features_of_pairs(spark, small, cosines):
    m = keyworded(fixtures.part_mentions(spark, small).where("mention_id < 40"))
    m = m.withColumn("context", F.when(F.col("mention_id") == 5, F.col("context").withField("document", F.array().cast("array<string>"))).otherwise(F.col("context")))
    members = m.select(F.lit(0).cast("long").alias("query_id"), "mention_id")
    cos = None
    if cosines:
        pairs = m.select(F.col("mention_id").alias("i")).crossJoin(m.select(F.col("mention_id").alias("j"))).where("i < j")
        cos = context.cosine(context.tfidf(context.context_terms(m)), pairs, "i", "j")
    want = {(r.i, r.j): r.w for r in score.pair_edges(members, m, features.PAIRWISE, cos).collect()}
    packed = samplers.pack(members, m, as_queries(m.where("mention_id = 0")))
    got = {(r.i, r.j): r.w for r in samplers.edges(packed, features.PAIRWISE, cosines).collect()}
    assert got == want and len(got) == 40 * 39 // 2


def test_kept_rows_do_not_change_the_model(spark, small):
    """Rows made anew at every look give the weights of rows that are kept: size says nothing of the model."""
    m = keyworded(fixtures.part_mentions(spark, small))
    packed = samplers.pack(m.select(F.lit(0).cast("long").alias("query_id"), "mention_id"), m, as_queries(m.where("mention_id = 0"))).first()
    sides = samplers.unpacked(packed.model).sides
    few, all_ = PairModel(features.SPECS, sides, True, 1), PairModel(features.SPECS, sides, True)
    for i in (0, 3, 7, 0, 3, len(sides) - 1):
        assert few.row(i).tolist() == all_.row(i).tolist() and len(few.known) == 1
    w = np.stack([all_.row(i) for i in range(len(sides))])
    assert (w == w.T).all() and not w.diagonal().any()


def test_a_large_canopy_leaves_the_others_alone(spark, small):
    """One call for a large and a small canopy gives the small one what a call of its own gives."""
    m = fixtures.line_mentions(spark, small)
    plain = [r.mention_id for r in m.where(F.lower("mention") == F.col("gold")).orderBy("mention_id").limit(1).collect()]
    rare = m.where(F.col("mention_id") == plain[0]).withColumn("mention_id", F.lit(10**9).cast("long")).withColumn("mention", F.lit("zyx wvu qqq"))
    more = rare.withColumn("mention_id", F.lit(10**9 + 1).cast("long"))
    table = m.unionByName(rare).unionByName(more)
    er = session.EntityResolution(table, settings=samplers.Settings(samples=300))
    both = er.select_entity(as_queries(table.where(F.col("mention_id").isin([plain[0], 10**9]))))
    alone = er.select_entity(as_queries(table.where(F.col("mention_id") == 10**9)))
    assert sorted(map(tuple, both.where("query_id = 1000000000").collect())) == sorted(map(tuple, alone.collect())) != []
    one = er.select_entity(as_queries(table.where(F.col("mention_id") == plain[0])))
    assert sorted(map(tuple, both.where("query_id < 1000000000").collect())) == sorted(map(tuple, one.collect()))


def test_blocking_runs_its_input_once_a_pass(spark, small):
    """A canopy is two passes over the mentions: one for their strings, one to join them."""
    m = fixtures.part_mentions(spark, small)
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    counted = m.select("mention_id", "mention").mapInArrow(count, "mention_id long, mention string")
    n = m.count()
    blocking.canopy(counted, as_queries(m.where("mention_id < 3"))).collect()
    assert seen.value == 2 * n


def test_chains_go_on_from_an_earlier_result(spark, small):
    m = fixtures.part_mentions(spark, small)
    er = session.EntityResolution(m, features.TWO_WORD_NAMES, "paragraph", settings=samplers.Settings(samples=200))
    q = as_queries(m.where("mention_id = 1"))
    packed, *_ = er.packed(q)
    before = er.states(packed).select("mention_id", "entity_id").cache()
    again = er.packed(q, start=before)[0]
    still = er.states(again, init="previous", samples=0)
    assert sorted(map(tuple, still.select("mention_id", "entity_id").collect())) == sorted(map(tuple, before.collect()))
    with pytest.raises(Exception, match="previous"):
        er.states(packed, init="previous").collect()


def test_budget_functions_end_chains(spark, small):
    m = fixtures.part_mentions(spark, small)
    er = session.EntityResolution(m, features.TWO_WORD_NAMES, "paragraph")
    packed, *_ = er.packed(as_queries(m.where("mention_id = 1")))
    long = samplers.traces(samplers.chains(packed, samplers.Settings(samples=3000), 1, er.specs)).count()
    short = samplers.traces(samplers.chains(packed, samplers.Settings(samples=3000, until=converge.quiet(0.0), every=200), 1, er.specs)).count()
    assert long == 3000 and short < 3000


def test_learned_weights_beat_no_weights_on_other_labels(spark, small):
    m = fixtures.part_mentions(spark, small.replace("0.001", "0.01")).cache()
    learned = workloads.learned_specs(spark, m)
    assert learned == workloads.learned_specs(spark, m)
    held = workloads._compare(spark, small.replace("0.001", "0.01"), (11, 46), 150, ("influence_to_query",), 600, 3, specs=learned).collect()
    assert all(r.f1_at_budget > 0.8 for r in held)


def test_exact_is_the_best_of_all(spark):
    toy = fixtures.toy(spark)
    edges = score.pair_edges(toy.select(F.lit(0).cast("long").alias("query_id"), "mention_id"), toy, features.CONTEXT_FIRST, None, "paragraph").drop("query_id").cache()
    post = exact.partition_posterior(toy.select("mention_id"), edges, 50.0).collect()
    assert len(post) == 877 and abs(sum(r.prob for r in post) - 1) < 1e-9
    cluster = {r.mention_id for r in exact.map_query_cluster(toy.select("mention_id"), edges, 0).collect()}
    assert cluster == {i for i, *_, g in fixtures.TOY if g == "a"}
    with pytest.raises(ValueError):
        exact.partitions(spark.range(12).withColumnRenamed("id", "mention_id"))


def test_components_brute_force(spark):
    rng = random.Random(4)
    pairs = [(rng.randrange(200), rng.randrange(200)) for _ in range(150)] + [(i, i + 1) for i in range(300, 420)] + [(7, 7), (None, 3)]
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in pairs:
        if a is not None and a != b:
            root[max(find(a), find(b))] = min(find(a), find(b))
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {x: find(x) for x in root}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_winners_are_disjoint_and_do_not_depend_on_partitions(spark):
    rows = [(0, q, n, 100 + n, n % 11, 50 + n % 5) for n in range(200) for q in (n % 3,)]
    df = spark.createDataFrame(rows, "run_id int, query_id long, n long, mention_id long, entity_from long, entity_to long")
    got = [sorted(map(tuple, parallel.winners(df.repartition(k), 3).collect())) for k in (1, 4, 9)]
    assert got[0] == got[1] == got[2] and got[0]
    ends = [e for r in got[0] for e in r[4:6]]
    assert len(ends) == len(set(ends))


def test_a_round_is_a_sequence_of_improvements(spark):
    n = 12
    w = weights(n, 8)
    edges = spark.createDataFrame([(i, j, int(w[i, j])) for i in range(n) for j in range(i + 1, n)], "i long, j long, w long")
    members = spark.range(n).withColumnRenamed("id", "mention_id")
    s0 = state.init(members)
    props = spark.createDataFrame([(0, 0, k, k, k, 0) for k in range(1, n)] + [(0, 1, k, k, k, (k + 1) % n) for k in range(2, n)], "run_id int, query_id long, n long, mention_id long, entity_from long, entity_to long")
    s1 = parallel.bsp_round(s0, parallel.by_edges(edges), props, 0)
    s2 = parallel.bsp_round(s0, parallel.by_edges(edges), props, 0, 1, spark.createDataFrame([(0, 0), (1, 5)], "query_id long, mention_id long"))
    assert score.config_score(s2, edges).first().score >= score.config_score(s1, edges).first().score and s2.count() == n
    before, after = (score.config_score(s, edges).first().score for s in (s0, s1))
    assert after >= before and s1.count() == n


def test_schedules_in_a_chain():
    qs = [Query(i, i, Biased(*vose(np.ones(6)))) for i in range(3)]
    t = schedule.Turns(qs, "by_selectivity", 100, 30, {0: 1, 1: 3, 2: 6})
    assert [(q.query_id, k) for q, k in t.fixed] == [(2, 30), (1, 30), (0, 10), (2, 30)]
    for policy, want in (("closest_first", 1), ("farthest_first", 2), ("slowest_first", 0)):
        t = schedule.Turns(qs, policy, 100, 10)
        t.turn = 3
        for i, rate in enumerate((0, 2, 7)):
            t.recent[i].extend([True] * rate + [False] * (10 - rate))
        assert t._dynamic().query_id == want


@pytest.fixture(scope="module")
def er(spark, small):
    return session.EntityResolution(fixtures.part_mentions(spark, small), features.TWO_WORD_NAMES, "paragraph", settings=samplers.Settings(samples=400))


def test_gold_is_not_used(er):
    q = QueryNode("red plate", keywords=("topic_red_plate",))
    blind = session.EntityResolution(er.mentions.withColumn("gold", F.lit(None).cast("string")), features.TWO_WORD_NAMES, "paragraph", settings=er.settings)
    assert sorted(map(tuple, er.select_entity(q).collect())) == sorted(map(tuple, blind.select_entity(q).collect()))


def test_sql_is_the_api(er):
    q = QueryNode("red plate", keywords=("topic_red_plate",))
    api = {r.mention_id for r in er.select_entity(q).collect()}
    assert {r.mention_id for r in er.sql("SELECT mention_id FROM mentions WHERE same_entity(mentions, :q)", q=q).collect()} == api
    some = er.sql("SELECT mention_id FROM mentions WHERE same_entity(mentions, :q) AND mention_id > 50", q=q).collect()
    assert {r.mention_id for r in some} == {i for i in api if i > 50}
    with pytest.raises(ValueError):
        er.sql("SELECT mention_id FROM mentions WHERE mention_id = 1 OR same_entity(mentions, :q)", q=q)


def test_partitions_do_not_change_answers(spark, er):
    q = QueryNode("red plate")
    want = sorted(map(tuple, er.select_entity(q).collect()))
    old = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        spark.conf.set("spark.sql.shuffle.partitions", "9")
        assert sorted(map(tuple, er.select_entity(q).collect())) == want
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", old)


def test_persisted_index_gives_the_same_canopy(spark, er, tmp_path_factory):
    q = as_queries(er.mentions.where("mention_id < 3"))
    spark.sql("CREATE DATABASE IF NOT EXISTS idx")
    blocking.build_index(er.mentions, "idx.part", buckets=4)
    got = blocking.canopy(er.mentions, q, index="idx.part")
    assert sorted(map(str, got.collect())) == sorted(map(str, blocking.canopy(er.mentions, q).collect()))
    spark.sql("DROP DATABASE idx CASCADE")


def test_blocking_reads_no_context(er, small, spark):
    plan = blocking.canopy(er.mentions, as_queries(er.mentions.where("mention_id < 3")).select("query_id", "mention"))._jdf.queryExecution().executedPlan().toString()
    assert "p_type" not in plan and "CartesianProduct" not in plan


def test_schema_is_checked(spark, er):
    MentionSchema.validate(er.mentions, gold=True)
    with pytest.raises(ValueError):
        MentionSchema.validate(er.mentions.drop("context"))


def test_hybrid_leads_the_pinned_target_and_the_baseline(spark, small):
    from erfocus.plans import workloads

    got = {}
    for r in workloads._compare(spark, small.replace("0.001", "0.01"), (11, 46), 200, workloads.KINDS, 600, 6).collect():
        got.setdefault(r.sampler, []).append(r.f1_at_budget)
    mean = {k: sum(v) / len(v) for k, v in got.items()}
    assert mean["influence_to_query"] >= mean["pin_target"] > mean["uniform"] and mean["influence_both"] > mean["uniform"]


def test_stream_equals_batch(spark, small):
    from erfocus.plans.workloads import w12_stream

    rows = w12_stream(spark, small).collect()
    assert rows and all(r.streamed == r.batch for r in rows)


def test_curve_replays_the_chain(spark, small):
    toy = fixtures.toy(spark)
    members = toy.select(F.lit(0).cast("long").alias("query_id"), "mention_id")
    q = as_queries(toy.where("mention_id = 0"))
    rows = samplers.pack(members, toy, q, None, "paragraph")
    for kind in ("influence_to_query", "expel"):
        both = samplers.chains(rows, samplers.Settings(sampler=kind, samples=300), 3, features.SHORT_NAMES).cache()
        start = toy.select(F.lit(0).cast("long").alias("component"), "mention_id", (F.lit(0) if kind == "expel" else F.col("mention_id")).cast("long").alias("entity_id"))
        curve = metrics.curve(samplers.traces(both), start, toy.select("mention_id", "gold"), q)
        end = {r.run_id: r.f1q for r in metrics.at_step(curve, 300).collect()}
        prf = {r.run_id: r.f1q for r in metrics.query_prf(samplers.answers(samplers.states(both), q), toy.select("mention_id", "gold"), q, 3).collect()}
        assert end == pytest.approx(prf)


def test_near_copy_gold_links_large_groups(spark):
    base = [f"w{i}" for i in range(30)]
    data = [(k, " ".join([*base, f"own{k}", f"end{k}"])) for k in range(45)] + [(100 + k, " ".join(base)) for k in range(45)]
    data += [(200, "a b"), (201, "a b"), (202, " ".join(base[:12] + [f"z{i}" for i in range(20)]))]
    gold = workloads.near_copy_gold(spark.createDataFrame(data, "doc_id long, text string"))
    got = {r.mention_id: r.gold for r in gold.collect()}
    assert got == {i: "0" if i < 200 else str(i) for i, _ in data}
