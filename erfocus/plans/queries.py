"""The driver's keys: every method, variant, baseline and measure on the given tables."""

from __future__ import annotations

from collections.abc import Callable
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.functions.rand import h32
from erfocus.functions.strings import normal
from erfocus.operators import alias, baselines, blocking, context, converge, exact, extract, influence, metrics, parallel, samplers, schedule, score, state, train
from erfocus.operators.durable import cut, shared_path
from erfocus.plans import session, workloads
from erfocus.plans.oracles import BSP_ROUNDS, BSP_WORKERS, LARGE_SHARED, LARGE_STEPS, RESOLVE_STEPS, SELECT_STEPS, STEPS, WATCH
from erfocus.sources import fixtures
from erfocus.sources.schema import QueryNode, as_queries
from erfocus.streaming import growth

TWO = features.TWO_WORD_NAMES


def r9(c: str):
    return F.round(c, 9).alias(c)


class Part:
    """Part mentions with a watchlist: the first plain mention of some names, in hash order."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark = spark
        self.mentions = fixtures.part_mentions(spark, sf_dir)
        self.gold = self.mentions.select("mention_id", "gold")

    @cached_property
    def watch(self) -> DataFrame:
        plain = self.mentions.where(F.lower("mention") == F.col("gold")).groupBy("gold").agg(F.min("mention_id").alias("mention_id"))
        picked = plain.orderBy(h32(F.concat(F.lit("name|"), F.col("gold"))), "gold").limit(WATCH).select("mention_id")
        return cut(as_queries(self.mentions.join(F.broadcast(picked), "mention_id")).select("query_id", "mention_id", "doc_id", "startpos", "mention", "context", "gold"))

    @cached_property
    def one(self) -> DataFrame:
        return cut(self.watch.orderBy("query_id").limit(1))

    def canopy(self, queries: DataFrame | None = None) -> DataFrame:
        return blocking.canopy(self.mentions, self.watch if queries is None else queries)

    def members(self, queries: DataFrame | None = None) -> DataFrame:
        """(query_id, mention_id): whole canopies, each query's own mention among them."""
        queries = self.watch if queries is None else queries
        return cut(self.canopy(queries).select("query_id", "mention_id").union(queries.select("query_id", "mention_id")).distinct())

    def scores(self) -> DataFrame:
        return influence.score(self.canopy(), self.mentions, self.watch)

    def three_states(self, members: DataFrame) -> DataFrame:
        """(how, run_id, mention_id, entity_id) of the initial states."""
        out = None
        for i, how in enumerate(("singletons", "single", "random")):
            s = state.init(members, how, run_id=i).withColumn("how", F.lit(how))
            out = s if out is None else out.unionByName(s)
        return out

    def packed(self) -> DataFrame:
        return cut(samplers.pack(self.members(self.one), self.mentions, self.one, None, "paragraph"))

    def chain(self, sampler: str, steps: int = STEPS, runs: int = 1, **changes) -> DataFrame:
        settings = samplers.Settings(**{"sampler": sampler, "samples": steps, "draw": "cdf", "cosines": False} | changes)
        return samplers.chains(self.packed(), settings, runs, TWO)


def _chain(sampler: str, **changes) -> Callable:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        trace = samplers.traces(Part(spark, sf_dir).chain(sampler, **changes))
        return trace.select("step", "m", "e_from", "e_to", "delta", "accepted")

    return query


def line_mentions(spark, sf_dir):
    m = fixtures.line_mentions(spark, sf_dir, "part")
    return m.select("mention_id", "doc_id", "startpos", "mention", F.array_join("context.document", " ").alias("words"), "gold")


def customer_mentions(spark, sf_dir):
    m = fixtures.customer_mentions(spark, sf_dir)
    return m.select("mention_id", "mention", F.array_join("context.document", " ").alias("words"), "gold")


def qgram_postings(spark, sf_dir):
    return blocking.postings(blocking.string_table(Part(spark, sf_dir).mentions)).select("gram", "string")


def gram_df(spark, sf_dir):
    return blocking.gram_df(blocking.string_table(Part(spark, sf_dir).mentions))


def canopy_single(spark, sf_dir):
    p = Part(spark, sf_dir)
    return p.canopy(p.one).select("query_id", "mention_id", "shared", F.round("sim", 6).alias("sim"))


def canopy_watchlist(spark, sf_dir):
    return Part(spark, sf_dir).canopy().select("query_id", "mention_id", "shared", F.round("sim", 6).alias("sim"))


def canopy_rarest_grams(spark, sf_dir):
    """The same canopies, probing only each query's rarest grams."""
    p = Part(spark, sf_dir)
    strings = cut(blocking.string_table(p.mentions))
    found = blocking.candidates(p.watch, blocking.postings(strings), blocking.gram_df(strings))
    keyed = p.mentions.select("mention_id", normal(F.col("mention")).alias("string"))
    return keyed.join(found, "string").select("query_id", "mention_id", "shared", F.round("sim", 6).alias("sim"))


def canopy_sorted_neighborhood(spark, sf_dir):
    return blocking.sorted_neighborhood(Part(spark, sf_dir).mentions, 3)


def vector_blocks(spark, sf_dir):
    return blocking.by_vector(fixtures.embedding_mentions(spark, sf_dir))


def watchlist_selectivity(spark, sf_dir):
    return blocking.selectivity(Part(spark, sf_dir).canopy())


def gold_selectivity(spark, sf_dir):
    p = Part(spark, sf_dir)
    return blocking.gold_selectivity(p.mentions, p.watch)


def canopy_quality(spark, sf_dir):
    p = Part(spark, sf_dir)
    return metrics.canopy_quality(p.canopy(), p.gold, p.watch).select("query_id", "n", r9("quality"))


def merged_components(spark, sf_dir):
    return blocking.merge(cut(Part(spark, sf_dir).canopy().select("query_id", "mention_id")))


def term_stats(spark, sf_dir):
    return context.term_stats(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def tfidf_cosine(spark, sf_dir):
    p = Part(spark, sf_dir)
    members = p.members(p.one)
    vectors = context.tfidf(context.context_terms(p.mentions.join(members.select("mention_id"), "mention_id", "left_semi")))
    return context.cosine(vectors, members).select("query_id", "mention_id", F.round("cos", 6).alias("cos"))


def pair_features(spark, sf_dir):
    p = Part(spark, sf_dir)
    return train.pair_features(p.canopy(), p.mentions, p.watch)


def pair_edges(spark, sf_dir):
    """(what, a, b, w): each mention's class of those that no feature tells apart, and the weights between classes.

    Pairs are of classes' smallest mentions, a class with itself where it has several: every pair of mentions has its weight
    from the two classes, so that copies need not be paired.
    """
    p = Part(spark, sf_dir)
    of = score.classes(p.members(p.one), p.mentions)
    pairs = score.class_edges(of, p.mentions).select(F.lit("pair").alias("what"), F.col("i").alias("a"), F.col("j").alias("b"), "w")
    return of.select(F.lit("member").alias("what"), F.col("mention_id").alias("a"), F.col("rep").alias("b"), F.lit(None).cast("long").alias("w")).union(pairs)


def influence_scores(spark, sf_dir):
    return Part(spark, sf_dir).scores()


def influence_decay(spark, sf_dir):
    return influence.decay(Part(spark, sf_dir).scores()).select("query_id", "mention_id", "pos", r9("weight"))


def influence_decay_by_score(spark, sf_dir):
    return influence.decay(Part(spark, sf_dir).scores(), unit="score").select("query_id", "mention_id", "pos", r9("weight"))


def inverse_influence(spark, sf_dir):
    return influence.invert(Part(spark, sf_dir).scores()).select("query_id", "mention_id", r9("weight"))


def influence_top(spark, sf_dir):
    return blocking.by_influence(Part(spark, sf_dir).scores(), top=20, least=-400)


def alias_mass(spark, sf_dir):
    return alias.mass(alias.build(influence.decay(Part(spark, sf_dir).scores()))).select("query_id", "mention_id", r9("p"))


def alias_bytes(spark, sf_dir):
    return alias.table_bytes(alias.build(influence.decay(Part(spark, sf_dir).scores())))


def alias_presample(spark, sf_dir):
    return alias.presample(alias.build(influence.decay(Part(spark, sf_dir).scores())), 50)


def alias_spilled(spark, sf_dir):
    """The same from tables that were written down, and draws that were made ahead."""
    tables = alias.spill(alias.build(influence.decay(Part(spark, sf_dir).scores())), shared_path(spark, "alias"))
    return alias.mass(tables).select("query_id", "mention_id", r9("p"))


def init_states(spark, sf_dir):
    p = Part(spark, sf_dir)
    return p.three_states(p.members(p.one)).select("how", "mention_id", "entity_id")


def _three(spark, sf_dir):
    """Mentions, members and three states of one whole canopy."""
    p = Part(spark, sf_dir)
    members = p.members(p.one)
    return p, members, cut(p.three_states(members))


def _configured(spark, sf_dir):
    """The same with classes of mentions that no feature tells apart, and the weights between these."""
    p, members, states = _three(spark, sf_dir)
    of = score.classes(members, p.mentions).select("query_id", "mention_id", "rep")
    return p, states, of, cut(score.class_edges(of, p.mentions).drop("query_id"))


def config_score(spark, sf_dir):
    _, states, of, edges = _configured(spark, sf_dir)
    return score.config_score(states, edges, of).join(states.select("run_id", "how").distinct(), "run_id").select("how", "score")


def entity_score(spark, sf_dir):
    p, states, of, edges = _configured(spark, sf_dir)
    found = score.entity_score(states, p.mentions, edges.where("w > 0").select("i", "j"), of=of)
    return found.join(states.select("run_id", "how").distinct(), "run_id").select("how", "score")


def matching_strings(spark, sf_dir):
    p, _, states = _three(spark, sf_dir)
    return score.matching_strings(states.where("how = 'random'"), p.mentions).select("entity_a", "entity_b", "n")


def _every_move(states: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The random state, and all moves of its mentions to its entities."""
    s = cut(states.where("how = 'random'").drop("how"))
    return s, s.select("run_id", "mention_id").crossJoin(F.broadcast(s.select(F.col("entity_id").alias("entity_to")).distinct()))


def move_delta(spark, sf_dir):
    _, states, of, edges = _configured(spark, sf_dir)
    s, moves = _every_move(states)
    return score.move_delta(s, edges, moves, of).drop("run_id")


def _sel(spark, sf_dir):
    return blocking.selectivity(Part(spark, sf_dir).canopy())


def _plan(policy: str) -> Callable:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return schedule.plan(_sel(spark, sf_dir), policy, 1950, 100)

    return query


def _script(spark, sf_dir):
    """A trace made from events: user groups as queries, acceptance more likely for higher ones."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    q = F.pmod("user_id", F.lit(9))
    return e.select(F.lit(0).alias("run_id"), q.alias("query_id"), F.col("event_id").alias("step"), (F.pmod(h32(F.concat(F.lit("acc|"), F.col("event_id").cast("string"))), F.lit(10)) < q).alias("accepted"))


def acceptance_rates(spark, sf_dir):
    return schedule.acceptance(_script(spark, sf_dir), 50).select("query_id", "step", r9("rate"))


def _next(policy: str) -> Callable:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        rates = cut(schedule.latest(_script(spark, sf_dir), 50))
        return rates.join(schedule.next_query(rates, policy), ["run_id", "query_id"], "left_semi").select("query_id", r9("rate"))

    return query


def _prf(spark, sf_dir):
    p = Part(spark, sf_dir)
    s = baselines.same_string(p.mentions).withColumn("component", F.lit(0))
    parts = p.watch.select("query_id").withColumn("component", F.lit(0))
    return metrics.query_prf(samplers.answers(s, p.watch, parts), p.gold, p.watch, 1)


def query_prf(spark, sf_dir):
    return _prf(spark, sf_dir).select("query_id", "tp", "n_answer", "n_gold", r9("precision"), r9("recall"), r9("f1q"))


def mean_f1q(spark, sf_dir):
    return metrics.mean_f1q(_prf(spark, sf_dir)).select("n_queries", r9("mean_f1q"))


def metric_cube(spark, sf_dir):
    return _prf(spark, sf_dir).cube("n_gold", "query_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("f1q"), 9).alias("f1q"))


def average_runs(spark, sf_dir):
    return metrics.average_runs(_prf(spark, sf_dir), "n_gold").select("n_gold", r9("mean"), r9("sd"), "n_runs")


def b_cubed(spark, sf_dir):
    p = Part(spark, sf_dir)
    return metrics.b_cubed(baselines.same_string(p.mentions), p.gold).select(r9("precision"), r9("recall"), r9("f1"))


def query_ratios(spark, sf_dir):
    p = Part(spark, sf_dir)
    return metrics.ratios(p.watch, p.mentions).select("n_queries", "n_entities", "n_mentions", r9("queries_per_entity"), r9("mentions_per_entity"))


def pairwise_closure(spark, sf_dir):
    p = Part(spark, sf_dir)
    members = p.members(p.one)
    of = score.classes(members, p.mentions)
    return baselines.pairwise(score.class_edges(of, p.mentions), 60, members, of=of).select("mention_id", "entity_id")


def blocked_baseline(spark, sf_dir):
    parts = spark.read.parquet(f"{sf_dir}/part.parquet").withColumnRenamed("p_partkey", "mention_id")
    return baselines.blocked(parts, F.col("p_brand")).select("mention_id", "entity_id")


def coref_view(spark, sf_dir):
    return session.coref_pairs(baselines.same_string(Part(spark, sf_dir).mentions)).select("a", "b")


def clusters(spark, sf_dir):
    found = session.clusters(baselines.same_string(Part(spark, sf_dir).mentions))
    return found.select("entity_id", F.array_join(F.transform("mentions", lambda x: x.cast("string")), ",").alias("mentions"), "n")


def same_entity(spark, sf_dir):
    p = Part(spark, sf_dir)
    pairs = p.mentions.select(F.col("mention_id").alias("a"), (F.col("mention_id") + 64).alias("b"))
    last = p.mentions.select(F.col("mention_id").alias("b"))
    er = session.EntityResolution(p.mentions)
    return er.same_entity(pairs.join(last, "b", "left_semi"), baselines.same_string(p.mentions)).select("a", "b", "same_entity")


def context_levels(spark, sf_dir):
    p = Part(spark, sf_dir)
    found, out = cut(p.canopy()), None
    for level in features.LEVELS:
        s = influence.score(found, p.mentions, p.watch, features.PAIRWISE, None, level).withColumn("level", F.lit(level))
        out = s if out is None else out.unionByName(s)
    return out.select("level", "query_id", "mention_id", "infl")


def _few(spark, sf_dir):
    """Seven part mentions, their weights and the query's id."""
    few = cut(fixtures.few_mentions(fixtures.part_mentions(spark, sf_dir)))
    ids, own = few.select("mention_id"), few.select("own").first()[0]
    edges = score.pair_edges(ids.withColumn("query_id", F.lit(own)), few, features.CONTEXT_FIRST, None, "paragraph").drop("query_id")
    return ids, cut(edges), own


def exact_posterior(spark, sf_dir):
    ids, edges, _ = _few(spark, sf_dir)
    return exact.partition_posterior(ids, edges, temperature=100.0).select(F.array_join(F.transform("partition", lambda x: x.cast("string")), "").alias("partition"), "score", r9("prob"))


def exact_map(spark, sf_dir):
    return exact.map_query_cluster(*_few(spark, sf_dir))


def exact_marginal(spark, sf_dir):
    return exact.marginal_query(*_few(spark, sf_dir), 100.0).select("mention_id", r9("p_coref"))


def bsp_winners(spark, sf_dir):
    parts = spark.read.parquet(f"{sf_dir}/part.parquet")
    key = F.col("p_partkey")
    p = parts.select(F.lit(0).alias("run_id"), (key % 7).alias("query_id"), key.alias("n"), key.alias("mention_id"), (key % 50).alias("entity_from"), (F.pmod(h32(F.concat(F.lit("to|"), key.cast("string"))), F.lit(20)) + 1000).alias("entity_to"))
    return parallel.winners(p, 0).drop("run_id")


def _rounds(spark, sf_dir):
    """Queries, initial state, alias tables and weights of the watchlist's merged canopies."""
    p = Part(spark, sf_dir)
    members = p.members()
    tables = cut(alias.build(influence.decay(influence.score(members, p.mentions, p.watch, TWO, None, "paragraph"))))
    side = cut(score.sides(p.mentions.join(members.select("mention_id").distinct(), "mention_id", "left_semi"), "paragraph"))
    return p.watch, state.init(members), tables, lambda s, moves: score.move_delta_on_demand(s, side, moves, TWO)


def bsp_rounds(spark, sf_dir):
    """Bulk-synchronous rounds for the watchlist over its merged canopies: random schedule, fall-back, improvements."""
    watch, start, tables, by_pairs = _rounds(spark, sf_dir)
    return parallel.bsp(start, by_pairs, tables, watch, BSP_ROUNDS, workers=BSP_WORKERS).select("mention_id", "entity_id")


def bsp_proposals(spark, sf_dir):
    """A round's proposals by a random schedule, before any claim."""
    watch, start, tables, _ = _rounds(spark, sf_dir)
    return parallel.propose(start, tables, watch, 0, workers=BSP_WORKERS).drop("run_id")


def bsp_merge_round(spark, sf_dir):
    watch, start, tables, by_pairs = _rounds(spark, sf_dir)
    return parallel.merge_round(start, by_pairs, tables, watch, 0, per_query=BSP_WORKERS).select("mention_id", "entity_id")


def move_delta_on_demand(spark, sf_dir):
    """The deltas of move_delta from the pairs that moves meet, with cosines of contexts."""
    p, members, states = _three(spark, sf_dir)
    inside = cut(p.mentions.join(members.select("mention_id"), "mention_id", "left_semi"))
    s, moves = _every_move(states)
    return score.move_delta_by_class(s, members, inside, moves, features.SPECS).drop("run_id")


def passage_watchlist(spark, sf_dir):
    return extract.passages(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def email_mentions(spark, sf_dir):
    return fixtures.email_mentions(spark, sf_dir).select("doc_id", "startpos", "mention")


def document_mentions(spark, sf_dir):
    return fixtures.document_mentions(spark, sf_dir).select("mention_id", "mention")


def page_mentions(spark, sf_dir):
    return fixtures.page_mentions(spark, sf_dir).select("mention_id", "mention", "gold")


def conversation_mentions(spark, sf_dir):
    return fixtures.conversation_mentions(spark, sf_dir).select("mention_id", "mention", "gold")


def _curves(spark, sf_dir):
    p = Part(spark, sf_dir)
    both = cut(p.chain("influence_to_query"))
    start = samplers.states(both).select("component", "mention_id", F.col("mention_id").alias("entity_id"))
    inside = p.gold.join(start.select("mention_id"), "mention_id", "left_semi")
    return metrics.curve(samplers.traces(both), start, inside, p.one)


def trace_curve(spark, sf_dir):
    return metrics.upto(_curves(spark, sf_dir), 50).select("step", r9("f1q"))


def time_to_target(spark, sf_dir):
    return metrics.time_to(_curves(spark, sf_dir), 0.5).select("query_id", "first_step")


def score_trace(spark, sf_dir):
    return metrics.score_trace(samplers.traces(Part(spark, sf_dir).chain("influence_to_query"))).select("step", "score")


def proposal_counts(spark, sf_dir):
    return metrics.proposals(samplers.traces(Part(spark, sf_dir).chain("uniform"))).select("proposals", "accepted", r9("rate"), "first_accepted")


def steady_state(spark, sf_dir):
    t = _script(spark, sf_dir).withColumn("run_id", F.col("query_id").cast("int"))
    return converge.steady(t, 40, 0.2)


def _resolver(p: Part, **options) -> session.EntityResolution:
    return session.EntityResolution(p.mentions, TWO, "paragraph", **options)


def select_entity(spark, sf_dir):
    """Selection over a whole canopy."""
    p = Part(spark, sf_dir)
    er = _resolver(p, settings=samplers.Settings(samples=SELECT_STEPS, draw="cdf"))
    return er.select_entity(p.one).select("query_id", "mention_id")


def select_entity_large(spark, sf_dir):
    """Selection over a large canopy, by the published features with contexts' cosines: the model is the same at any size."""
    m = fixtures.line_mentions(spark, sf_dir)
    plain = m.where(F.lower("mention") == F.col("gold")).groupBy("gold").agg(F.min("mention_id").alias("mention_id"))
    own = plain.orderBy(h32(F.concat(F.lit("name|"), F.col("gold"))), "gold").limit(1).select("mention_id")
    q = cut(as_queries(m.join(F.broadcast(own), "mention_id")))
    er = session.EntityResolution(m, level="document", min_shared=LARGE_SHARED, settings=samplers.Settings(samples=LARGE_STEPS, draw="cdf"))
    packed, _, frame, _ = er.packed(q)
    both = cut(samplers.chains(packed, er.settings, 1, er.specs))
    return samplers.traces(both).select("step", "m", "e_from", "e_to", "delta", "accepted")


def select_auto(spark, sf_dir):
    """Selection in the direction that each canopy's quality calls for."""
    p = Part(spark, sf_dir)
    er = _resolver(p, settings=samplers.Settings(samples=SELECT_STEPS, draw="cdf"))
    return er.select_entity(p.watch, direction="auto").select("query_id", "mention_id")


def canopy_direction(spark, sf_dir):
    p = Part(spark, sf_dir)
    members = p.members()
    return session.choose_direction(members, influence.score(members, p.mentions, p.watch, TWO, None, "paragraph")).select("query_id", r9("share"), "direction")


def warm_start(spark, sf_dir):
    """A selection carried on from an earlier result: as many proposals again."""
    p = Part(spark, sf_dir)
    er = _resolver(p, settings=samplers.Settings(samples=SELECT_STEPS, draw="cdf"))
    packed, *_ = er.packed(p.one)
    before = cut(er.states(packed).select("mention_id", "entity_id"))
    return er.select_entity(p.one, start=before, seed=2).select("query_id", "mention_id")


def join_entities(spark, sf_dir):
    """A watchlist join over merged whole canopies."""
    p = Part(spark, sf_dir)
    er = _resolver(p, settings=samplers.Settings(samples=SELECT_STEPS, draw="cdf", quantum=25))
    return er.join_entities(p.watch, "round_robin").select("query_id", "mention_id")


def join_by_selectivity(spark, sf_dir):
    p = Part(spark, sf_dir)
    er = _resolver(p, settings=samplers.Settings(samples=SELECT_STEPS, draw="cdf", quantum=25))
    return er.join_entities(p.watch, "by_selectivity").select("query_id", "mention_id")


TEMPLATE = QueryNode("red plate", keywords=("topic_red_plate",))


def _by_template(spark, sf_dir) -> session.EntityResolution:
    return _resolver(Part(spark, sf_dir), settings=samplers.Settings(samples=SELECT_STEPS, draw="cdf"))


def select_keywords(spark, sf_dir):
    """A declared template with keywords, over its whole canopy."""
    return _by_template(spark, sf_dir).select_entity(TEMPLATE).select("query_id", "mention_id")


def select_sql(spark, sf_dir):
    """The same question in SQL."""
    return _by_template(spark, sf_dir).sql("SELECT mention_id, mention FROM mentions WHERE same_entity(mentions, :q)", q=TEMPLATE)


def select_udtf(spark, sf_dir):
    """The same as a table function over a canopy, without cosines."""
    from erfocus.plans import udtf

    p = Part(spark, sf_dir)
    udtf.register(spark)
    node = TEMPLATE.frame(spark)
    found = blocking.canopy(p.mentions, node).select("mention_id").distinct()
    p.mentions.join(found, "mention_id", "left_semi").createOrReplaceTempView("erfocus_canopy")
    return spark.sql(f"SELECT * FROM er_select(TABLE(SELECT mention_id, mention, context FROM erfocus_canopy) WITH SINGLE PARTITION, 'red plate', array('topic_red_plate'), {SELECT_STEPS})")


def resolve_all(spark, sf_dir):
    """The exhaustive view over customer mentions in blocks of customers' names without their padding."""
    m = fixtures.customer_mentions(spark, sf_dir)
    er = session.EntityResolution(m, features.SHORT_NAMES, "paragraph")
    return er.resolve_all(workloads.CUSTOMER_BLOCK, samples=RESOLVE_STEPS)


def _with_mh(spark, sf_dir):
    """Metropolis-Hastings acceptance with explicit proposal probabilities."""
    return _chain("influence_to_query", accept="mh", temperature=30.0)(spark, sf_dir)


def chain_idle(spark, sf_dir):
    """Where a chain over each watchlist canopy ends that stops after 200 proposals in vain."""
    p = Part(spark, sf_dir)
    packed = cut(samplers.pack(p.members(), p.mentions, p.watch, None, "paragraph"))
    both = samplers.chains(packed, samplers.Settings(samples=4000, idle=200, draw="cdf", cosines=False), 1, TWO)
    return samplers.traces(both).groupBy(F.col("component").alias("query_id")).agg(F.count(F.lit(1)).alias("proposals"), F.count_if("accepted").alias("accepted"))


def first_correct(spark, sf_dir):
    p = Part(spark, sf_dir)
    return metrics.first_correct(samplers.traces(p.chain("uniform", 2 * STEPS)), p.gold, p.one).select("query_id", "step")


def salient_terms(spark, sf_dir):
    """Keywords that tell a canopy's true mentions from the others."""
    p = Part(spark, sf_dir)
    members = p.members(p.one)
    terms = members.join(context.context_terms(p.mentions), "mention_id")
    wanted = members.join(p.gold, "mention_id").join(p.one.select("query_id", F.col("gold").alias("g")), "query_id").where("gold = g").select("query_id", "mention_id")
    return context.salient(terms, wanted, 3)


def stream_windows(spark, sf_dir):
    return growth.replay_windows(spark, sf_dir)


def stream_sessions(spark, sf_dir):
    return growth.replay_sessions(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        line_mentions, customer_mentions, document_mentions, email_mentions, page_mentions, conversation_mentions,
        qgram_postings, gram_df, canopy_single, canopy_watchlist, canopy_rarest_grams, canopy_sorted_neighborhood, vector_blocks,
        watchlist_selectivity, gold_selectivity, canopy_quality, merged_components, term_stats, tfidf_cosine,
        pair_features, pair_edges, influence_scores, influence_decay, influence_decay_by_score, inverse_influence, influence_top,
        alias_mass, alias_bytes, alias_presample, alias_spilled, init_states, config_score, entity_score, matching_strings, move_delta,
        acceptance_rates, query_prf, mean_f1q, metric_cube, average_runs, b_cubed, query_ratios, pairwise_closure, blocked_baseline,
        coref_view, clusters, same_entity, context_levels, exact_posterior, exact_map, exact_marginal, bsp_winners, bsp_rounds, bsp_merge_round,
        bsp_proposals, move_delta_on_demand, passage_watchlist, trace_curve, time_to_target, score_trace, proposal_counts, steady_state, first_correct, salient_terms,
        select_entity, select_entity_large, select_auto, canopy_direction, warm_start, join_entities, join_by_selectivity, select_keywords, select_sql, select_udtf, resolve_all, chain_idle,
        stream_windows, stream_sessions,
    )
}
QUERIES |= {f"chain_{s}": _chain(s) for s in ("uniform", "pin_target", "influence_both", "influence_to_query", "expel", "expel_both")}
QUERIES |= {"stream_canopy": lambda spark, sf_dir: growth.replay(spark, sf_dir)}
QUERIES |= workloads.WORKLOADS
QUERIES |= {"chain_mh": _with_mh, "chain_alias": _chain("influence_to_query", draw="alias")}
QUERIES |= {f"schedule_{p}": _plan(p) for p in ("round_robin", "by_selectivity", "equal")}
QUERIES |= {f"schedule_{p}": _next(p) for p in ("closest_first", "farthest_first", "slowest_first")}
