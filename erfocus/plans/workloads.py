"""The experiments on the given tables.  Settings are fixed here, before samplers are compared.

Where a table has fewer mentions of a name than a workload asks for, all it has are taken.  A target that is
not reached is null, never lowered.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.functions.rand import h32
from erfocus.operators import alias, baselines, blocking, context, exact, extract, influence, metrics, parallel, samplers, score, state, train
from erfocus.operators.components import connected_components
from erfocus.operators.durable import cut, freed, held, sized
from erfocus.plans import session
from erfocus.sources import fixtures
from erfocus.sources.schema import QueryNode, as_queries

TWO = features.TWO_WORD_NAMES
LEVEL = "paragraph"
#: Selectivities of the comparisons.
COMPARED = (11, 46, 130)
RISING = (11, 46, 68, 130, 301)
SCHEDULED = (130, 63, 68, 7, 12, 12, 301, 11, 46)
#: Canopies of the three real-time queries, and the accuracy of one entity of all that they start from.
REAL_TIME = ((103, 0.65), (226, 0.92), (1302, 0.97))
TARGET = 0.95


def names(mentions: DataFrame, n: int) -> DataFrame:
    """(query_id, gold, own): n names, in hash order, with a representative query: their first clean mention in its own topic."""
    topic = F.concat(F.lit("topic_"), F.replace("gold", F.lit(" "), F.lit("_")))
    clean = mentions.where((F.lower("mention") == F.col("gold")) & F.array_contains("context.paragraph", topic)).groupBy("gold").agg(F.min("mention_id").alias("own"))
    order = (h32(F.concat(F.lit("name|"), F.col("gold"))), "gold")
    w = Window.orderBy(*order)
    return clean.orderBy(*order).limit(n).withColumn("query_id", (F.row_number().over(w)).cast("long")).select("query_id", "gold", "own")


def designed(mentions: DataFrame, wanted: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(members (query_id, mention_id), queries) from (query_id, gold, own, sel, size): canopies of size mentions, sel of the label.

    Others are the best matches of the other labels, of each label in turn.  mentions should lie written down.
    """
    few = held(wanted)
    queries = cut(mentions.join(few.select("query_id", "own"), F.col("mention_id") == F.col("own")).drop("own"))
    same = mentions.join(few, "gold").where("mention_id <> own").select("query_id", "mention_id", "sel", F.row_number().over(Window.partitionBy("query_id").orderBy("mention_id")).alias("k")).where("k < sel")
    named = mentions.select("mention_id", F.col("gold").alias("g"))
    found = blocking.canopy(mentions, queries, min_shared=2).join(named, "mention_id").join(few, "query_id").where("g <> gold")
    found = found.withColumn("turn", F.row_number().over(Window.partitionBy("query_id", "g").orderBy(F.desc("shared"), "mention_id"))).where("turn <= size")
    w = Window.partitionBy("query_id").orderBy("turn", F.desc("shared"), "mention_id")
    other = found.withColumn("k", F.row_number().over(w)).where("k <= size - sel").select("query_id", "mention_id")
    members = same.select("query_id", "mention_id").union(other).union(queries.select("query_id", "mention_id")).distinct()
    return cut(members), queries


def packed(mentions: DataFrame, members: DataFrame, queries: DataFrame, level: str = LEVEL, components: DataFrame | None = None) -> DataFrame:
    return cut(samplers.pack(members, mentions, queries, components, level))


def start_of(members: DataFrame, single: bool, components: DataFrame | None = None) -> DataFrame:
    owner = components if components is not None else members.select("query_id").distinct().withColumn("component", F.col("query_id"))
    rows = members.join(held(owner), "query_id").select("component", "mention_id").distinct()
    least = rows.groupBy("component").agg(F.min("mention_id").alias("entity_id"))
    return rows.join(least, "component") if single else rows.withColumn("entity_id", F.col("mention_id"))


def run(rows: DataFrame, mentions: DataFrame, members: DataFrame, queries: DataFrame, settings: samplers.Settings, runs: int, components: DataFrame | None = None, specs=TWO) -> tuple[DataFrame, DataFrame]:
    """(curves, seconds by component and run)."""
    both = cut(samplers.chains(rows, settings, runs, specs))
    single = settings.sampler in ("expel", "expel_both") and settings.init is None
    gold = mentions.select("mention_id", "gold").join(members.select("mention_id").distinct(), "mention_id", "left_semi")
    curves = metrics.curve(samplers.traces(both), start_of(members, single, components), gold, queries, components)
    return cut(curves), samplers.seconds(both)


def _wanted(picked: DataFrame, sizes: list[tuple[int, int]]) -> DataFrame:
    rows = picked.sparkSession.createDataFrame([(i + 1, s, n) for i, (s, n) in enumerate(sizes)], "query_id long, sel int, size int")
    return picked.join(F.broadcast(rows), "query_id")


REAL_TIME_SIZES = [(round(n * f / (2 - f)), n) for n, f in REAL_TIME]
REAL_TIME_SETTINGS = samplers.Settings(sampler="expel", samples=500, draw="cdf")


def _real_time(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, metrics.Timings]:
    """(accuracy and size by query, chain seconds by query, seconds of the stages)."""
    t = metrics.Timings()
    with t.stage("corpus"):
        m = cut(fixtures.line_mentions(spark, sf_dir))
        wanted = cut(_wanted(names(m, 3), REAL_TIME_SIZES))
    with t.stage("blocking"):
        members, queries = designed(m, wanted)
    with t.stage("context"):
        rows = packed(m, members, queries)
    with t.stage("inference"):
        both = cut(samplers.chains(rows, REAL_TIME_SETTINGS, 6, TWO))
    with t.stage("answers"):
        cut(samplers.answers(samplers.states(both), queries))
    gold = m.select("mention_id", "gold").join(members.select("mention_id").distinct(), "mention_id", "left_semi")
    curves = cut(metrics.curve(samplers.traces(both), start_of(members, True), gold, queries))
    at = lambda step, name: metrics.at_step(curves, step).groupBy("query_id").agg(F.avg("f1q").alias(name))
    size = members.groupBy("query_id").agg(F.count(F.lit(1)).alias("canopy"))
    found = size.join(at(-1, "f1_start"), "query_id").join(at(49, "f1_50"), "query_id").join(at(499, "f1_500"), "query_id")
    return found, samplers.seconds(both).groupBy(F.col("component").alias("query_id")).agg(F.avg("seconds").alias("chain_seconds")), t


def w1_real_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three single queries over line mentions: expulsion from one entity of all, first 50 proposals, 6 runs."""
    found, _, _ = _real_time(spark, sf_dir)
    return found.select("query_id", "canopy", *[F.round(c, 9).alias(c) for c in ("f1_start", "f1_50", "f1_500")])


def w1_timings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the stages of the same, for all three queries together, and of a query's chain."""
    found, seconds_, t = _real_time(spark, sf_dir)
    out = found.select("query_id", "canopy").join(seconds_, "query_id")
    for name, s in t.seconds.items():
        out = out.withColumn(f"{name}_seconds", F.lit(round(s, 3)))
    return out.withColumn("total_seconds", F.lit(round(t.total, 3)))


#: Proposals, canopy and runs of the comparisons.
COMPARISON = dict(canopy=300, samples=2500, runs=10)
KINDS = ("uniform", "pin_target", "influence_both", "influence_to_query")


def _without_topics(m: DataFrame) -> DataFrame:
    """Every mention with a topic word of its own label, for names() where no topic says anything."""
    own = F.array(F.concat(F.lit("topic_"), F.replace("gold", F.lit(" "), F.lit("_"))))
    return m.withColumn("context", F.col("context").withField("paragraph", own))


def _compare(spark: SparkSession, sf_dir: str, sels: tuple[int, ...], canopy: int, kinds: tuple[str, ...], samples: int, runs: int, informative: int = fixtures.INFORMATIVE, specs=TWO, seconds: bool = False, **changes) -> DataFrame:
    m = cut(fixtures.part_mentions(spark, sf_dir, informative=informative))
    picked = names(m if informative else _without_topics(m), len(sels))
    members, queries = designed(m, cut(_wanted(picked, [(s, canopy) for s in sels])))
    rows = packed(m, members, queries)
    true = members.join(m.select("mention_id", "gold"), "mention_id").join(queries.select("query_id", F.col("gold").alias("g")), "query_id").where("gold = g").groupBy("query_id").agg(F.count(F.lit(1)).alias("selectivity"))
    out = None
    for kind in kinds:
        curves, took = run(rows, m, members, queries, samplers.Settings(sampler=kind, samples=samples, draw="cdf", **changes), runs, specs=specs)
        end = metrics.at_step(curves, samples).join(metrics.time_to(curves, TARGET), ["component", "run_id", "query_id"]).join(took, ["component", "run_id"])
        reached = end.groupBy("query_id").agg(
            F.avg("f1q").alias("f1_at_budget"), F.stddev("f1q").alias("sd"), F.avg("first_step").alias("steps_to_target"), F.count("first_step").alias("runs_reached"), F.count(F.lit(1)).alias("runs"), F.avg("seconds").alias("chain_seconds")
        ).withColumn("sampler", F.lit(kind))
        out = reached if out is None else out.unionByName(reached)
    rounded = [F.round(c, 9).alias(c) for c in ("f1_at_budget", "sd", "steps_to_target")]
    return out.join(true, "query_id").select("sampler", "query_id", "selectivity", *rounded, "runs_reached", "runs", *(["chain_seconds"] if seconds else []))


def w2_samplers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four samplers, gathering, at three selectivities and one canopy size."""
    return _compare(spark, sf_dir, COMPARED, kinds=KINDS, **COMPARISON)


def w2_uninformative(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same without any topic word that names an entity: what strings alone give."""
    return _compare(spark, sf_dir, COMPARED, kinds=KINDS, informative=0, **COMPARISON)


def w2_annealed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with Metropolis-Hastings acceptance at a temperature."""
    return _compare(spark, sf_dir, COMPARED, kinds=KINDS, accept="mh", temperature=30.0, **COMPARISON)


def w2_published(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with the published table's weights, the decay's p as published, and entity-wide terms."""
    return _compare(spark, sf_dir, COMPARED, kinds=KINDS, specs=features.SPECS, scaled=False, entity_wide=True, **COMPARISON)


#: Names that weights are learned from stand after those that workloads ask for.
TRAINING = (12, 20)


def learned_specs(spark: SparkSession, m: DataFrame) -> tuple:
    """Weights learned by ranking on the labels of names that no workload asks for."""
    every = names(m, TRAINING[1])
    picked = every.where(F.col("query_id") > TRAINING[0])
    sizes = F.lit(60).alias("sel"), F.lit(200).alias("size")
    members, queries = designed(m, cut(picked.select("*", *sizes)))
    learned = cut(train.sample_rank(packed(m, members, queries), m.select("mention_id", "gold"), features.PAIRWISE, 6000, 1))
    return train.fitted(learned, features.PAIRWISE)


def w2_learned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same with weights learned on the labels of other names, as for the labelled corpus of the experiments."""
    m = cut(fixtures.part_mentions(spark, sf_dir))
    return _compare(spark, sf_dir, COMPARED, kinds=KINDS, specs=learned_specs(spark, m), **COMPARISON)


def trained_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(feature, w_pos, w_neg): what ranking on labels makes of the pairwise features; tiers as features of their own."""
    specs = learned_specs(spark, cut(fixtures.part_mentions(spark, sf_dir)))
    rows = [(s.name, s.plus, s.minus) for s in specs if s.name != "f08"]
    rows += [(f"f08>={least}", w, 0) for s in specs if s.name == "f08" for least, w in (*s.tiers, (0.0, s.lowest))]
    return spark.createDataFrame(rows, "feature string, w_pos long, w_neg long")


def w3_score_decay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rising selectivity with decay on the score instead of the rank."""
    return _compare(spark, sf_dir, RISING, 1000, ("influence_both", "influence_to_query"), 8000, 3, unit="score")


def w3_selectivity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Proposals to the target over rising selectivity at one canopy size; weights learned on other names."""
    m = cut(fixtures.part_mentions(spark, sf_dir))
    return _compare(spark, sf_dir, RISING, 1000, KINDS, 8000, 3, specs=learned_specs(spark, m))


def w4_schedules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nine queries over one merged model under each schedule: mean accuracy along the way, 3 runs."""
    m = cut(fixtures.part_mentions(spark, sf_dir))
    members, queries = designed(m, cut(_wanted(names(m, len(SCHEDULED)), [(s, 2 * s + 40) for s in SCHEDULED])))
    one = queries.select("query_id").withColumn("component", F.lit(0).cast("long"))
    rows = packed(m, members, queries, components=one)
    total, out = 18_000, None
    for policy in ("round_robin", "by_selectivity", "closest_first", "farthest_first", "slowest_first", "equal"):
        curves, _ = run(rows, m, members, queries, samplers.Settings(samples=total, policy=policy, draw="cdf"), 3, one)
        for at in (total // 8, total // 4, total // 2, total):
            mean = metrics.at_step(curves, at).groupBy("run_id").agg(F.avg("f1q").alias("f")).agg(F.avg("f").alias("mean_f1q"), F.stddev("f").alias("sd"))
            row = mean.select(F.lit(policy).alias("policy"), F.lit(at).alias("proposals"), F.round("mean_f1q", 9).alias("mean_f1q"), F.round("sd", 9).alias("sd"))
            out = row if out is None else out.unionByName(row)
    return out


#: What the query's context may be: its level, whether it has keywords, the level at which mentions are read.
CONTEXTS = (("none", "none", False, "paragraph"), ("paragraph", "paragraph", False, "paragraph"), ("document", "document", False, "document"), ("paragraph+keywords", "paragraph", True, "paragraph"), ("document+keywords", "document", True, "document"))
CONTEXT_SETTINGS = samplers.Settings(sampler="expel", samples=600, draw="cdf")


def w5_context(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of expulsion by how much context the query has, and with keywords, 6 runs."""
    m = cut(fixtures.part_mentions(spark, sf_dir))
    members, queries = designed(m, cut(_wanted(names(m, 1), [(46, 103)])))
    gold = queries.first()["gold"]
    words, out = (f"topic_{gold.replace(' ', '_')}",), None
    inside = cut(m.join(members.select("mention_id").distinct(), "mention_id", "left_semi"))
    for label, of_query, with_words, level in CONTEXTS:
        row = _in_context(inside, members, queries, of_query, words if with_words else (), level, TWO)
        out = row.withColumn("level", F.lit(label)) if out is None else out.unionByName(row.withColumn("level", F.lit(label)))
    return out.select("level", "f1_start", "f1_end", "sd")


def _in_context(m: DataFrame, members: DataFrame, queries: DataFrame, of_query: str, words: tuple, level: str, specs) -> DataFrame:
    """(f1_start, f1_end, sd): expulsion with the queries' context changed, 6 runs, averaged over queries."""
    q = context.apply(queries, of_query, words)
    changed = m.join(q.select("mention_id", F.col("context").alias("qc")), "mention_id", "left").withColumn("context", F.coalesce("qc", "context")).select(m.columns)
    curves, _ = run(packed(changed, members, q, level), m, members, queries, CONTEXT_SETTINGS, 6, specs=specs)
    start = metrics.at_step(curves, -1).agg(F.round(F.avg("f1q"), 9).alias("f1_start"))
    end = metrics.at_step(curves, CONTEXT_SETTINGS.samples).groupBy("run_id").agg(F.avg("f1q").alias("f1q")).agg(F.round(F.avg("f1q"), 9).alias("f1_end"), F.round(F.stddev("f1q"), 9).alias("sd"))
    return start.crossJoin(end)


def w5_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over text: near copies of documents, whose contexts are the words of a paragraph or of the whole text.

    Queries are the six largest groups' first documents; keywords are the words most particular to the group.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    gold = cut(near_copy_gold(docs))
    m = fixtures.document_mentions(spark, sf_dir)
    q = _largest_groups(m, gold, 6)
    every = cut(cut(m.select("mention_id")).join(gold, "mention_id").select("mention_id", h32(F.concat(F.lit("d|"), F.col("mention_id").cast("string"))).alias("h"), F.col("gold").alias("g")))
    # A query takes its group and the first others by hash: these are among as many firsts of all as the largest takes.
    groups = q.select("query_id", F.col("gold").alias("qgold"))
    mine = cut(every.join(F.broadcast(groups.select(F.col("qgold").alias("g")).distinct()), "g", "left_semi").select("mention_id", "h", "g"))
    most = mine.groupBy("g").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    near = cut(mine.union(every.orderBy("h", "mention_id").limit(3 * most + 20)).distinct())
    rows = near.crossJoin(F.broadcast(groups))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.when(F.col("g") == F.col("qgold"), 0).otherwise(1), "h", "mention_id"))
    n_gold = F.count_if(F.col("g") == F.col("qgold")).over(Window.partitionBy("query_id"))
    members = cut(rows.select("query_id", "mention_id", rank.alias("k"), n_gold.alias("n")).where("k <= 3 * n + 20").select("query_id", "mention_id"))
    labels = near.join(members.select("mention_id").distinct(), "mention_id", "left_semi").select("mention_id", F.col("g").alias("gold"))
    inside = cut(m.drop("gold").join(held(labels), "mention_id").select("mention_id", "doc_id", "startpos", "mention", "context", "gold"))
    terms = members.join(context.context_terms(inside, "document"), "mention_id")
    wanted = members.join(inside.select("mention_id", F.col("gold").alias("g")), "mention_id").join(q.select("query_id", "gold"), "query_id").where("g = gold").select("query_id", "mention_id")
    words = tuple(sorted({r["term"] for r in context.salient(terms, wanted, 2).toLocalIterator()}))
    out = None
    for label, of_query, with_words, level in CONTEXTS:
        row = _in_context(inside, members, q, of_query, words if with_words else (), level, features.SHORT_NAMES).withColumn("level", F.lit(label))
        out = row if out is None else out.unionByName(row)
    return out.select("level", "f1_start", "f1_end", "sd")


#: Queries, workers of a round, and the rounds after which accuracy is taken.
PARALLEL = dict(counts=(1, 8, 64, 512), workers=4096, marks=(1, 2))


def w6_parallel(spark: SparkSession, sf_dir: str, counts: tuple[int, ...] = PARALLEL["counts"], marks: tuple[int, ...] = PARALLEL["marks"]) -> DataFrame:
    """Rising numbers of random queries over line mentions: parallel rounds of the hybrid at tau 1 over one merged
    canopy, beside rounds of uniform proposals; mean accuracy, and seconds and bytes of the alias tables.

    Whole canopies (five grams shared) are taken.  A round has the same number of workers for any number of queries; each
    takes a query at random.  Workers of one query would all claim its entity: its improvements are merged at once and
    repaired.  The baseline makes as many proposals, all uniform.
    """
    # Mentions of equal string, context and label are of one class, named by its smallest: pairs, influence and canopies
    # are those of classes, and only ids are kept of the others.
    m = fixtures.line_mentions(spark, sf_dir)
    first = F.min_by(F.struct(*[c for c in m.columns if c not in ("mention_id", "mention", "gold")]), "mention_id").alias("r")
    alike = cut(m.groupBy("mention", F.col("context.paragraph").alias("words"), "gold").agg(F.min("mention_id").alias("rep"), first, F.collect_list("mention_id").alias("ids")))
    of = cut(alike.select(F.explode("ids").alias("mention_id"), "rep"))
    reps = cut(alike.select(F.col("rep").alias("mention_id"), "mention", "gold", "r.*").select(m.columns))
    n_of = cut(alike.select("rep", F.size("ids").cast("long").alias("n")))
    side = sized(cut(score.sides(reps, LEVEL)))
    labels = sized(cut(reps.select(F.col("mention_id").alias("rep"), "gold")))
    order = of.select("mention_id", h32(F.concat(F.lit("q|"), F.col("mention_id").cast("string"))).alias("h")).orderBy("h", "mention_id").limit(max(counts))
    ranked = order.withColumn("rank", F.row_number().over(Window.orderBy("h", "mention_id"))).select("mention_id", "rank")
    shown = reps.select(F.col("mention_id").alias("rep"), "mention", "context", "gold")
    picked = cut(as_queries(of.join(held(ranked), "mention_id").join(shown, "rep").drop("rep")))
    gold, entities = of.join(labels, "rep").select("mention_id", "gold"), reps.select("gold").distinct().count()
    out = []
    for n in counts:
        queries = cut(picked.where(F.col("rank") <= n))
        # A query shares all its grams with itself, so that its own class is in its canopy.
        found = cut(blocking.canopy(reps, queries, min_shared=5).select("query_id", "mention_id"))
        members = found.withColumnRenamed("mention_id", "rep").join(n_of, "rep").agg(F.sum("n")).first()[0] or 0
        inside = cut(of.join(held(found.select(F.col("mention_id").alias("rep")).distinct()), "rep").select("mention_id", "rep"))
        scores = influence.score(found, reps, queries, TWO, None, LEVEL).withColumnRenamed("mention_id", "rep")
        draws, seconds_ = parallel.draws_seconds(cut(scores), inside, queries, max(marks), PARALLEL["workers"])
        by_pairs = lambda state, moves, inside=inside: score.move_delta_on_demand(state, side, moves, TWO, of=inside)
        pool = inside.count()
        workers = PARALLEL["workers"]
        parts = queries.select("query_id").withColumn("component", F.lit(0).cast("long"))
        judge = lambda s, q=queries, parts=parts: metrics.query_prf(samplers.answers(s.withColumn("component", F.lit(0).cast("long")), q, parts), gold, q, 1).agg(F.avg("f1q")).first()[0]
        s = base = state.init(inside.select("mention_id"))
        done = 0
        for mark in marks:
            for step in range(done, mark):
                drawn = draws.where(F.col("step") == step).drop("step")
                s = cut(parallel.merge_round(s, by_pairs, None, queries, step, workers=workers, drawn=drawn))
                base = parallel.uniform_round(base, by_pairs, workers, step)
            done = mark
            out.append((n, entities, n / entities, pool, members, mark, workers * mark, judge(s), judge(base), round(seconds_, 3), 12 * members))
    return spark.createDataFrame(
        out, "n_queries long, n_entities long, queries_per_entity double, pool long, table_entries long, rounds long, proposals long, mean_f1q double, uniform_f1q double, alias_seconds double, alias_bytes long"
    )


def w7_worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seven part mentions: each sampler's best score over 20 runs beside the exact maximum."""
    few = cut(fixtures.few_mentions(fixtures.part_mentions(spark, sf_dir)))
    members = few.select(F.col("own").alias("query_id"), "mention_id")
    queries = as_queries(few.where("mention_id = own"))
    rows = cut(samplers.pack(members, few, queries, None, LEVEL))
    edges = cut(samplers.edges(rows, features.CONTEXT_FIRST))
    best = exact.map_partition(exact.partition_posterior(few.select("mention_id"), edges)).first()["score"]
    out = None
    for kind in ("uniform", "pin_target", "influence_both", "influence_to_query", "expel", "expel_both"):
        states = samplers.states(samplers.chains(rows, samplers.Settings(sampler=kind, samples=400, draw="cdf"), 20, features.CONTEXT_FIRST))
        got = score.config_score(states, edges).agg(F.max("score").alias("best_score"), F.avg("score").alias("mean_score"))
        row = got.select(F.lit(kind).alias("sampler"), "best_score", "mean_score", F.lit(best).alias("exact_score"))
        out = row if out is None else out.unionByName(row)
    return out


#: Blocks of customers; proposals of a block's chain stopped early, the most of a whole one, and how many in vain end it.
CUSTOMER_BLOCK = "regexp_extract(mention, '([0-9]{8})', 1)"
EXHAUSTIVE = (300, 60_000, 3000)


def w8_exhaustive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customer mentions resolved wholly, beside baselines, by B-cubed."""
    m = fixtures.customer_mentions(spark, sf_dir)
    gold = m.select("mention_id", "gold")
    er = session.EntityResolution(m, features.SHORT_NAMES, LEVEL)
    packed = er.packed_blocks(CUSTOMER_BLOCK)
    found = {
        "stopped early": er.resolve_all(CUSTOMER_BLOCK, samples=EXHAUSTIVE[0], packed=packed),
        "exhaustive": er.resolve_all(CUSTOMER_BLOCK, samples=EXHAUSTIVE[1], packed=packed, idle=EXHAUSTIVE[2]),
        "same_string": baselines.same_string(m),
        "blocked": baselines.blocked(m, F.expr(CUSTOMER_BLOCK)),
        "alone": baselines.alone(m),
    }
    out = None
    for k, s in found.items():
        row = metrics.b_cubed(s, gold).select(F.lit(k).alias("method"), *[F.round(c, 9).alias(c) for c in ("precision", "recall", "f1")])
        out = row if out is None else out.unionByName(row)
    return out


def near_copy_gold(documents: DataFrame, least: float = 0.5) -> DataFrame:
    """(mention_id, gold): components of documents whose word 3-shingles have a Jaccard of at least this; a fixture's truth.

    Texts of the same shingles are one.  Each is indexed by its rarest shingles, so many that two texts of that
    similarity share one of them; no link is lost.  Shingles are made anew from the texts where they are asked for and
    never written down; those of one text only leave the first exchange, and of a pair's two texts only one is exchanged
    with the pair.
    """
    split = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), lambda w: w != "")

    def shingled(docs: DataFrame) -> DataFrame:
        # Rows of an explode are worked out once, not anew for each element of a lambda that uses them.
        rows = docs.select(F.col("doc_id").alias("mention_id"), F.explode(F.array(split)).alias("ws"))
        shingles = F.array_distinct(F.transform(F.slice("ws", 1, F.greatest(F.size("ws") - 2, F.lit(0))), lambda w, i: F.xxhash64(w, F.get("ws", i + 1), F.get("ws", i + 2))))
        return rows.select("mention_id", F.explode(F.array(shingles)).alias("s"))

    # Sixty-four bits of a shingle are what texts are compared by; forty propose, of which a text has x fewer.
    forty = F.array_distinct(F.transform("s", lambda x: x.bitwiseAND(F.lit((1 << 40) - 1))))
    digest = F.sha2(F.array_join(F.transform(F.array_sort("s"), lambda x: x.cast("string")), ","), 256)
    d = cut(shingled(documents).select("mention_id", F.size("s").alias("n"), (F.size("s") - F.size(forty)).alias("x"), F.when(F.size("s") > 0, digest).alias("key")))
    same = Window.partitionBy("key")
    d = cut(d.select("mention_id", "n", "x", F.when(F.col("n") > 0, F.min("mention_id").over(same)).otherwise(F.col("mention_id")).alias("node")))
    classes = cut(d.where("mention_id = node AND n > 0").select("node", "n", "x"))
    texts = lambda ids: documents.select("doc_id", "text").join(sized(ids.select(F.col("node").alias("doc_id"))), "doc_id", "left_semi")
    each = shingled(texts(classes)).select(F.col("mention_id").alias("node"), F.explode(forty).alias("g"))
    common = each.withColumn("f", F.count(F.lit(1)).over(Window.partitionBy("g"))).where("f > 1")
    # A text's shingles of no other text come first in its order, so that only their number is needed.
    of = Window.partitionBy("node")
    ranked = common.withColumn("k", F.row_number().over(of.orderBy("f", "g"))).withColumn("c", F.count(F.lit(1)).over(of)).join(sized(classes), "node")
    kept = freed(cut(ranked.where(F.col("k") <= F.col("c") - F.ceil(least * F.col("n") - 1e-9) + 1 + F.col("x")).select("g", "node", "n", (F.col("c") + F.col("x")).alias("c"))))
    other = kept.withColumnsRenamed({"node": "j", "n": "m", "c": "d"})
    near = (F.col("i") < F.col("j")) & (F.least("n", "m") >= least * F.greatest("n", "m")) & (F.least("c", "d") * (1 + least) >= least * (F.col("n") + F.col("m")))
    pairs = freed(cut(kept.withColumnRenamed("node", "i").join(other, "g").where(near).select("i", "j").distinct()))
    met = cut(pairs.select(F.explode(F.array("i", "j")).alias("node")).distinct())
    whole = shingled(texts(met))
    left = pairs.join(whole.select(F.col("mention_id").alias("i"), F.col("s").alias("a")), "i")
    both = left.join(whole.select(F.col("mention_id").alias("j"), F.col("s").alias("b")), "j")
    common = F.size(F.array_intersect("a", "b"))
    links = freed(cut(both.where(common >= least * (F.size("a") + F.size("b") - common)).select("i", "j")))
    parts = connected_components(links, "i", "j")
    return d.select("mention_id", "node").join(parts, "node", "left").select("mention_id", F.coalesce("component", "node").cast("string").alias("gold"))


def _largest_groups(m: DataFrame, gold: DataFrame, n: int) -> DataFrame:
    """The first mentions of the n largest groups of several, as queries; of the mentions only these are read whole."""
    sizes = gold.groupBy("gold").agg(F.count(F.lit(1)).alias("n"), F.min("mention_id").alias("mention_id")).where("n > 1")
    first = F.broadcast(cut(sizes.orderBy(F.desc("n"), "mention_id").limit(n).select("mention_id", "gold")))
    return cut(as_queries(m.drop("gold").join(first, "mention_id").select("mention_id", "doc_id", "startpos", "mention", "context", "gold")))


def w9_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text: entities of near copies, addresses, and passages looked up in documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    gold = cut(near_copy_gold(docs))
    m = fixtures.document_mentions(spark, sf_dir)
    q = _largest_groups(m, gold, 12)
    gold = cut(gold.join(cut(m.select("mention_id")), "mention_id", "left_semi"))
    er = session.EntityResolution(m, features.SHORT_NAMES, "document", settings=samplers.Settings(samples=600))
    answers = er.select_entity(q)
    prf = metrics.mean_f1q(metrics.query_prf(answers, gold, q, 1)).select(F.lit("near_copies").alias("what"), F.col("n_queries").alias("n"), F.col("mean_f1q").alias("value"))
    mails = cut(fixtures.email_mentions(spark, sf_dir).select("mention_id", "mention", "gold"))
    same = metrics.b_cubed(baselines.same_string(mails), mails.select("mention_id", "gold")).select(F.lit("addresses").alias("what"), F.lit(mails.count()).alias("n"), F.col("f1").alias("value"))
    hits = extract.passages(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("item_id").cast("double").alias("value")).select(F.lit("passages").alias("what"), "n", "value")
    return prf.unionByName(same).unionByName(hits)


def w10_refine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A template refined twice: without keywords, with a topic word, and with a second one dropped again."""
    m = fixtures.part_mentions(spark, sf_dir)
    first = names(m, 1).first()
    gold = first["gold"]
    er = session.EntityResolution(m, TWO, LEVEL, settings=samplers.Settings(samples=2000))
    node, out = QueryNode(gold, gold=gold), None
    topic = f"topic_{gold.replace(' ', '_')}"
    for step, (add, drop) in enumerate((((), ()), ((topic, "topic_1"), ()), ((), ("topic_1",)))):
        node, answers = er.refine(node, add, drop)
        q = node.frame(spark).withColumn("mention_id", F.col("query_id"))
        prf = metrics.query_prf(cut(answers), m.select("mention_id", "gold"), q, 1).select(F.lit(step).alias("step"), F.lit(", ".join(node.keywords)).alias("keywords"), "precision", "recall", "f1q")
        out = prf if out is None else out.unionByName(prf)
    return out


def w11_negative_control(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors whose cosine says nothing of their labels: accuracy stays near that of chance."""
    v = fixtures.embedding_mentions(spark, sf_dir)
    blocks = blocking.by_vector(v, 6).join(v.select("mention_id", "gold"), "mention_id")
    s = blocks.withColumn("entity_id", F.min("mention_id").over(Window.partitionBy("block"))).select(F.lit(0).alias("run_id"), "mention_id", "entity_id")
    order = blocking.ranked(v.select("mention_id", "gold"), "mention_id", name="a")
    other = blocking.ranked(v.select(F.col("gold").alias("other"), h32(F.col("mention_id").cast("string")).alias("h"), F.col("mention_id").alias("m")), "h", "m", name="a")
    shuffled = order.join(other, "a")
    chance = metrics.b_cubed(s, shuffled.select("mention_id", F.col("other").alias("gold")))
    real = metrics.b_cubed(s, v.select("mention_id", "gold"))
    cells = [F.round(c, 9).alias(c) for c in ("precision", "recall", "f1")]
    return real.select(F.lit("labels").alias("what"), *cells).unionByName(chance.select(F.lit("shuffled labels").alias("what"), *cells))


def w12_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Canopy counts grown by a stream of events beside those of one batch."""
    from erfocus.streaming import growth

    m = fixtures.event_mentions(spark, sf_dir)
    return growth.replay(spark, sf_dir).withColumnRenamed("n_mentions", "streamed").join(growth.counts(m, growth.watch(m)).withColumnRenamed("n_mentions", "batch"), "query_id", "full")


WORKLOADS = {
    f.__name__: f
    for f in (
        w1_real_time, w1_timings, w2_samplers, w2_uninformative, w2_annealed, w2_published, w2_learned, w3_selectivity, w3_score_decay, w4_schedules,
        w5_context, w5_documents, w6_parallel, w7_worked_example, w8_exhaustive, w9_text, w10_refine, w11_negative_control, w12_stream, trained_weights,
    )
}
