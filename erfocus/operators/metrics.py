"""Accuracy of answers to queries, convergence and cost."""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from erfocus.operators.durable import cut, sized


def _f1(p: Column, r: Column) -> Column:
    return F.when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0)


def query_prf(answers: DataFrame, gold: DataFrame, queries: DataFrame, n_runs: int | None = None) -> DataFrame:
    """(run_id, query_id, tp, n_answer, n_gold, precision, recall, f1q).

    answers: (run_id, query_id, mention_id) without the queries' own; gold: (mention_id, gold) of all mentions
    that count, the whole table or the canopies; queries: (query_id, mention_id, gold).  A query without an
    answer has precision 0, one without relevant mentions recall 0.  With n_runs, runs 0 to n_runs - 1 count
    also where they answer nothing.
    """
    q = cut(queries.select("query_id", F.col("mention_id").alias("own"), F.col("gold").alias("qgold")))
    few = sized(q)
    relevant = gold.join(few, F.col("gold") == F.col("qgold")).where("mention_id <> own").groupBy("query_id").agg(F.count(F.lit(1)).alias("n_gold"))
    judged = answers.join(gold, "mention_id").join(few, "query_id").where("mention_id <> own")
    found = judged.groupBy("run_id", "query_id").agg(F.count_if(F.col("gold") == F.col("qgold")).alias("tp"), F.count(F.lit(1)).alias("n_answer"))
    runs = answers.select("run_id").distinct() if n_runs is None else answers.sparkSession.range(n_runs).select(F.col("id").cast("int").alias("run_id"))
    every = q.select("query_id").crossJoin(F.broadcast(runs))
    rows = every.join(found, ["run_id", "query_id"], "left").join(relevant, "query_id", "left")
    rows = rows.select("run_id", "query_id", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("tp", "n_answer", "n_gold")])
    p = F.when(F.col("n_answer") > 0, F.col("tp") / F.col("n_answer")).otherwise(0.0)
    r = F.when(F.col("n_gold") > 0, F.col("tp") / F.col("n_gold")).otherwise(0.0)
    rows = rows.withColumn("precision", p).withColumn("recall", r)
    return rows.withColumn("f1q", _f1(F.col("precision"), F.col("recall")))


def mean_f1q(prf: DataFrame) -> DataFrame:
    """(run_id, n_queries, mean_f1q)."""
    return prf.groupBy("run_id").agg(F.count(F.lit(1)).alias("n_queries"), F.avg("f1q").alias("mean_f1q"))


def average_runs(values: DataFrame, *keys: str, value: str = "f1q") -> DataFrame:
    """Means and deviations of a value over runs."""
    return values.groupBy(*keys).agg(F.avg(value).alias("mean"), F.coalesce(F.stddev(value), F.lit(0.0)).alias("sd"), F.count(F.lit(1)).alias("n_runs"))


def b_cubed(state: DataFrame, gold: DataFrame) -> DataFrame:
    """(run_id, precision, recall, f1) averaged over mentions, by counts of (entity, label), entity and label."""
    rows = state.join(gold.select("mention_id", "gold"), "mention_id")
    both = rows.groupBy("run_id", "entity_id", "gold").agg(F.count(F.lit(1)).alias("k"))
    e, g = Window.partitionBy("run_id", "entity_id"), Window.partitionBy("run_id", "gold")
    cells = both.withColumn("ne", F.sum("k").over(e)).withColumn("ng", F.sum("k").over(g))
    sums = cells.groupBy("run_id").agg((F.sum(F.col("k") * F.col("k") / F.col("ne")) / F.sum("k")).alias("precision"), (F.sum(F.col("k") * F.col("k") / F.col("ng")) / F.sum("k")).alias("recall"))
    return sums.withColumn("f1", _f1(F.col("precision"), F.col("recall")))


def curve(trace: DataFrame, start: DataFrame, gold: DataFrame, queries: DataFrame, components: DataFrame | None = None) -> DataFrame:
    """(component, run_id, query_id, step, tp, n_answer, f1q): accuracy after each proposal; step -1 is the start.

    The accepted moves are replayed on the start (component, mention_id, entity_id), outside the sampler, a
    run at a time.
    """
    q = queries.select("query_id", F.col("mention_id").alias("own"), F.col("gold").alias("qgold"))
    q = q.join(components, "query_id") if components is not None else q.withColumn("component", F.col("query_id"))
    members = start.select("component", "mention_id", "entity_id").join(gold.select("mention_id", "gold"), "mention_id")
    packed = members.groupBy("component").agg(F.collect_list(F.struct("mention_id", "entity_id", "gold")).alias("ms")).join(q.groupBy("component").agg(F.collect_list(F.struct("query_id", "own", "qgold")).alias("qs")), "component")
    moves = trace.where("accepted").groupBy("component", "run_id").agg(F.array_sort(F.collect_list(F.struct("step", "m", "e_to"))).alias("moves"))
    ends = trace.groupBy("component", "run_id").agg(F.max("step").alias("last"))
    rows = ends.join(moves, ["component", "run_id"], "left").join(packed, "component")

    def replay(batches):
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                yield _replay(r)

    return rows.mapInPandas(replay, "component long, run_id int, query_id long, step int, tp long, n_answer long, f1q double")


def _replay(r) -> pd.DataFrame:
    entity = {x["mention_id"]: x["entity_id"] for x in r.ms}
    gold = {x["mention_id"]: x["gold"] for x in r.ms}
    members: dict[int, set] = {}
    for m, e in entity.items():
        members.setdefault(e, set()).add(m)
    # Traces name entities by their smallest member at the time.
    where = {min(own): e for e, own in members.items()}
    relevant = {q["query_id"]: sum(g == q["qgold"] for g in gold.values()) - 1 for q in r.qs}
    out = []

    def note(step):
        for q in r.qs:
            own = members[entity[q["own"]]]
            tp = sum(gold[x] == q["qgold"] for x in own) - 1
            n, g = len(own) - 1, relevant[q["query_id"]]
            p, c = tp / n if n else 0.0, tp / g if g > 0 else 0.0
            out.append((r.component, r.run_id, q["query_id"], step, tp, n, 2 * p * c / (p + c) if p + c else 0.0))

    note(-1)
    fresh = max(entity.values(), default=0)
    for move in r.moves if r.moves is not None else ():
        m, e_from = move["m"], entity[move["m"]]
        old = members[e_from]
        del where[min(old)]
        old.discard(m)
        if old:
            where[min(old)] = e_from
        if move["e_to"] == -1:
            fresh += 1
            to = fresh
            members[to] = set()
        else:
            to = where.pop(move["e_to"])
        members[to].add(m)
        entity[m] = to
        where[min(members[to])] = to
        note(move["step"])
    if not out or out[-1][3] != r.last:
        note(r.last)
    return pd.DataFrame(out, columns=["component", "run_id", "query_id", "step", "tp", "n_answer", "f1q"]).drop_duplicates(["query_id", "step"], keep="last")


def at_step(curves: DataFrame, step: int) -> DataFrame:
    """(component, run_id, query_id, f1q): accuracy after the last change up to a step."""
    return curves.where(F.col("step") <= step).groupBy("component", "run_id", "query_id").agg(F.max_by("f1q", "step").alias("f1q"))


def upto(curves: DataFrame, last: int = 50) -> DataFrame:
    """The curve's values at each of the first steps."""
    steps = curves.select("component", "run_id", "query_id").distinct().withColumn("step", F.explode(F.sequence(F.lit(0), F.lit(last - 1))))
    w = Window.partitionBy("component", "run_id", "query_id").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    keys = ["component", "run_id", "query_id", "step"]
    known = curves.select(*keys, "f1q").where(F.col("step") < last)
    filled = steps.select(*keys).union(known.select(*keys)).distinct().join(known, keys, "left")
    return filled.withColumn("f1q", F.last("f1q", ignorenulls=True).over(w)).where("step >= 0")


def time_to(curves: DataFrame, target: float = 0.95) -> DataFrame:
    """(component, run_id, query_id, first_step): null where the target is not reached."""
    return curves.groupBy("component", "run_id", "query_id").agg(F.min(F.when(F.col("f1q") >= target, F.col("step") + 1)).alias("first_step"))


def score_trace(trace: DataFrame, start: int = 0) -> DataFrame:
    """(run_id, step, score): the model's score after each proposal, from the deltas."""
    w = Window.partitionBy("run_id").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    return trace.select("run_id", "step", (F.sum(F.when(F.col("accepted"), F.col("delta")).otherwise(0)).over(w) + start).alias("score"))


def proposals(trace: DataFrame) -> DataFrame:
    """(run_id, proposals, accepted, rate, first_accepted)."""
    return trace.groupBy("run_id").agg(F.count(F.lit(1)).alias("proposals"), F.count_if("accepted").alias("accepted"), F.avg(F.col("accepted").cast("int")).alias("rate"), F.min(F.when(F.col("accepted"), F.col("step"))).alias("first_accepted"))


def first_correct(trace: DataFrame, gold: DataFrame, queries: DataFrame) -> DataFrame:
    """(run_id, query_id, step): the first accepted proposal that moves a mention of the query's label into its entity's name."""
    q = queries.select("query_id", F.col("mention_id").alias("own"), F.col("gold").alias("qgold"))
    moved = trace.where("accepted").join(gold.select(F.col("mention_id").alias("m"), "gold"), "m").join(F.broadcast(q), "query_id").where("gold = qgold")
    return moved.groupBy("run_id", "query_id").agg(F.min("step").alias("step"))


def canopy_quality(canopy: DataFrame, gold: DataFrame, queries: DataFrame) -> DataFrame:
    """(query_id, n, quality): the share of each canopy that is of the query's label."""
    q = queries.select("query_id", F.col("gold").alias("qgold"))
    rows = canopy.select("query_id", "mention_id").join(gold.select("mention_id", "gold"), "mention_id").join(F.broadcast(q), "query_id")
    return rows.groupBy("query_id").agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("gold") == F.col("qgold")).cast("int")).alias("quality"))


def ratios(queries: DataFrame, mentions: DataFrame) -> DataFrame:
    """(n_queries, n_entities, n_mentions, queries_per_entity, mentions_per_entity)."""
    m = mentions.agg(F.count(F.lit(1)).alias("n_mentions"), F.count_distinct("gold").alias("n_entities"))
    q = queries.agg(F.count(F.lit(1)).alias("n_queries"))
    both = q.crossJoin(m)
    return both.select("n_queries", "n_entities", "n_mentions", (F.col("n_queries") / F.col("n_entities")).alias("queries_per_entity"), (F.col("n_mentions") / F.col("n_entities")).alias("mentions_per_entity"))


class Timings:
    """Seconds of a query's stages; total includes whatever is timed under other names."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def stage(self, name: str) -> Iterator[None]:
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began

    @property
    def total(self) -> float:
        return sum(self.seconds.values())
