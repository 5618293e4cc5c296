"""Bulk-synchronous rounds for models too large for one task.

A round: workers pick queries by a random schedule and draw a mention by its influence, to be moved to the query's
entity; every proposal claims its two entities with a hashed priority; those first on both of theirs win, so that
winners touch disjoint entities and their order is of no matter.  Losers back out and make a baseline proposal
each, over entities that no winner holds; those claim among themselves once more.  Nobody waits.  The winners' deltas
are worked out from the pairs they meet, and improvements applied.  With few queries nearly all proposals claim
the query's entity; merge_round() scores all candidates against the frozen entity at once and repairs afterwards.
Rounds make another chain than the sequential one.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from erfocus.functions.rand import SPAN, h32
from erfocus.operators.alias import draw
from erfocus.operators.durable import BROADCAST_ROWS, cut
from erfocus.operators.score import move_delta
from erfocus.operators.state import apply_moves, canonical


def _small(rows: int) -> Callable[[DataFrame], DataFrame]:
    """A broadcast hint for tables of at most so many rows, where that is few; else none."""
    return F.broadcast if rows <= BROADCAST_ROWS else lambda df: df


#: What scores moves: (state, moves) -> moves with delta.
Score = Callable[[DataFrame, DataFrame], DataFrame]


def by_edges(edges: DataFrame) -> Score:
    """Deltas from written-out weights (i, j, w)."""
    return lambda state, moves: move_delta(state, edges, moves)


def _h(seed: int, step: int, slot: str, *cols: Column | str) -> Column:
    parts = [F.col(c).cast("string") if isinstance(c, str) else c.cast("string") for c in cols]
    return h32(F.concat_ws("|", F.lit(f"{seed}|{step}|{slot}"), *parts))


def scheduled(queries: DataFrame, step: int, seed: int, workers: int) -> DataFrame:
    """(query_id, n): for each worker the query that it takes, uniformly at random."""
    ids = queries.select("query_id").distinct()
    places = ids.select("query_id", (F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("query_id")) - 1).alias("place"), F.count(F.lit(1)).over(Window.partitionBy(F.lit(0))).alias("many"))
    many = places.agg(F.max("many").alias("many"))
    picked = ids.sparkSession.range(1, workers + 1).withColumnRenamed("id", "n").crossJoin(F.broadcast(many)).where("many > 0")
    picked = picked.withColumn("place", F.shiftright(_h(seed, step, "q", "n") * F.col("many"), 32).cast("int"))
    return picked.join(places.select("query_id", "place"), "place").select("query_id", "n")


def propose(state: DataFrame, tables: DataFrame | None, queries: DataFrame, step: int, seed: int = 1, per_query: int = 1, workers: int | None = None, n_queries: int | None = None, drawn: DataFrame | None = None) -> DataFrame:
    """(run_id, query_id, n, mention_id, entity_from, entity_to): influence draws to the query's entity.

    tables: alias tables; queries: (query_id, mention_id), n_queries of them if that is known.  per_query draws for each
    query, or as many in all as there are workers, each with a query of its own choice.  Draws of mentions already there,
    or of queries' own, are left out.  Draws are made where a table lies; only mentions leave it.  drawn: (query_id, n,
    mention_id) of this step from draws_ahead(), instead of tables.
    """
    few = _small(queries.count() if n_queries is None else n_queries)
    if drawn is not None:
        return _proposed(state, drawn, queries, few)
    if workers is None:
        asked = queries.select("query_id", F.sequence(F.lit(1).cast("long"), F.lit(per_query).cast("long")).alias("ns")).distinct()
    else:
        asked = scheduled(queries, step, seed, workers).groupBy("query_id").agg(F.sort_array(F.collect_list("n")).alias("ns"))
    u = lambda slot, n: _h(seed, step, slot, "query_id", n) / SPAN
    drawn = tables.join(few(asked), "query_id").select("query_id", F.explode(F.transform("ns", lambda n: F.struct(n.alias("n"), draw(u("a", n), u("b", n)).alias("mention_id")))).alias("d")).select("query_id", "d.n", "d.mention_id")
    return _proposed(state, drawn, queries, few)


def _proposed(state: DataFrame, drawn: DataFrame, queries: DataFrame, few: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Proposals of the drawn mentions to their queries' entities."""
    own = queries.select("query_id", F.col("mention_id").alias("own"))
    to = state.withColumnRenamed("mention_id", "own").join(few(own), "own").select("run_id", "query_id", F.col("entity_id").alias("entity_to"))
    source = state.withColumnRenamed("entity_id", "entity_from")
    rows = drawn.join(source, "mention_id").join(to, ["run_id", "query_id"]).where("entity_from <> entity_to")
    return rows.join(few(own.select(F.col("own").alias("mention_id"))), "mention_id", "left_anti").select("run_id", "query_id", "n", "mention_id", "entity_from", "entity_to")


def draws_ahead(scores: DataFrame, of: DataFrame, queries: DataFrame, steps: int, workers: int, seed: int = 1) -> DataFrame:
    """(query_id, step, n, mention_id): what propose() draws in rounds of workers, from tables that never leave their tasks.

    scores: (query_id, rep, infl) of classes of like mentions; of: (mention_id, rep).  Draws depend on no state, so those of
    all rounds are made where a query's table is built, over each of its canopy's mentions.
    """
    u = lambda step, slot: (_h(seed, step, slot, "query_id", "n") / SPAN)
    asked = None
    for step in range(steps):
        rows = scheduled(queries, step, seed, workers).select("query_id", F.lit(step).alias("step"), "n", u(step, "a").alias("u1"), u(step, "b").alias("u2"))
        asked = rows if asked is None else asked.union(rows)
    ids = of.groupBy("rep").agg(F.collect_list("mention_id").alias("ids"))
    canopies = scores.select("query_id", "rep", "infl").join(ids, "rep").select("query_id", "infl", "ids")

    def run(canopy, wanted):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        from erfocus.operators.alias import vose
        from erfocus.operators.influence import DECAY_P

        lists = canopy["ids"].combine_chunks()
        ids = np.asarray(pc.list_flatten(lists))
        infl = np.repeat(canopy["infl"].to_numpy(), np.asarray(pc.list_value_length(lists)))
        order = np.argsort(ids)
        ids, infl = ids[order], infl[order]
        n, pos = len(ids), np.empty(len(ids))
        pos[np.argsort(-infl, kind="stable")] = np.arange(n)
        p = min(DECAY_P, 5.0 / max(n, 1))
        prob, alias = vose(p * (1 - p) ** pos)
        i = np.minimum(np.floor(wanted["u1"].to_numpy() * n).astype(np.int64), n - 1)
        got = ids[np.where(wanted["u2"].to_numpy() < prob[i], i, alias[i])] if n else np.zeros(0, dtype=np.int64)
        return wanted.select(["query_id", "step", "n"]).slice(0, len(got)).append_column("mention_id", pa.array(got))

    return canopies.groupBy("query_id").cogroup(asked.groupBy("query_id")).applyInArrow(run, "query_id long, step int, n long, mention_id long")


def baseline_proposals(state: DataFrame, losers: DataFrame, step: int, seed: int = 1) -> DataFrame:
    """(run_id, query_id, n, mention_id, entity_from, entity_to): a uniform proposal for each proposal that backed out.

    Uniform sources without replacement are the entities of least hash, as many as there are losers, one of their
    mentions by another; targets likewise by a third.  So some times as many rows as there are losers are ranked, never
    all entities.
    """
    entities = cut(state.groupBy("run_id", "entity_id").agg(F.min_by("mention_id", _h(seed, step, "bm", "mention_id")).alias("mention_id")))
    place = lambda *order: F.row_number().over(Window.partitionBy("run_id").orderBy(*order))
    asked = losers.select("run_id", "query_id", "n", place("query_id", "n").alias("k"))
    many = losers.groupBy("run_id").agg(F.count(F.lit(1)).alias("many"))

    def least(slot: str) -> DataFrame:
        ranked = entities.select("run_id", "entity_id", "mention_id", _h(seed, step, slot, "entity_id").alias("h"))
        # The losers' number of least hashes lies in a share of the hashes' range that is known from the counts; three
        # times that share, and never less than some hundreds, holds them but for a chance that needs no thought.
        bound = F.least(F.lit(SPAN), F.lit(SPAN) * (3 * F.col("many") + 300) / F.col("all"))
        near = ranked.join(many.join(entities.groupBy("run_id").agg(F.count(F.lit(1)).alias("all")), "run_id"), "run_id").where(F.col("h") <= bound)
        return near.withColumn("k", place("h", "entity_id")).where("k <= many")

    sources = least("bs").select("run_id", "k", "mention_id", F.col("entity_id").alias("entity_from"))
    targets = least("bt").select("run_id", "k", F.col("entity_id").alias("entity_to"))
    both = asked.join(sources, ["run_id", "k"]).join(targets, ["run_id", "k"]).where("entity_from <> entity_to")
    return both.select("run_id", "query_id", "n", "mention_id", "entity_from", "entity_to")


def winners(proposals: DataFrame, step: int, seed: int = 1) -> DataFrame:
    """The proposals that are first, by hashed priority, on both entities they claim; ties go to smaller ids.

    Claims are least-of-group aggregations with a map-side part, so a claimed hub is no hot task.
    """
    p = proposals.withColumn("__p", F.struct(_h(seed, step, "p", "query_id", "n").alias("h"), F.col("query_id").alias("q"), F.col("n").alias("n")))
    claims = p.select("run_id", F.col("entity_from").alias("e"), "__p").union(p.select("run_id", F.col("entity_to").alias("e"), "__p"))
    first = claims.groupBy("run_id", "e").agg(F.min("__p").alias("__first"))
    a = first.withColumnsRenamed({"e": "entity_from", "__first": "__fa"})
    b = first.withColumnsRenamed({"e": "entity_to", "__first": "__fb"})
    return p.join(a, ["run_id", "entity_from"]).join(b, ["run_id", "entity_to"]).where("__p = __fa AND __p = __fb").select(*proposals.columns)


def bsp_round(state: DataFrame, score: Score, proposals: DataFrame, step: int, seed: int = 1, queries: DataFrame | None = None, workers: int | None = None) -> DataFrame:
    """The state after the winners' improvements; entities named by their smallest mention again.

    With queries, losers fall back to baseline proposals over entities that no winner claims; queries' own mentions
    stay where they are.  proposals should lie written down; workers: the most that they can be, if it is known.
    """
    won = cut(winners(proposals, step, seed))
    if queries is not None:
        few = _small(2 * workers if workers is not None else 2 * proposals.count())
        losers = proposals.join(won.select("run_id", "query_id", "n"), ["run_id", "query_id", "n"], "left_anti")
        claimed = won.select("run_id", F.explode(F.array("entity_from", "entity_to")).alias("entity_id")).distinct()
        free = state.join(few(claimed), ["run_id", "entity_id"], "left_anti")
        back = baseline_proposals(free, losers, step, seed).join(queries.select("mention_id").distinct(), "mention_id", "left_anti").select(*won.columns)
        won = won.union(winners(cut(back), step, seed))
    moves = won.select("run_id", "mention_id", "entity_to")
    good = score(state, moves).where("delta > 0").select("run_id", "mention_id", "entity_to")
    return canonical(apply_moves(state, good))


def uniform_round(state: DataFrame, score: Score, workers: int, step: int, seed: int = 1) -> DataFrame:
    """A round of the baseline: as many uniform proposals as there are workers."""
    state = cut(state)
    asked = state.select("run_id").distinct().crossJoin(F.broadcast(state.sparkSession.range(1, workers + 1))).select("run_id", F.lit(0).cast("long").alias("query_id"), F.col("id").alias("n"))
    return cut(bsp_round(state, score, cut(baseline_proposals(state, asked, step, seed)), step, seed))


def bsp(state: DataFrame, score: Score | DataFrame, tables: DataFrame, queries: DataFrame, rounds: int, seed: int = 1, per_query: int = 1, workers: int | None = None, fallback: bool = True, first: int = 0) -> DataFrame:
    """Rounds of propose, claim, fall back, accept, apply; lineage is cut after each, as a round reads its state several times.

    score: by_edges(), or any function that scores moves; edges (i, j, w) are taken too.  Rounds are numbered from
    first on, so that a run may be carried on.
    """
    score = by_edges(score) if isinstance(score, DataFrame) else score
    state, queries = cut(state), cut(queries.select("query_id", "mention_id"))
    n = queries.count()
    for step in range(first, first + rounds):
        proposals = cut(propose(state, tables, queries, step, seed, per_query, workers, n))
        state = cut(bsp_round(state, score, proposals, step, seed, queries if fallback else None, workers or n * per_query))
    return state


def merge_round(state: DataFrame, score: Score | DataFrame, tables: DataFrame | None, queries: DataFrame, step: int, seed: int = 1, per_query: int = 64, workers: int | None = None, drawn: DataFrame | None = None) -> DataFrame:
    """Many mentions to the same query's entity at once.

    Candidates are scored against the frozen entity and all improvements merged (of a mention that several
    queries draw, the best); a repair then sets those apart whose edges to the merged entity sum to less than nothing.
    """
    score = by_edges(score) if isinstance(score, DataFrame) else score
    state = cut(state)
    asked = propose(state, tables, queries, step, seed, per_query, workers, drawn=drawn).select("run_id", "mention_id", "entity_to").distinct()
    scored = score(state, cut(asked)).where("delta > 0")
    best = cut(cut(scored).withColumn("__k", F.row_number().over(Window.partitionBy("run_id", "mention_id").orderBy(F.desc("delta"), "entity_to"))).where("__k = 1"))
    moved = cut(apply_moves(state, best.select("run_id", "mention_id", "entity_to")))
    apart = best.select("run_id", "mention_id").withColumn("entity_to", -F.col("mention_id") - 1)
    alone = score(moved, apart).where("delta > 0")
    return canonical(apply_moves(moved, alone.select("run_id", "mention_id", F.col("entity_to"))))


def draws_seconds(*given, **more) -> tuple[DataFrame, float]:
    """draws_ahead() written down, and the seconds that the tables and their draws took."""
    import time

    began = time.perf_counter()
    drawn = cut(draws_ahead(*given, **more))
    return drawn, time.perf_counter() - began


def parallel_alias_seconds(weights: DataFrame) -> tuple[DataFrame, float]:
    """The alias tables of all queries, and the seconds their building took."""
    import time

    from erfocus.operators.alias import build

    began = time.perf_counter()
    tables = cut(build(weights))
    return tables, time.perf_counter() - began
