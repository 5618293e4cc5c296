"""Scores of configurations and of moves over the edges of canopies."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.functions.strings import qgrams
from erfocus.operators import context
from erfocus.operators.durable import cut, sized

#: Mentions with their contexts that pair_edges() broadcasts.
MAX_BROADCAST_MENTIONS = 20_000


def pair_edges(canopy: DataFrame, mentions: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, cosines: DataFrame | None = None, level: str = "document", key: str = "query_id") -> DataFrame:
    """(key, i, j, w) with i < j of each canopy's pairs: a theta join inside a canopy, never over the table.

    As many rows as half the squares of the canopies' sizes: for small ones, exact inference and checks; chains
    work rows of weights out as they need them (pairs.PairModel).  Canopies of up to MAX_BROADCAST_MENTIONS in
    all are compared map-side.  cosines: (i, j, cos) for the tiers; without them the strings' q-gram Jaccard is used.
    """
    own = features.prepare(mentions.select("mention_id", "mention", "context"), level, "s").select("mention_id", "s", qgrams(F.col("s.m")).alias("g"))
    rows = cut(canopy.select(key, "mention_id").join(own, "mention_id"))
    # One canopy is one key: its left mentions are dealt over tasks, so that its pairs are not all one task's.
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    a = rows.select(key, F.col("mention_id").alias("i"), F.col("s").alias("a"), F.col("g").alias("ga")).repartition(tasks, "i")
    b = sized(rows.select(F.col(key).alias("__k"), F.col("mention_id").alias("j"), F.col("s").alias("b"), F.col("g").alias("gb")), MAX_BROADCAST_MENTIONS)
    pairs = a.join(b, (a[key] == b["__k"]) & (a["i"] < b["j"]))
    if cosines is not None:
        pairs = pairs.join(cosines.withColumnRenamed("cos", "__s"), ["i", "j"], "left")
        s = F.col("__s")
    else:
        s = features.gram_similarity(F.col("ga"), F.col("gb"))
    return pairs.select(key, "i", "j", features.total(specs, F.col("a"), F.col("b"), s).alias("w"))


def classes(canopy: DataFrame, mentions: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, level: str = "document", key: str = "query_id") -> DataFrame:
    """(key, mention_id, rep): mentions that the features cannot tell apart, named by the smallest; without cosines.

    Of a context only words matter that are tokens or keywords of the canopy's mentions, and those that two mentions
    have in common; a word that all have makes all other common ones no matter.  So a canopy of many copies is few classes.
    """
    by = {s.name: bool(s.plus or s.minus) for s in specs}
    own = features.prepare(mentions.select("mention_id", "mention", "context"), level, "s").select("mention_id", "s")
    rows = cut(canopy.select(key, "mention_id").join(own, "mention_id"))
    full = cut(rows.groupBy(key, "s").agg(F.min("mention_id").alias("__r"), F.count(F.lit(1)).alias("n")))
    words = full.select(key, "__r", "n", F.explode("s.ctx").alias("w"))
    kept = full.select(key, F.explode("s.kw").alias("w"))
    if by.get("f10"):
        kept = kept.union(full.select(key, F.explode("s.toks").alias("w")))
    if by.get("f14"):
        seen = words.groupBy(key, "w").agg(F.sum("n").alias("n")).join(F.broadcast(full.groupBy(key).agg(F.sum("n").alias("all"))), key).where("n > 1")
        common = seen.groupBy(key).agg(F.min(F.when(F.col("n") == F.col("all"), F.col("w"))).alias("of_all"))
        kept = kept.union(seen.join(common, key).where("of_all IS NULL OR w = of_all").select(key, "w"))
    told = words.join(kept.distinct(), [key, "w"]).groupBy(key, "__r").agg(F.array_sort(F.collect_set("w")).alias("ctx"))
    few = full.join(told, [key, "__r"], "left").withColumn("ctx", F.coalesce("ctx", F.array().cast("array<string>")))
    rep = F.min("__r").over(Window.partitionBy(key, "s.m", "s.toks", "s.kw", "ctx")).alias("rep")
    return cut(rows.join(few.select(key, "s", rep), [key, "s"]).select(key, "mention_id", "rep"))


def class_edges(of: DataFrame, mentions: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, level: str = "document", key: str = "query_id") -> DataFrame:
    """(key, i, j, w), i <= j: weights between representatives of classes(); i = j: inside a class of several."""
    reps = cut(of.groupBy(key, F.col("rep").alias("mention_id")).agg(F.count(F.lit(1)).alias("n")))
    own = features.prepare(mentions.select("mention_id", "mention", "context"), level, "s").select("mention_id", "s", qgrams(F.col("s.m")).alias("g"))
    inside = reps.where("n > 1").join(own, "mention_id").select(key, F.col("mention_id").alias("i"), F.col("mention_id").alias("j"), features.total(specs, F.col("s"), F.col("s"), features.gram_similarity(F.col("g"), F.col("g"))).alias("w"))
    return pair_edges(reps.select(key, "mention_id"), mentions, specs, level=level, key=key).union(inside)


def _counted(state: DataFrame, of: DataFrame) -> DataFrame:
    """(run_id, entity_id, rep, k): how many members of each class an entity has; without classes each mention is its own."""
    rows = state.join(of.select("mention_id", "rep"), "mention_id") if of is not None else state.withColumn("rep", F.col("mention_id"))
    return cut(rows.groupBy("run_id", "entity_id", "rep").agg(F.count(F.lit(1)).alias("k")))


def _met(counts: DataFrame, edges: DataFrame) -> DataFrame:
    """(run_id, entity_id, i, j, ki, kj, w) of edges inside entities.

    Edges are joined with the entities of one end and then of the other; entities of a single member have none.
    """
    several = counts.join(counts.groupBy("run_id", "entity_id").agg(F.sum("k").alias("__n")).where("__n > 1"), ["run_id", "entity_id"], "left_semi")
    a = several.select("run_id", "entity_id", F.col("rep").alias("i"), F.col("k").alias("ki"))
    b = several.select("run_id", "entity_id", F.col("rep").alias("j"), F.col("k").alias("kj"))
    return edges.select("i", "j", "w").join(a, "i").join(b, ["run_id", "entity_id", "j"]).where("i <> j OR ki > 1")


def config_score(state: DataFrame, edges: DataFrame, of: DataFrame | None = None) -> DataFrame:
    """(run_id, score): the sum of edges inside entities; zero for a run without any.

    of: (mention_id, rep), where edges are those of classes.
    """
    pairs = F.when(F.col("i") == F.col("j"), F.expr("ki * (ki - 1) div 2")).otherwise(F.col("ki") * F.col("kj"))
    inside = _met(_counted(state, of), edges).groupBy("run_id").agg(F.sum(F.col("w") * pairs).alias("score"))
    return state.select("run_id").distinct().join(inside, "run_id", "left").select("run_id", F.coalesce("score", F.lit(0)).cast("long").alias("score"))


def entity_score(state: DataFrame, mentions: DataFrame, similar: DataFrame | None = None, specs: Iterable[features.FeatureSpec] = features.SPECS, of: DataFrame | None = None) -> DataFrame:
    """(run_id, score) of the entity-wide features: for each mention of an entity of several, whether another
    is similar to it (similar: (i, j) pairs, i < j; of classes, where of (mention_id, rep) names them) and whether another
    is of its document."""
    by = {s.name: s for s in specs}
    several = state.join(state.groupBy("run_id", "entity_id").agg(F.count(F.lit(1)).alias("n")), ["run_id", "entity_id"]).where("n > 1")
    docs = several.join(mentions.select("mention_id", "doc_id"), "mention_id")
    same = docs.groupBy("run_id", "entity_id", "doc_id").agg(F.count(F.lit(1)).alias("k"))
    out = same.select("run_id", F.when(F.col("k") > 1, F.col("k") * by["f16"].plus).otherwise(F.col("k") * by["f16"].minus).alias("s"))
    if similar is not None:
        counts = _counted(several.select("run_id", "mention_id", "entity_id"), of)
        near = _met(counts, similar.withColumn("w", F.lit(1)))
        has = near.select("run_id", "entity_id", F.col("i").alias("rep")).union(near.select("run_id", "entity_id", F.col("j").alias("rep"))).distinct().withColumn("has", F.lit(1))
        marked = counts.join(has, ["run_id", "entity_id", "rep"], "left")
        out = out.union(marked.select("run_id", F.col("k") * F.when(F.col("has") == 1, by["f15"].plus).otherwise(by["f15"].minus).alias("s")))
    total = out.groupBy("run_id").agg(F.sum("s").alias("score"))
    return state.select("run_id").distinct().join(total, "run_id", "left").select("run_id", F.coalesce("score", F.lit(0)).cast("long").alias("score"))


def matching_strings(state: DataFrame, mentions: DataFrame) -> DataFrame:
    """(run_id, entity_a, entity_b, n): pairs of equal normalised strings between two entities, counted by string."""
    from erfocus.functions.strings import normal

    rows = state.join(mentions.select("mention_id", normal(F.col("mention")).alias("s")), "mention_id").groupBy("run_id", "entity_id", "s").agg(F.count(F.lit(1)).alias("k"))
    a = rows.withColumnsRenamed({"entity_id": "entity_a", "k": "ka"})
    b = rows.withColumnsRenamed({"entity_id": "entity_b", "k": "kb"})
    return a.join(b, ["run_id", "s"]).where("entity_a < entity_b").groupBy("run_id", "entity_a", "entity_b").agg(F.sum(F.col("ka") * F.col("kb")).alias("n"))


def move_delta(state: DataFrame, edges: DataFrame, moves: DataFrame, of: DataFrame | None = None) -> DataFrame:
    """moves (run_id, mention_id, entity_to) with delta: edges to the target less edges to the rest of the source.

    Only edges of the moved mentions are read, once a class of them and entity.  A move to the mention's own entity has
    no delta.  of: (mention_id, rep), where edges are those of classes.
    """
    state = state.select("run_id", "mention_id", "entity_id")
    own = (state.join(of.select("mention_id", "rep"), "mention_id") if of is not None else state.withColumn("rep", F.col("mention_id"))).select("run_id", F.col("mention_id").alias("m"), F.col("rep").alias("c"), F.col("entity_id").alias("entity_from"))
    asked = cut(moves.select("run_id", F.col("mention_id").alias("m"), "entity_to").join(own, ["run_id", "m"]))
    ends = asked.select("run_id", "c", F.explode(F.array("entity_from", "entity_to")).alias("entity_id")).distinct()
    both = edges.select(F.col("i").alias("c"), F.col("j").alias("rep"), "w").union(edges.where("i <> j").select(F.col("j").alias("c"), F.col("i").alias("rep"), "w"))
    met = both.join(asked.select("c").distinct(), "c", "left_semi").join(_counted(state, of), "rep").join(ends, ["run_id", "c", "entity_id"], "left_semi")
    return deltas(asked, cut(met.groupBy("run_id", "c", "entity_id").agg(F.sum(F.col("k") * F.col("w")).alias("pull"))), edges.where("i = j").select(F.col("i").alias("c"), F.col("w").alias("__own")))


def deltas(asked: DataFrame, pulls: DataFrame, inside: DataFrame) -> DataFrame:
    """Moves (run_id, m, c, entity_from, entity_to) with delta, from (run_id, c, entity_id, pull) of classes c with entities.

    inside: (c, __own), the weight of two members of a class, which the source's pull has once too often.
    """
    to = pulls.select("run_id", "c", F.col("entity_id").alias("entity_to"), F.col("pull").alias("__to"))
    left = pulls.select("run_id", "c", F.col("entity_id").alias("entity_from"), F.col("pull").alias("__from"))
    out = asked.join(to, ["run_id", "c", "entity_to"], "left").join(left, ["run_id", "c", "entity_from"], "left").join(inside, "c", "left")
    zero = lambda c: F.coalesce(c, F.lit(0))
    delta = F.when(F.col("entity_from") == F.col("entity_to"), 0).otherwise(zero("__to") - zero("__from") + zero("__own"))
    return out.select("run_id", F.col("m").alias("mention_id"), "entity_from", "entity_to", delta.cast("long").alias("delta"))


def context_pulls(counts: DataFrame, vectors: DataFrame, spec: features.FeatureSpec) -> DataFrame:
    """(run_id, c, entity_id, pull): sums of the similarity tiers of each context with entities' contexts.

    counts: (run_id, entity_id, rep, k) of classes of equal contexts; vectors: (rep, term, w).  Contexts and counts go to
    each task once, packed; no pair of contexts is written.
    """
    import numpy as np
    import pandas as pd

    rows = counts.select("run_id", "entity_id", "rep", "k", F.lit(None).cast("string").alias("term"), F.lit(None).cast("double").alias("w")).union(
        vectors.select(F.lit(None).cast("int"), F.lit(None).cast("long"), "rep", F.lit(None).cast("long"), "term", "w")
    )

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        import pickle
        import zlib

        v, c = pdf[pdf["term"].notna()], pdf[pdf["term"].isna()]
        reps, at = np.unique(c["rep"].to_numpy(np.int64), return_inverse=True)
        ends = c[["run_id", "entity_id"]].astype(np.int64)
        entity, place = np.unique(ends.to_numpy(), axis=0, return_inverse=True)
        v = v[v["rep"].isin(reps)]
        term = np.unique(v["term"].to_numpy(dtype=object).astype(str), return_inverse=True)[1]
        whole = (reps, at, c["k"].to_numpy(np.float64), entity, place.reshape(-1), np.searchsorted(reps, v["rep"].to_numpy(np.int64)), term, v["w"].to_numpy(np.float64))
        return pd.DataFrame({"model": [zlib.compress(pickle.dumps(whole, protocol=5), 1)]})

    def run(batches):
        import pickle
        import zlib

        from erfocus.operators.pairs import PairModel

        for pdf in batches:
            for blob, part, parts in zip(pdf["model"], pdf["part"], pdf["parts"], strict=True):
                reps, at, k, entity, place, row, term, w = pickle.loads(zlib.decompress(blob))
                order = np.argsort(term, kind="stable")
                post, weight = row[order], w[order]
                begins = np.concatenate([[0], np.cumsum(np.bincount(term))]).astype(np.int64)
                own = np.argsort(row, kind="stable")
                ptr = np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(reps)))]).astype(np.int64)
                has, tiers = np.diff(ptr) > 0, PairModel.tier_weights(spec)
                for i in range(int(part), len(reps), int(parts)):
                    near = np.zeros(len(reps))
                    for x in own[ptr[i] : ptr[i + 1]].tolist():
                        a, b = begins[term[x]], begins[term[x] + 1]
                        near[post[a:b]] += w[x] * weight[a:b]
                    near[~has] = np.nan
                    t = tiers[PairModel.tier_of(near if has[i] else near * np.nan, spec)]
                    pull = np.bincount(place, weights=t[at] * k, minlength=len(entity))
                    met = np.flatnonzero(pull) if pull.any() else np.arange(1)  # a row at least, as it has the inside
                    out = pd.DataFrame({"run_id": entity[met, 0], "c": reps[i], "entity_id": entity[met, 1], "pull": pull[met].astype(np.int64), "inside": int(t[i])})
                    yield out

    parts = counts.sparkSession.sparkContext.defaultParallelism * 4
    packed = cut(rows.withColumn("__one", F.lit(0)).groupBy("__one").applyInPandas(lambda pdf: pack(pdf), "model binary"))
    dealt = packed.crossJoin(F.broadcast(counts.sparkSession.range(parts).select(F.col("id").cast("int").alias("part"), F.lit(parts).alias("parts")))).repartition(parts, "part")
    return dealt.mapInPandas(run, "run_id int, c long, entity_id long, pull long, inside long")


def sides(mentions: DataFrame, level: str = "document", vectors: DataFrame | None = None) -> DataFrame:
    """(mention_id, s, g, v): prepared mentions with their grams, and their context vector as a map if vectors (mention_id, term, w) are given."""
    rows = features.prepare(mentions.select("mention_id", "mention", "context"), level, "s").select("mention_id", "s", qgrams(F.col("s.m")).alias("g"))
    if vectors is None:
        return rows.withColumn("v", F.lit(None).cast("map<string,double>"))
    maps = vectors.groupBy("mention_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("term", "w")))).alias("v"))
    return rows.join(maps, "mention_id", "left")


def _cosine(a: Column, b: Column) -> Column:
    dot = F.aggregate(F.map_entries(a), F.lit(0.0), lambda acc, e: acc + e["value"] * F.coalesce(F.try_element_at(b, e["key"]), F.lit(0.0)))
    return F.when(a.isNotNull() & b.isNotNull(), dot)


def move_delta_on_demand(state: DataFrame, side: DataFrame, moves: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, cosines: bool = False, of: DataFrame | None = None) -> DataFrame:
    """What move_delta() gives, with the weights of only those pairs that the moves meet, worked out from sides().

    A pair for each member of the two entities of each move; nothing of the model is stored.  of: (mention_id, rep)
    where sides are of representatives of mentions that are alike.  Without cosines pairs are those of classes, met in
    rows of weights: see _delta_by_rows().
    """
    if not cosines:
        return _delta_by_rows(state, side, moves, tuple(specs), of)

    def seen(rows: DataFrame, c: str, k: str) -> DataFrame:
        """rows with the side of the mention in c."""
        if of is not None:
            rows = rows.join(of.select(F.col("mention_id").alias(c), F.col("rep").alias("__r")), c)
        key = c if of is None else "__r"
        return rows.join(side.select(F.col("mention_id").alias(key), F.col("s").alias(k), F.col("g").alias(f"g{k}"), F.col("v").alias(f"v{k}")), key)

    own = state.select("run_id", "mention_id", F.col("entity_id").alias("entity_from"))
    asked = moves.select("run_id", "mention_id", "entity_to").join(own, ["run_id", "mention_id"])
    asked = seen(asked, "mention_id", "a").drop("__r")
    ends = asked.withColumn("end", F.explode(F.array_distinct(F.array("entity_from", "entity_to"))))
    other = state.select("run_id", F.col("mention_id").alias("x"), F.col("entity_id").alias("end"))
    met = ends.join(other, ["run_id", "end"]).where("x <> mention_id")
    met = seen(met, "x", "b")
    similar = _cosine(F.col("va"), F.col("vb")) if cosines else features.gram_similarity(F.col("ga"), F.col("gb"))
    w = features.total(specs, F.col("a"), F.col("b"), similar)
    sums = met.where("entity_from <> entity_to").groupBy("run_id", "mention_id", "entity_to").agg(F.sum(F.when(F.col("end") == F.col("entity_to"), w).otherwise(-w)).alias("delta"))
    out = asked.select("run_id", "mention_id", "entity_from", "entity_to").join(sums, ["run_id", "mention_id", "entity_to"], "left")
    return out.select("run_id", "mention_id", "entity_from", "entity_to", F.coalesce("delta", F.lit(0)).cast("long").alias("delta"))


def _delta_by_rows(state: DataFrame, side: DataFrame, moves: DataFrame, specs: tuple, of: DataFrame | None) -> DataFrame:
    """Deltas by the strings' model: a class of movers is weighed once with all classes in the entities that moves meet.

    Only the sides of those classes and the entities' counts of them go to the tasks, packed, and a mover's row of weights is
    made where it is summed, so that no pair of mentions is a row.
    """
    import numpy as np

    own = state.select("run_id", "mention_id", F.col("entity_id").alias("entity_from"))
    asked = moves.select("run_id", "mention_id", "entity_to").join(own, ["run_id", "mention_id"])
    asked = asked.join(of.select("mention_id", "rep"), "mention_id") if of is not None else asked.withColumn("rep", F.col("mention_id"))
    asked = cut(asked.select("run_id", F.col("mention_id").alias("m"), F.col("rep").alias("c"), "entity_from", "entity_to"))
    ends = cut(asked.select("run_id", "c", F.explode(F.array("entity_from", "entity_to")).alias("entity_id")).distinct())
    inside = cut(state.select("run_id", "mention_id", "entity_id").join(sized(ends.select("run_id", "entity_id").distinct()), ["run_id", "entity_id"], "left_semi"))
    counts = _counted(sized(inside), of).select("run_id", "entity_id", "rep", "k")
    # A row of no members asks for the pull of its entity on its class.
    met = cut(counts.union(ends.select("run_id", "entity_id", "c", F.lit(0).cast("long"))))
    few = side.join(sized(cut(met.select(F.col("rep").alias("mention_id")).distinct())), "mention_id", "left_semi")
    few = few.select(F.lit(0).alias("__one"), "mention_id", F.col("mention_id").alias("doc_id"), "s.m", "s.toks", "s.ctx", "s.kw").withColumn("m", F.coalesce("m", F.lit("")))

    def pack(sides, rows):
        import pickle
        import zlib

        import pyarrow as pa

        from erfocus.operators.pairs import Sides

        if not sides.num_rows:
            return pa.table({"model": pa.array([], pa.binary())})
        whole = Sides.of_table(sides.sort_by("mention_id")), *(rows[c].to_numpy() for c in ("run_id", "entity_id", "rep", "k"))
        return pa.table({"model": pa.array([zlib.compress(pickle.dumps(whole, protocol=5), 1)], pa.binary())})

    def run(batches):
        import pickle
        import zlib

        import pandas as pd

        from erfocus.operators.pairs import PairModel

        for pdf in batches:
            for blob, part, parts in zip(pdf["model"], pdf["part"], pdf["parts"], strict=True):
                sides, run_id, entity, rep, k = pickle.loads(zlib.decompress(blob))
                known = np.isin(rep, sides.ids)
                run_id, entity, rep, k = run_id[known], entity[known], np.searchsorted(sides.ids, rep[known]), k[known]
                names, at = np.unique(np.stack([run_id.astype(np.int64), entity], axis=1), axis=0, return_inverse=True)
                at = at.reshape(-1)
                held = np.flatnonzero(k > 0)
                held = held[np.argsort(at[held], kind="stable")]
                begin = np.concatenate([[0], np.cumsum(np.bincount(at[held], minlength=len(names)))]).astype(np.int64)
                rep_of, k_of = rep[held], k[held]
                wanted = np.flatnonzero((k == 0) & (rep % int(parts) == int(part)))
                wanted = wanted[np.argsort(rep[wanted], kind="stable")]
                model, last, out = PairModel(specs, sides, cosines=False), -1, []
                for x in wanted.tolist():
                    c, e = int(rep[x]), at[x]
                    if c != last:
                        row, last = model.weigh(c).astype(np.int64), c
                        row[c] = model.own_weight(c)
                    a, b = begin[e], begin[e + 1]
                    out.append((int(names[e, 0]), int(sides.ids[c]), int(names[e, 1]), int((row[rep_of[a:b]] * k_of[a:b]).sum()), int(row[c])))
                if out:
                    yield pd.DataFrame(out, columns=["run_id", "c", "entity_id", "pull", "inside"])

    spark = state.sparkSession
    parts = spark.sparkContext.defaultParallelism
    packed = cut(few.groupBy("__one").cogroup(met.withColumn("__one", F.lit(0)).groupBy("__one")).applyInArrow(pack, "model binary"))
    dealt = packed.crossJoin(F.broadcast(spark.range(parts).select(F.col("id").cast("int").alias("part"), F.lit(parts).alias("parts")))).repartition(parts, "part")
    pulls = cut(dealt.mapInPandas(run, "run_id int, c long, entity_id long, pull long, inside long"))
    return deltas(asked, pulls.drop("inside"), pulls.select("c", F.col("inside").alias("__own")).distinct())


def move_delta_by_class(state: DataFrame, members: DataFrame, mentions: DataFrame, moves: DataFrame, specs: Iterable[features.FeatureSpec] = features.SPECS, level: str = "document") -> DataFrame:
    """What move_delta_on_demand() gives with cosines, for moves that meet most pairs of one canopy.

    Weights are sums of features, so that those of strings and common words are summed over classes() and the
    similarity of contexts over classes of equal contexts; no pair of mentions is met.
    """
    specs = tuple(specs)
    plain = move_delta(state, *_by_class(members, mentions, [s for s in specs if s.name != "f08"], level, moves))
    out = plain
    for spec in (s for s in specs if s.name == "f08"):
        words = mentions.select("mention_id", F.array_sort(F.array_distinct(F.coalesce(F.col(f"context.{level}"), F.array().cast("array<string>")))).alias("__x"))
        of = cut(words.select("mention_id", F.min("mention_id").over(Window.partitionBy("__x")).alias("rep")))
        vectors = context.tfidf(context.context_terms(mentions, level)).join(of.where("mention_id = rep").select("mention_id"), "mention_id", "left_semi").withColumnRenamed("mention_id", "rep")
        own = state.join(of, "mention_id").select("run_id", F.col("mention_id").alias("m"), F.col("rep").alias("c"), F.col("entity_id").alias("entity_from"))
        asked = cut(moves.select("run_id", F.col("mention_id").alias("m"), "entity_to").join(own, ["run_id", "m"]))
        pulls = cut(context_pulls(_counted(state, of), vectors, spec))
        inside = pulls.groupBy("c").agg(F.max("inside").alias("__own"))
        near = deltas(asked, pulls.drop("inside"), inside).select("run_id", "mention_id", "entity_to", F.col("delta").alias("__d"))
        out = out.join(near, ["run_id", "mention_id", "entity_to"]).select("run_id", "mention_id", "entity_from", "entity_to", (F.col("delta") + F.col("__d")).alias("delta"))
    return out


def _by_class(members: DataFrame, mentions: DataFrame, specs: list, level: str, moves: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(edges, moves, classes) as move_delta() takes them."""
    of = classes(members, mentions, specs, level)
    return cut(class_edges(of, mentions, specs, level).select("i", "j", "w")), moves, of
