"""Feature weights from labels: ranking updates inside a chain, with a confidence for each weight."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.functions.rand import py_h32
from erfocus.operators.durable import held
from erfocus.operators.kernel import Chain
from erfocus.operators.pairs import PairModel, Rows
from erfocus.operators.samplers import unpacked

#: The step of a confidence-weighted update, and the weight that the largest learned one gets.
REGULAR = 1.0
SCALE = 120
LEARNED = "component long, run_id int, weight array<double>, variance array<double>, updates long"


def pair_features(canopy: DataFrame, mentions: DataFrame, queries: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, similarity: DataFrame | None = None, level: str = "document") -> DataFrame:
    """(query_id, mention_id, a column per feature): the weight each feature gives the pair."""
    m = features.prepare(mentions.select("mention_id", "mention", "context"), level, "a").select("mention_id", "a")
    q = features.prepare(queries.select("query_id", "mention", "context"), level, "b").select("query_id", "b")
    rows = canopy.select("query_id", "mention_id").join(m, "mention_id").join(held(q), "query_id")
    if similarity is not None:
        rows = rows.join(similarity.withColumnRenamed("cos", "__s"), ["query_id", "mention_id"], "left")
        s = F.col("__s")
    else:
        s = features.text_similarity(F.col("a"), F.col("b"))
    return rows.select("query_id", "mention_id", *[features.value(f, F.col("a"), F.col("b"), s).cast("long").alias(f.name) for f in specs])


def width(specs: Iterable[features.FeatureSpec]) -> int:
    """How many indicators the pairwise features have."""
    return sum(len(s.tiers) + 1 if s.name == "f08" else 2 for s in specs if s.klass != "entity")


class Ranking:
    """Diagonal confidence-weighted ranking of neighbouring configurations.

    x is the difference of the indicators of a move; the better configuration by the labels is to score higher by a
    margin of one.  A wrong pair moves the weights the more, the less sure they are, and makes them surer.
    """

    def __init__(self, n: int, regular: float = REGULAR):
        self.w, self.variance, self.regular, self.updates = np.zeros(n), np.ones(n), regular, 0

    def learn(self, x: np.ndarray, better: int) -> None:
        margin = better * float(self.w @ x)
        if margin >= 1:
            return
        spread = float(self.variance @ (x * x))
        if spread <= 0:
            return
        beta = 1 / (spread + self.regular)
        self.w += (1 - margin) * beta * better * self.variance * x
        self.variance -= beta * (self.variance * x) ** 2
        np.maximum(self.variance, 1e-9, out=self.variance)
        self.updates += 1


class _Indicated(Rows):
    """Rows of indicators of a model, kept as bits."""

    def __init__(self, model: PairModel):
        super().__init__(model.n)
        self.model, self.most = model, max(1, (256 << 20) // max(model.n * width(model.specs), 1))

    def weigh(self, i: int) -> np.ndarray:
        out = self.model.indicators(i)
        out[:, i] = False
        return out


def rank_chain(model: PairModel, gold: np.ndarray, steps: int, seed: int, run: int, ranking: Ranking) -> Ranking:
    """Weights learned along a uniform chain over labelled mentions: each proposal that the labels judge is one lesson.

    A move is better if it joins more mentions of the same label and parts fewer, worse in the other case, and says
    nothing if both are alike.  The chain takes what the weights prefer, so that it learns where it goes.
    """
    rows, size = _Indicated(model), len(gold)
    chain = Chain(model.sides.ids, model, [], "uniform", seed=seed, run=run, allow_new_target=True)
    same = lambda m, members: sum(1 if gold[m] == gold[x] else -1 for x in members if x != m)
    for _ in range(steps if size > 1 else 0):
        source = chain.pick_entity(1)
        m, target = chain.pick(chain.members[source], 2), chain.pick_entity(3, new=True)
        chain.step += 1
        if target == source or (target == -1 and len(chain.members[source]) == 1):
            continue
        into, out_of = chain.members.get(target, []), [x for x in chain.members[source] if x != m]
        truth = same(m, into) - same(m, out_of)
        flags = rows.row(m)
        x = flags[:, into].sum(axis=1).astype(float) - flags[:, out_of].sum(axis=1)
        if truth:
            # The difference is of as many pairs as there are members: a lesson is of one pair's size.
            ranking.learn(x / max(len(into) + len(out_of), 1), 1 if truth > 0 else -1)
        if float(ranking.w @ x) > 0:
            chain.move(m, source, target)
    return ranking


def sample_rank(packed: DataFrame, gold: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, steps: int = 4000, runs: int = 1, seed: int = 1, cosines: bool = True, max_labelled: int = 2000) -> DataFrame:
    """(component, run_id, weight, variance, updates): what each component's labelled mentions teach.

    gold: (mention_id, gold); mentions without a label are left out.  A component takes at most max_labelled labelled
    mentions, those of least hash: the bound of the sample that weights are fitted on.
    """
    specs = tuple(s for s in specs if s.klass != "entity")
    labels = packed.select("component", "model").join(_labels(packed, gold), "component").withColumn("run_id", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))))

    def go(batches):
        for pdf in batches:
            for r in pdf.itertuples(index=False):
                sides = unpacked(r.model).sides
                known = {x["mention_id"]: x["gold"] for x in r.labels}
                keep = sorted((i for i, m in enumerate(sides.ids.tolist()) if m in known), key=lambda i: py_h32(f"train|{seed}|{sides.ids[i]}"))[:max_labelled]
                part = sides.some(np.array(sorted(keep), dtype=np.int64))
                model = PairModel(specs, part, cosines)
                found = rank_chain(model, np.array([known[m] for m in part.ids.tolist()], dtype=object), steps, seed, int(r.run_id), Ranking(width(specs)))
                yield pd.DataFrame({"component": [r.component], "run_id": [r.run_id], "weight": [found.w.tolist()], "variance": [found.variance.tolist()], "updates": [found.updates]})

    return labels.mapInPandas(go, LEARNED)


def _labels(packed: DataFrame, gold: DataFrame) -> DataFrame:
    ids = packed.select("component", "model").mapInPandas(_ids, "component long, mention_id long")
    return ids.join(gold.where("gold IS NOT NULL").select("mention_id", "gold"), "mention_id").groupBy("component").agg(F.collect_list(F.struct("mention_id", "gold")).alias("labels"))


def _ids(batches):
    for pdf in batches:
        for component, blob in zip(pdf["component"], pdf["model"], strict=True):
            yield pd.DataFrame({"component": component, "mention_id": unpacked(blob).sides.ids})


def mixed(learned: DataFrame) -> DataFrame:
    """(place, weight, precision): the components' weights, each counted by how sure it is."""
    cells = learned.select(F.posexplode(F.arrays_zip("weight", "variance")).alias("place", "x")).select("place", F.col("x.weight").alias("w"), (1 / F.col("x.variance")).alias("p"))
    return cells.groupBy("place").agg((F.sum(F.col("w") * F.col("p")) / F.sum("p")).alias("weight"), F.sum("p").alias("precision"))


def fitted(learned: DataFrame, specs: Iterable[features.FeatureSpec] = features.PAIRWISE, scale: int = SCALE) -> tuple[features.FeatureSpec, ...]:
    """specs with the learned weights as integers; what comes to the driver is a number per indicator."""
    from dataclasses import replace

    specs = tuple(specs)
    w = np.zeros(width(specs))
    for r in mixed(learned).toLocalIterator():
        w[r["place"]] = r["weight"]
    w = np.round(w * scale / max(np.abs(w).max(initial=0.0), 1e-12)).astype(int).tolist()
    out = []
    for s in specs:
        if s.klass == "entity":
            out.append(s)
            continue
        own = [w.pop(0) for _ in range(len(s.tiers) + 1 if s.name == "f08" else 2)]
        if s.name == "f08":
            out.append(replace(s, lowest=own[0], tiers=tuple((least, x) for (least, _), x in zip(s.tiers, reversed(own[1:]), strict=True))))
        else:
            holds, fails = own
            out.append(replace(s, plus=fails, minus=holds) if s.name == "f13" else replace(s, plus=holds, minus=fails))
    return tuple(out)
