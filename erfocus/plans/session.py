"""Queries over entities: selection, join with a watchlist, the exhaustive view, the predicate in SQL."""

from __future__ import annotations

import re
from collections.abc import Iterable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erfocus.functions import features
from erfocus.operators import blocking, metrics, samplers
from erfocus.operators.durable import cut
from erfocus.sources.schema import MENTION, MentionSchema, QueryNode, query_frame


class EntityResolution:
    """Query-focused resolution over one mention table.

    Blocking reads keys and strings only; contexts are joined for canopy members alone.
    """

    def __init__(
        self,
        mentions: DataFrame,
        specs: Iterable[features.FeatureSpec] = features.SPECS,
        level: str = "document",
        min_shared: int = 3,
        index: str | None = None,
        cosines: bool = True,
        settings: samplers.Settings = samplers.Settings(),
        max_canopy: int | None = None,
    ):
        self.mentions = MentionSchema.validate(mentions)
        self.spark: SparkSession = mentions.sparkSession
        self.specs, self.level, self.min_shared, self.index = tuple(specs), level, min_shared, index
        self.settings = replace(settings, cosines=cosines and level != "none")
        self.max_canopy = max_canopy
        self.timings = metrics.Timings()

    # query nodes

    def nodes(self, queries) -> tuple[DataFrame, DataFrame]:
        """(mention table with declared templates appended, queries with their mention ids)."""
        if isinstance(queries, str):
            queries = [QueryNode(queries)]
        if isinstance(queries, QueryNode):
            queries = [queries]
        if isinstance(queries, list):
            named = [replace(q, query_id=-i - 1) if q.query_id >= 0 else q for i, q in enumerate(queries)]
            frame = query_frame(self.spark, named)
        else:
            frame = queries
        frame = frame.withColumn("mention_id", F.col("query_id")) if "mention_id" not in frame.columns else frame
        columns = [f.name for f in MENTION if f.name in self.mentions.columns]
        declared = frame.where("mention_id < 0")
        for c in columns:
            if c not in declared.columns:
                declared = declared.withColumn(c, F.lit(None).cast(self.mentions.schema[c].dataType))
        table = self.mentions.select(columns).unionByName(declared.select(columns))
        return table, frame

    # plans

    def canopy(self, queries: DataFrame) -> DataFrame:
        """(query_id, mention_id) with each query's own mention in its canopy."""
        found = blocking.canopy(self.mentions, queries, self.index, min_shared=self.min_shared)
        own = queries.select("query_id", "mention_id")
        if self.max_canopy:
            found = blocking.top_canopy(found.join(own, ["query_id", "mention_id"], "left_anti"), self.max_canopy - 1)
        return found.select("query_id", "mention_id").union(own).distinct()

    def packed(self, queries, merged: bool = False, start: DataFrame | None = None) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame | None]:
        """(packed canopies, mention table, queries, components or null): everything before the chains.

        start: (mention_id, entity_id) of an earlier result, for chains that set out from it (init='previous').
        """
        with self.timings.stage("blocking"):
            table, frame = self.nodes(queries)
            frame = cut(frame)
            found = cut(self.canopy(frame))
            components = cut(blocking.merge(found)) if merged else None
        with self.timings.stage("context"):
            out = cut(samplers.pack(found, table, frame, components, self.level, start=start))
        return out, table, frame, components

    # queries

    def select_entity(self, query, runs: int = 1, direction: str | None = None, start: DataFrame | None = None, **changes) -> DataFrame:
        """(run_id, query_id, mention_id): mentions that are of the query's entity.

        direction: 'attract' gathers single mentions, 'repel' sheds from one entity of all, 'auto' takes the latter
        for canopies whose mentions are mostly of positive influence.  start: an earlier result to set out from.
        """
        changes |= self._directed(direction)
        packed, _, frame, components = self.packed(query, start=start)
        return self._answers(packed, frame, components, runs, **({"init": "previous"} if start is not None else {}), **changes)

    def join_entities(self, watchlist: DataFrame, policy: str = "by_selectivity", runs: int = 1, direction: str | None = None, start: DataFrame | None = None, **changes) -> DataFrame:
        """(run_id, query_id, mention_id): mentions joined with the watchlist's nodes, scheduled over merged canopies."""
        changes |= self._directed(direction)
        packed, _, frame, components = self.packed(watchlist, merged=True, start=start)
        return self._answers(packed, frame, components, runs, policy=policy, **({"init": "previous"} if start is not None else {}), **changes)

    DIRECTIONS = {"attract": "influence_to_query", "repel": "expel", "auto": "auto"}

    def _directed(self, direction: str | None) -> dict:
        if direction is None:
            return {}
        if direction not in self.DIRECTIONS:
            raise ValueError(f"direction {direction} is none of {tuple(self.DIRECTIONS)}")
        return {"sampler": self.DIRECTIONS[direction]}

    def _answers(self, packed: DataFrame, frame: DataFrame, components: DataFrame | None, runs: int, **changes) -> DataFrame:
        return samplers.answers(self.states(packed, runs, **changes), frame, components)

    def states(self, packed: DataFrame, runs: int = 1, **changes) -> DataFrame:
        """(component, run_id, mention_id, entity_id) after the chains: also what a later call may start from."""
        with self.timings.stage("inference"):
            return samplers.states(cut(samplers.chains(packed, replace(self.settings, **changes), runs, self.specs)))

    def refine(self, query: QueryNode, add: Iterable[str] = (), drop: Iterable[str] = (), runs: int = 1, **changes) -> tuple[QueryNode, DataFrame]:
        """The query with changed keywords, and its answers: a step of an interactive search."""
        words = [k for k in dict.fromkeys([*query.keywords, *add]) if k not in set(drop)]
        changed = replace(query, keywords=tuple(words))
        return changed, self.select_entity(changed, runs, **changes)

    def resolve_all(self, block: str = "mention", runs: int = 1, samples: int | None = None, packed: DataFrame | None = None, **changes) -> DataFrame:
        """(run_id, mention_id, entity_id) of the whole table: the exhaustive baseline, block by block.

        Blocks are components of mentions with common normalised strings, or of an expression's equal values.  With
        `idle` each block's chain runs until so many proposals in a row have changed nothing, or its samples are spent.
        packed: the same blocks' packed_blocks(), where several calls share them.
        """
        key = self._block(block)
        packed = packed if packed is not None else self.packed_blocks(block)
        settings = replace(self.settings, sampler="uniform", **({"samples": samples} if samples else {}), **changes)
        done = samplers.resolved(packed, settings, runs, self.specs).select("run_id", "mention_id", "entity_id")
        keyed = self.mentions.select("mention_id", key.alias("b"))
        single = keyed.where("b IS NOT NULL").groupBy("b").agg(F.min("mention_id").alias("mention_id"), F.count(F.lit(1)).alias("n")).where("n = 1").select("mention_id")
        alone = single.union(keyed.where("b IS NULL").select("mention_id"))
        return done.unionByName(alone.select(F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run_id"), "mention_id", F.col("mention_id").alias("entity_id")))

    def _block(self, block: str):
        from erfocus.functions.strings import normal

        return normal(F.col("mention")) if block == "mention" else F.expr(block)

    def packed_blocks(self, block: str = "mention") -> DataFrame:
        """Packed blocks of several mentions, written down: for several calls of resolve_all()."""
        return cut(samplers.pack_blocks(self.mentions, self._block(block), self.level))

    def view(self, name: str, state: DataFrame) -> DataFrame:
        """The mention table with its entities as a view of this name."""
        rows = self.mentions.join(state.select("mention_id", "entity_id"), "mention_id")
        rows.createOrReplaceTempView(name)
        return rows

    def same_entity(self, pairs: DataFrame, state: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
        """pairs with same_entity: a look-up in a resolved state, as one pair's answer depends on all others'."""
        e = state.select("mention_id", "entity_id")
        left = e.withColumnsRenamed({"mention_id": a, "entity_id": "__ea"})
        right = e.withColumnsRenamed({"mention_id": b, "entity_id": "__eb"})
        joined = pairs.join(left, a, "left").join(right, b, "left")
        return joined.withColumn("same_entity", F.coalesce(F.col("__ea") == F.col("__eb"), F.col(a) == F.col(b))).drop("__ea", "__eb")

    # SQL

    CALL = re.compile(r"same_entity\s*\(\s*(\w+)\s*,\s*('(?:[^']|'')*'|:\w+|-?\d+)\s*\)", re.IGNORECASE)

    def sql(self, text: str, **named) -> DataFrame:
        """SELECT ... FROM mentions WHERE same_entity(mentions, 'text' | id | :name) [AND ...].

        The predicate needs the whole table, so it is no function of a row: it is taken out of the top-level
        conjunction, answered by a canopy and a chain, and put back as a semi-join.  Anywhere else it is refused.
        """
        calls = list(self.CALL.finditer(text))
        if not calls:
            self.mentions.createOrReplaceTempView("mentions")
            return self.spark.sql(text)
        if len(calls) > 1:
            raise ValueError("one same_entity() is allowed in a query; join_entities() takes many")
        call = calls[0]
        before, after = text[: call.start()], text[call.end() :]
        where = re.split(r"\bwhere\b", before, flags=re.IGNORECASE)
        if len(where) != 2 or re.search(r"\b(or|not)\b|\(", where[1] + after.split("GROUP BY")[0], re.IGNORECASE):
            raise ValueError("same_entity() must be a conjunct of the top-level WHERE")
        answers = self.select_entity(self._node(call[2], named)).select("mention_id").distinct()
        view = self.mentions.join(answers, "mention_id", "left_semi")
        view.createOrReplaceTempView("erfocus_answer")
        body = re.sub(r"\bmentions\b(?=\s*(where|$|\s+\w+\s+where))", "erfocus_answer", before + "true" + after, count=1, flags=re.IGNORECASE)
        return self.spark.sql(body)

    def _node(self, value: str, named: dict):
        if value.startswith(":"):
            return named[value[1:]]
        if value.startswith("'"):
            return QueryNode(value[1:-1].replace("''", "'"))
        return self.mentions.where(F.col("mention_id") == int(value)).withColumn("query_id", F.col("mention_id"))


def coref_pairs(state: DataFrame) -> DataFrame:
    """(run_id, a, b): pairs of an entity, a < b.  As many as the squares of entities' sizes: for small tables."""
    a, b = state.withColumnRenamed("mention_id", "a"), state.withColumnRenamed("mention_id", "b")
    return a.join(b, ["run_id", "entity_id"]).where("a < b").select("run_id", "a", "b")


def clusters(state: DataFrame) -> DataFrame:
    """(run_id, entity_id, mentions, n)."""
    return state.groupBy("run_id", "entity_id").agg(F.array_sort(F.collect_set("mention_id")).alias("mentions"), F.count(F.lit(1)).alias("n"))


def choose_direction(found: DataFrame, infl: DataFrame) -> DataFrame:
    """(query_id, share, direction): canopies mostly of positive influence shed, the others gather."""
    rows = found.select("query_id", "mention_id").join(infl, ["query_id", "mention_id"])
    share = F.avg((F.col("infl") > 0).cast("int"))
    return rows.groupBy("query_id").agg(share.alias("share")).withColumn("direction", F.when(F.col("share") > 0.5, "expel").otherwise("influence_to_query"))
