"""Moves into large entities are weighed in rows of classes: no pair of mentions is a row."""

from pyspark.sql import functions as F

from erfocus.functions.features import PAIRWISE, TWO_WORD_NAMES
from erfocus.operators import score
from erfocus.plans import queries


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def _copied(spark, small, copies):
    p = queries.Part(spark, small)
    base = p.mentions.join(p.members(p.one).select("mention_id"), "mention_id", "left_semi")
    keyed = base.withColumn("context", F.when(F.col("mention_id") % 3 == 0, F.col("context").withField("keywords", F.array(F.lit("topic_1"), F.lit("red")))).otherwise(F.col("context")))
    m = keyed.crossJoin(spark.range(copies).withColumnRenamed("id", "k")).withColumn("of", F.col("mention_id")).withColumn("mention_id", F.col("mention_id") + 10_000 * F.col("k")).drop("k").localCheckpoint()
    return m.drop("of"), m.select("mention_id", F.col("of").alias("rep"))


def test_deltas_by_rows_are_those_of_all_edges(spark, small):
    mentions, of = _copied(spark, small, 3)
    members = mentions.select(F.lit(0).cast("long").alias("query_id"), "mention_id")
    state = mentions.select(F.explode(F.array(F.lit(0), F.lit(1))).alias("run_id"), "mention_id").withColumn("entity_id", F.when(F.col("run_id") == 0, F.col("mention_id") % 5).otherwise(F.col("mention_id"))).localCheckpoint()
    some = state.where("mention_id % 4 = 1").select("run_id", "mention_id")
    moves = some.withColumn("entity_to", F.col("mention_id") % 3).union(some.withColumn("entity_to", -F.col("mention_id") - 1)).localCheckpoint()
    reps = mentions.where("mention_id < 10000")
    for specs in (PAIRWISE, TWO_WORD_NAMES):
        edges = score.pair_edges(members, mentions, specs, level="paragraph").drop("query_id").localCheckpoint()
        want = rows(score.move_delta(state, edges, moves))
        assert any(r[4] for r in want)
        assert rows(score.move_delta_on_demand(state, score.sides(mentions, "paragraph"), moves, specs)) == want
        assert rows(score.move_delta_on_demand(state, score.sides(reps, "paragraph"), moves, specs, of=of)) == want


def test_moves_into_a_large_entity_make_no_row_a_pair(spark, small, monkeypatch):
    mentions, of = _copied(spark, small, 40)
    state = mentions.select(F.lit(0).alias("run_id"), "mention_id", F.when(F.col("mention_id") % 2 == 0, 0).otherwise(F.col("mention_id")).cast("long").alias("entity_id")).localCheckpoint()
    moves = state.where("entity_id > 0").select("run_id", "mention_id", F.lit(0).cast("long").alias("entity_to")).localCheckpoint()
    side = score.sides(mentions.where("mention_id < 10000"), "paragraph").localCheckpoint()
    most, cut = [], score.cut
    monkeypatch.setattr(score, "cut", lambda df: (done := cut(df), most.append(done.count()))[0])
    found = score.move_delta_on_demand(state, side, moves, TWO_WORD_NAMES, of=of)
    assert found.count() == moves.count() and 0 < max(most) <= 2 * state.count()
    assert found.groupBy("delta").count().count() <= side.count()


def test_no_move_has_no_delta(spark, small):
    mentions, of = _copied(spark, small, 2)
    state = mentions.select(F.lit(0).alias("run_id"), "mention_id", F.col("mention_id").alias("entity_id"))
    none = state.where("false").select("run_id", "mention_id", F.lit(0).cast("long").alias("entity_to"))
    assert score.move_delta_on_demand(state, score.sides(mentions, "paragraph"), none, TWO_WORD_NAMES).count() == 0
