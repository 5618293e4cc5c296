"""Every registered query beside its SQL, on the smallest tables."""

import math
import os
from decimal import Decimal

import duckdb
import pytest

import __spark_entry__ as entry
from erfocus.plans import oracles, queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(small):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return c


def cell(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return "null"
    if isinstance(v, (float, Decimal)):
        return f"{float(v):.7g}"
    return str(v)


def table(names, rows):
    order = sorted(range(len(names)), key=names.__getitem__)
    return sorted(tuple(cell(r[i]) for i in order) for r in rows)


@pytest.mark.parametrize("name", sorted(oracles.oracle_sql()))
def test_query_equals_its_sql(spark, small, con, name):
    got = entry.queries()[name](spark, small)
    want = con.execute(entry.oracle_sql()[name])
    names = [d[0] for d in want.description]
    assert sorted(got.columns) == sorted(names)
    assert table(got.columns, got.collect()) == table(names, want.fetchall())


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert set(queries.QUERIES) <= set(entry.queries())


def test_entry_gives_rows(spark):
    assert entry.entry(spark).columns == ["query_id", "mention_id"]


def test_nothing_outside_imports_the_llm_subpackage():
    root = os.path.dirname(os.path.abspath(entry.__file__))
    for folder, _, files in os.walk(os.path.join(root, "erfocus")):
        if os.path.basename(folder) == "llm":
            continue
        for f in files:
            if f.endswith(".py"):
                with open(os.path.join(folder, f)) as text:
                    assert "erfocus.llm" not in text.read(), f


def test_exact_keys_take_their_mentions_from_the_given_table(spark, small, tmp_path):
    from pyspark.sql import functions as F

    for t in TABLES:
        os.symlink(f"{small}/{t}.parquet", tmp_path / f"{t}.parquet")
    (tmp_path / "part.parquet").unlink()
    parts = spark.read.parquet(f"{small}/part.parquet").withColumn("p_partkey", F.col("p_partkey") + 5000)
    parts.coalesce(1).write.parquet(str(tmp_path / "part.parquet"))
    for name in ("exact_map", "exact_marginal"):
        ids = {r.mention_id for r in entry.queries()[name](spark, str(tmp_path)).collect()}
        assert ids and min(ids) >= 5000
    best = entry.queries()["exact_posterior"](spark, str(tmp_path)).agg(F.max("score")).first()[0]
    assert {r.exact_score for r in entry.queries()["w7_worked_example"](spark, str(tmp_path)).collect()} == {best}
