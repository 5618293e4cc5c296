"""Registered chains over a canopy of over a hundred thousand mentions, beside a walk over the SQL's own canopy, weights and draws.

The whole SQL pairs all mentions of the canopy; here each pair's weight is that of its two classes of equal sides.
"""

from bisect import bisect_left, bisect_right, insort

import duckdb
import pytest

import __spark_entry__ as entry
from erfocus.functions.features import TWO_WORD_NAMES
from erfocus.functions.rand import py_h32
from erfocus.plans import oracles


class Large:
    """A part table of names of one noun, repeated with shifted keys, and what the SQL makes of it."""

    def __init__(self, source, folder, rows=160_000):
        self.folder, self.con = str(folder), duckdb.connect()
        self.con.execute(f"CREATE TABLE once AS SELECT * REPLACE (row_number() OVER (ORDER BY p_partkey) - 1 AS p_partkey) FROM '{source}/part.parquet' WHERE p_name LIKE '% ' || (SELECT split_part(p_name, ' ', 2) FROM '{source}/part.parquet' ORDER BY p_partkey LIMIT 1)")
        n = self.rows("SELECT count(*) FROM once")[0][0]
        self.con.execute(f"COPY (SELECT o.* REPLACE (p_partkey + k * {n} AS p_partkey) FROM once o, range({rows // n}) r(k)) TO '{folder}/part.parquet'")
        self.con.execute(f"CREATE VIEW part AS SELECT * FROM '{folder}/part.parquet'")
        self.con.execute(f"CREATE TABLE c1 AS WITH {oracles.base()}, {oracles.ALL_OF}, {oracles.OF_ONE} SELECT c1.*, gold, mention, paragraph FROM c1 JOIN m USING (mention_id)")
        self.con.execute(f"CREATE TABLE sd AS WITH {oracles.sides('paragraph', 'c1')} SELECT *, min(mention_id) OVER (PARTITION BY m, toks, ctx, gs) AS rep FROM sd")
        self.con.execute("CREATE TABLE one_each AS SELECT * FROM sd WHERE mention_id = rep")
        self.weight = f"({oracles.weight(TWO_WORD_NAMES)})::BIGINT"
        self.own = self.rows("SELECT min(query_id) FROM c1")[0][0]
        infl = f"infl AS (SELECT a.mention_id AS query_id, sd.mention_id, w AS infl FROM (SELECT a.mention_id, b.rep, {self.weight} AS w FROM sd a, one_each b WHERE a.mention_id = {self.own}) a JOIN sd USING (rep))"
        found = self.rows(f"WITH {infl}, {oracles.DECAY} SELECT mention_id, rep, gold, floor(weight * 1000000 + 0.5)::BIGINT, sum(floor(weight * 1000000 + 0.5)::BIGINT) OVER (ORDER BY mention_id) FROM dec JOIN sd USING (mention_id) JOIN c1 USING (mention_id) ORDER BY mention_id")
        self.ids, self.rep, self.gold, _, self.cum = (list(x) for x in zip(*found, strict=True))
        self.known = {}

    def rows(self, sql):
        return self.con.execute(sql).fetchall()

    def pull(self, m, others):
        """The sum of m's weights with others."""
        r = self.rep[m]
        if r not in self.known:
            self.known[r] = dict(self.rows(f"SELECT b.rep, {self.weight} FROM one_each a, one_each b WHERE a.rep = {r}"))
        return sum(self.known[r][self.rep[x]] for x in others if x != m)

    def walk(self, sampler, steps):
        """(step, m, e_from, e_to, delta, accepted) from singletons, greedily."""
        n, at, out = len(self.ids), bisect_left(self.ids, self.own), []
        label, groups, ent = list(range(n)), {i: [i] for i in range(n)}, list(range(n))
        for t in range(steps):
            h = lambda slot: py_h32(f"1|0|{t}|{slot}")  # noqa: E731, B023
            if sampler == "uniform" or h(0) >= int(0.9 * 2**32):
                source, target = ent[h(1) * len(ent) >> 32], ent[h(3) * len(ent) >> 32]
                m = groups[source][h(2) * len(groups[source]) >> 32]
            else:
                tries = [bisect_right(self.cum, int(h(slot)) * int(self.cum[-1]) >> 32) for slot in (5, 9, 11, 13, 15)]
                m = next((x for x in tries if label[x] != label[at]), tries[-1])
                source, target = label[m], label[at]
            nothing = source == target or (sampler != "uniform" and m == at)
            delta = 0 if nothing else self.pull(m, groups[target]) - self.pull(m, groups[source])
            out.append((t, self.ids[m], self.ids[source], self.ids[target], delta, delta > 0))
            if delta > 0:
                left, joined = [x for x in groups[source] if x != m], sorted([*groups[target], m])
                for e in (source, target):
                    del groups[e], ent[bisect_left(ent, e)]
                for g in filter(None, (left, joined)):
                    groups[g[0]] = g
                    insort(ent, g[0])
                    for x in g:
                        label[x] = g[0]
        return out


@pytest.fixture(scope="module")
def large(tmp_path_factory):
    found = Large("/root/testdata/sf0.001", tmp_path_factory.mktemp("large"))
    assert len(found.ids) > 100_000
    return found


@pytest.fixture(scope="module")
def uniform(large):
    return large.walk("uniform", 2 * oracles.STEPS)


def got(spark, large, name):
    return sorted(tuple(r) for r in entry.queries()[name](spark, large.folder).collect())


def test_chain_influence_to_query(spark, large):
    want = large.walk("influence_to_query", oracles.STEPS)
    assert got(spark, large, "chain_influence_to_query") == want and len({r[5] for r in want}) == 2


def test_chain_uniform(spark, large, uniform):
    want = uniform[: oracles.STEPS]
    assert got(spark, large, "chain_uniform") == want and len({r[5] for r in want}) == 2


def test_first_correct(spark, large, uniform):
    gold = dict(zip(large.ids, large.gold, strict=True))
    right = [r[0] for r in uniform if r[5] and gold[r[1]] == gold[large.own]]
    assert right and got(spark, large, "first_correct") == [(large.own, right[0])]


def test_proposal_counts(spark, large, uniform):
    hits = [r[0] for r in uniform[: oracles.STEPS] if r[5]]
    assert got(spark, large, "proposal_counts") == [(oracles.STEPS, len(hits), round(len(hits) / oracles.STEPS, 9), hits[0])]
