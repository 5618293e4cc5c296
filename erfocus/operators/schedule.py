"""Schedules of many queries over one model: which query proposes next, and how often."""

from __future__ import annotations

from collections import deque

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

QUANTUM = 500
POLICIES = ("round_robin", "by_selectivity", "closest_first", "farthest_first", "slowest_first", "equal")


def plan(queries: DataFrame, policy: str, total: int, quantum: int = QUANTUM) -> DataFrame:
    """(slot, query_id, k): static schedules of total proposals over (query_id, sel).

    round_robin: quanta in turns; equal: a query's whole share at once, in turns of ids; by_selectivity: shares
    in proportion to selectivity, by largest remainders, cut into quanta that are spread evenly over the whole
    schedule, of equal places the larger query's first.
    """
    n = F.count(F.lit(1)).over(Window.partitionBy(F.lit(0)))
    if policy == "round_robin":
        place = F.row_number().over(Window.partitionBy(F.lit(0)).orderBy("query_id")) - 1
        slots = -(-total // quantum)
        rows = queries.select("query_id", place.alias("i"), n.alias("n"))
        rows = rows.withColumn("slot", F.explode(F.sequence(F.col("i"), F.greatest(F.col("i"), F.lit(slots - 1)), F.col("n")))).where(F.col("slot") < slots)
        k = F.least(F.lit(quantum), F.lit(total) - F.col("slot") * quantum)
        return rows.select(F.col("slot").cast("int").alias("slot"), "query_id", k.cast("int").alias("k"))
    shares = queries.withColumn("sel", F.lit(1)) if policy == "equal" else queries
    if policy not in ("equal", "by_selectivity"):
        raise ValueError(f"{policy} is no static schedule")
    whole = Window.partitionBy(F.lit(0))
    exact = F.lit(total) * F.col("sel") / F.sum("sel").over(whole)
    rows = shares.select("query_id", "sel", exact.alias("x")).withColumn("base", F.floor("x")).withColumn("left", F.lit(total) - F.sum("base").over(whole))
    rank = F.row_number().over(whole.orderBy(F.desc(F.round(F.col("x") - F.col("base"), 9)), "query_id"))
    rows = rows.withColumn("k", (F.col("base") + F.when(rank <= F.col("left"), 1).otherwise(0)).cast("int"))
    rows = rows.where("k > 0").withColumn("n", F.ceil(F.col("k") / quantum).cast("int") if policy == "by_selectivity" else F.lit(1))
    rows = rows.withColumn("part", F.explode(F.sequence(F.lit(1), F.col("n"))))
    size = F.when(F.col("part") < F.col("n"), F.lit(quantum)).otherwise(F.col("k") - (F.col("n") - 1) * quantum) if policy == "by_selectivity" else F.col("k")
    order = [(F.col("part") - 1) / F.col("n"), F.desc("sel"), "query_id"] if policy == "by_selectivity" else ["query_id", "part"]
    return rows.select((F.row_number().over(whole.orderBy(*order)) - 1).alias("slot"), "query_id", size.cast("int").alias("k"))


def acceptance(trace: DataFrame, last: int = QUANTUM) -> DataFrame:
    """(run_id, query_id, step, rate): accepted share of each query's last proposals up to each step."""
    w = Window.partitionBy("run_id", "query_id").orderBy("step").rowsBetween(-(last - 1), 0)
    return trace.select("run_id", "query_id", "step", F.avg(F.col("accepted").cast("int")).over(w).alias("rate"))


def latest(trace: DataFrame, last: int = QUANTUM) -> DataFrame:
    """(run_id, query_id, rate, n): the share accepted of each query's last proposals."""
    w = Window.partitionBy("run_id", "query_id").orderBy(F.desc("step"))
    tail = trace.withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= last)
    return tail.groupBy("run_id", "query_id").agg(F.avg(F.col("accepted").cast("int")).alias("rate"), F.count(F.lit(1)).alias("n"))


def next_query(rates: DataFrame, policy: str) -> DataFrame:
    """(run_id, query_id): the query a dynamic policy takes next from (run_id, query_id, rate).

    closest_first: the lowest positive rate; farthest_first: the highest; slowest_first: the lowest rate of
    all.  Ties go to the smaller id; if no rate is positive, so does the choice.
    """
    key = {
        "closest_first": [F.when(F.col("rate") > 0, F.col("rate")).asc_nulls_last()],
        "farthest_first": [F.desc("rate")],
        "slowest_first": [F.asc("rate")],
    }[policy]
    w = Window.partitionBy("run_id").orderBy(*key, "query_id")
    return rates.withColumn("__k", F.row_number().over(w)).where("__k = 1").select("run_id", "query_id")


class Turns:
    """A schedule inside a chain over one component's queries."""

    def __init__(self, queries: list, policy: str, total: int, quantum: int = QUANTUM, sel: dict | None = None, last: int | None = None):
        if policy not in POLICIES:
            raise ValueError(f"{policy} is none of {POLICIES}")
        self.queries, self.policy, self.quantum = queries, policy, quantum
        self.recent = {q.query_id: deque(maxlen=last or quantum) for q in queries}
        self.turn = 0
        self.fixed = self._fixed(total, sel) if policy in ("by_selectivity", "equal") else None

    def _fixed(self, total: int, sel: dict | None) -> list:
        weight = {q.query_id: (sel or {}).get(q.query_id, 1) if self.policy == "by_selectivity" else 1 for q in self.queries}
        share = {i: total * w / sum(weight.values()) for i, w in weight.items()}
        whole = {i: int(x) for i, x in share.items()}
        order = sorted(share, key=lambda i: (-round(share[i] - whole[i], 9), i))
        for i in order[: total - sum(whole.values())]:
            whole[i] += 1
        by = {q.query_id: q for q in self.queries}
        ids = sorted(whole, key=lambda i: (-weight[i], i))
        if self.policy == "equal":
            return [(by[i], whole[i]) for i in sorted(whole) if whole[i]]
        parts = {i: range(0, whole[i], self.quantum) for i in ids}
        slots = sorted((k / len(own), n, i, a) for n, (i, own) in enumerate(parts.items()) for k, a in enumerate(own))
        return [(by[i], min(self.quantum, whole[i] - a)) for _, _, i, a in slots]

    def __call__(self, chain):
        for r in chain.trace[-self._new :] if self.turn else ():
            self.recent[r[2]].append(r[-1])
        if self.fixed is not None:
            q, k = self.fixed[min(self.turn, len(self.fixed) - 1)]
        else:
            q, k = self._dynamic(), self.quantum
        self.turn += 1
        self._new = k
        return q, k

    def _dynamic(self):
        n = len(self.queries)
        if self.policy == "round_robin" or self.turn < n:
            return self.queries[self.turn % n]
        rate = {q.query_id: sum(self.recent[q.query_id]) / max(1, len(self.recent[q.query_id])) for q in self.queries}
        if not any(rate.values()):
            return self.queries[self.turn % n]
        if self.policy == "closest_first":
            return min((q for q in self.queries if rate[q.query_id] > 0), key=lambda q: (rate[q.query_id], q.query_id))
        if self.policy == "farthest_first":
            return min(self.queries, key=lambda q: (-rate[q.query_id], q.query_id))
        return min(self.queries, key=lambda q: (rate[q.query_id], q.query_id))
