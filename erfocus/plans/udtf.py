"""A table function for SQL: the entity of a text among a table's mentions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class SelectEntity:
    """er_select(TABLE(mentions) PARTITION BY block, text, keywords, samples): a chain over each partition.

    The partition is the canopy: it is to be blocked by the caller's WHERE or PARTITION BY, as a partition is one
    task's.  The table needs mention_id, mention and context.
    """

    def __init__(self):
        self.rows, self.args = [], None

    def eval(self, row, text: str, keywords, samples: int):
        self.rows.append((row["mention_id"], row["mention"], list(row["context"]["document"] or [])))
        self.args = (text, list(keywords or []), samples)

    def terminate(self):
        if self.args is None:
            return
        import numpy as np

        from erfocus.functions import features
        from erfocus.functions.strings import py_tokens
        from erfocus.operators.kernel import Budget, Chain, Query
        from erfocus.operators.pairs import PairModel, Sides
        from erfocus.operators.samplers import Settings, biased, decay_weights

        text, keywords, samples = self.args
        rows = sorted([*self.rows, (-1, text, [])], key=lambda r: r[0])
        names = [m or "" for _, m, _ in rows]
        sides = Sides.of([r[0] for r in rows], [r[0] for r in rows], [m.strip(" ").lower() for m in names], [py_tokens(m) for m in names], [ctx for _, _, ctx in rows], [keywords if i == -1 else () for i, _, _ in rows])
        model = PairModel(features.SHORT_NAMES, sides, cosines=False)
        at = next(k for k, r in enumerate(rows) if r[0] == -1)
        infl = model.row(at).astype(float)
        infl[at] = model.own_weight(at)
        s = Settings()
        chain = Chain(sides.ids, model, [Query(-1, at, biased(decay_weights(infl, s), "cdf"))])
        Budget(samples).spend(chain, lambda c: (c.queries[0], samples))
        for k in chain.members[int(chain.entity[at])]:
            if k != at:
                yield rows[k][0], rows[k][1]


def register(spark: SparkSession) -> None:
    spark.udtf.register("er_select", udtf(SelectEntity, returnType="mention_id bigint, mention string"))
