"""Functions of ground clauses for SQL sessions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

CLAUSE_VIOLATED = """
CREATE OR REPLACE TEMPORARY FUNCTION clause_violated(lits ARRAY<BIGINT>, weight DOUBLE, true_atoms ARRAY<BIGINT>) RETURNS BOOLEAN
RETURN (weight > 0) <> exists(lits, x -> (x > 0) = array_contains(true_atoms, abs(x)))"""


@udtf(returnType="true_atoms array<bigint>, hard bigint, soft double")
class EnumerateComponent:
    """``enumerate_component(lits, weights)``: every world of a small component (at most 16 atoms) with its cost.

    ``lits`` are the clauses' signed atoms, ``weights`` their weights; an infinite weight marks a hard clause.
    """

    def eval(self, lits, weights):
        from ruleworld.operators.kernel import Clauses, all_costs

        rows = [(x, 1.0 if w == float("inf") else w, w == float("inf")) for x, w in zip(lits or [], weights or [], strict=True)]
        cl = Clauses.build(rows)
        hard, soft = all_costs(cl, 16)
        for world in range(len(hard)):
            yield [a for k, a in enumerate(cl.ids) if world >> k & 1], int(hard[world]), float(soft[world])


def register(spark: SparkSession) -> None:
    """Make ``clause_violated`` and ``enumerate_component`` known to SQL of the session."""
    spark.sql(CLAUSE_VIOLATED)
    spark.udtf.register("enumerate_component", EnumerateComponent)
