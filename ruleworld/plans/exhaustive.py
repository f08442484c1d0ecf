"""Grounding without pruning: every substitution of every variable, as a check on small domains.

A rule with v variables over a domain of n values has n^v instances, whatever the evidence. Nothing here is meant for
large tables; the pruned grounding must give every world the same cost.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleworld.plans.ground import Atoms, evidence_rows
from ruleworld.plans.program import Clause, Literal, Program, Term

GROUND = "rule string, weight double, is_hard boolean, met boolean, literals array<struct<pred:string,args:string,positive:boolean>>"


def domains_of(program: Program, evidence: dict[str, DataFrame]) -> dict[str, DataFrame]:
    """The values of each domain of the declarations: all that evidence and candidates hold (column ``value``)."""
    found: dict[str, list[DataFrame]] = {}
    for name, p in program.predicates.items():
        rows = evidence_rows(p, evidence[name])
        for (domain, _), c in zip(p.args, p.columns, strict=True):
            found.setdefault(domain, []).append(rows.select(F.col(c).alias("value")))
    return {d: reduce(DataFrame.unionByName, parts).filter("value IS NOT NULL").distinct() for d, parts in found.items()}


def _value(t: Term) -> Column:
    return F.col(f"v_{t.value}") if t.variable else F.lit(t.value)


def _ground_literal(x: Literal) -> Column:
    args = F.concat_ws(",", *[_value(t).cast("string") for t in x.terms])
    return F.struct(F.lit(x.pred).alias("pred"), args.alias("args"), F.lit(x.positive).alias("positive"))


def _instances(program: Program, c: Clause, domains: dict[str, DataFrame]) -> DataFrame:
    kinds: dict[str, str] = {}
    for x in c.literals:
        for t, (d, _) in zip(x.terms, program.predicates[x.pred].args, strict=True):
            if t.variable:
                kinds[t.value] = d

    def over(names: list[str], start: DataFrame | None = None) -> DataFrame:
        parts = [domains[kinds[v]].select(F.col("value").alias(f"v_{v}")) for v in names]
        return reduce(DataFrame.crossJoin, parts if start is None else [start, *parts])

    spark = next(iter(domains.values())).sparkSession
    outer = sorted(set(kinds) - c.exists)
    rows = over(outer) if outer else spark.range(1).select(F.lit(1).alias("v__one"))
    met = reduce(Column.__or__, [(_value(e.left) == _value(e.right)) == F.lit(e.positive) for e in c.equals], F.lit(False))
    plain = [x for x in c.literals if not x.variables() & c.exists]
    literals = F.array(*[_ground_literal(x) for x in plain]) if plain else F.array().cast("array<struct<pred:string,args:string,positive:boolean>>")
    rows = rows.withColumn("met", met).withColumn("literals", literals)
    for x in c.literals:
        inner = sorted(x.variables() & c.exists)
        if inner:
            keys = [f"v_{v}" for v in outer] or ["v__one"]
            wide = over(inner, rows).groupBy(*keys, "met", "literals").agg(F.collect_list(_ground_literal(x)).alias("more"))
            rows = wide.withColumn("literals", F.concat("literals", "more")).drop("more")
    return rows.select(F.lit(c.id).alias("rule"), F.lit(float(c.weight)).alias("weight"), F.lit(c.hard).alias("is_hard"), "met", "literals")


def ground_exhaustive(program: Program, domains: dict[str, DataFrame]) -> DataFrame:
    """``GROUND``: every instance of every rule with all its literals; ``met`` tells that an equality holds already."""
    return reduce(DataFrame.unionByName, [_instances(program, c, domains) for c in program.clauses])


def full_world(atoms: Atoms, world: DataFrame) -> DataFrame:
    """``pred, args, value`` of all atoms that evidence or ``world`` (``aid, value``) makes true or false; all others are false."""
    parts = []
    for name, p in atoms.program.predicates.items():
        t = atoms.tables[name]
        args = F.concat_ws(",", *[F.col(c).cast("string") for c in p.columns]).alias("args")
        if p.open:
            t = t.join(world.select("aid", "value"), "aid", "left")
            value = F.when(F.col("truth") >= 0, F.col("truth") == 1).otherwise(F.coalesce("value", F.lit(False)))
        else:
            value = F.col("truth") == 1
        parts.append(t.select(F.lit(name).alias("pred"), args, value.alias("value")))
    return reduce(DataFrame.unionByName, parts)


def exhaustive_cost(ground: DataFrame, world: DataFrame) -> DataFrame:
    """``hard, soft`` of a full world over all instances."""
    rows = ground.withColumn("iid", F.monotonically_increasing_id())
    lit = rows.select("iid", F.explode_outer("literals").alias("x")).select("iid", "x.*")
    told = lit.join(world, ["pred", "args"], "left")
    true = told.groupBy("iid").agg(F.coalesce(F.bool_or(F.coalesce("value", F.lit(False)) == F.col("positive")), F.lit(False)).alias("true"))
    judged = rows.join(true, "iid").withColumn("true", F.col("true") | F.col("met"))
    bad = judged.filter((F.col("weight") > 0) != F.col("true"))
    return bad.agg(F.count_if("is_hard").alias("hard"), F.coalesce(F.sum(F.when(~F.col("is_hard"), F.abs("weight"))), F.lit(0.0)).alias("soft"))
