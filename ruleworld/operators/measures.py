"""Probabilities of worlds, what pruning saves, agreement with known labels, and times of phases."""

from __future__ import annotations

import time
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.operators import field as views
from ruleworld.operators import kernel


def potentials(field, world: DataFrame) -> DataFrame:
    """``cid, rule, potential`` of every clause: 1 where the world meets it, else exp(-|weight|), or 0 if it is hard."""
    bad = F.when(F.col("is_hard"), 0.0).otherwise(F.exp(-F.abs("weight")))
    return views.judged(field.clauses, world).select("cid", "rule", F.when(F.col("violated"), bad).otherwise(1.0).alias("potential"))


def log_partition(field, comps: DataFrame, most: int = 20) -> DataFrame:
    """``log_z``: logarithm of the sum of exp(-cost) over all worlds of the clauses' atoms, evidence's cost included.

    The sum of components' logarithms, each by enumeration. Raises where a component has more than ``most`` atoms, or where
    evidence or a component breaks hard rules in every world.
    """
    from ruleworld.plans.solve import _by_unit, _none_larger, binned, by_load

    _none_larger(comps, most)

    def run(t: pa.Table) -> pa.Table:
        out = [(comp, kernel.exact_marginals(kernel.Clauses.build(rows))[1]) for comp, rows in _by_unit(t, "comp")]
        return pa.table({"comp": pa.array([c for c, _ in out], pa.int64()), "log_z": pa.array([z for _, z in out], pa.float64())})

    each = by_load(binned(field.clauses, comps, budget="fixed"), run, "comp bigint, log_z double")
    base = field.constants.agg(F.coalesce(F.sum("hard_contradictions"), F.lit(0)).alias("h"), F.coalesce(F.sum("constant_cost"), F.lit(0.0)).alias("s"))
    whole = each.agg(F.coalesce(F.sum("log_z"), F.lit(0.0)).alias("z")).crossJoin(base)
    refused = F.raise_error(F.lit("evidence breaks hard rules in every world")).cast("double")
    return whole.select(F.when(F.col("h") > 0, refused).otherwise(F.col("z") - F.col("s")).alias("log_z"))


def world_probability(field, comps: DataFrame, world: DataFrame, most: int = 20) -> DataFrame:
    """``log_probability, probability`` of a world of the clauses' atoms; 0 where it breaks a hard rule."""
    both = views.world_cost(field, world).crossJoin(log_partition(field, comps, most))
    log = F.when(F.col("hard") > 0, float("-inf")).otherwise(-F.col("soft") - F.col("log_z"))
    return both.select(log.alias("log_probability"), F.exp(log).alias("probability"))


def prune_stats(program, atoms, closure: bool = True) -> DataFrame:
    """``rule, before, after, active``: instances with all evidence's truths left open, those evidence leaves undecided, and
    clauses of the rule in the active closure (null without ``closure``)."""
    from ruleworld.plans import ground as g
    from ruleworld.sources.scratch import settle

    before = None
    for c in program.clauses:
        rows = g.ground_rule(atoms, c, prune=False).agg(F.count("*").alias("before")).select(F.lit(c.id).alias("rule"), "before")
        before = rows if before is None else before.unionByName(rows)
    raw = settle(g.ground_raw(program, atoms).filter("state = 'free'"))
    after = raw.groupBy("rule").agg(F.count("*").alias("after"))
    out = before.join(after, "rule", "left").select("rule", "before", F.coalesce("after", F.lit(0)).alias("after"))
    if not closure:
        return out.withColumn("active", F.lit(None).cast("long"))
    clauses = settle(g.canonicalise(raw).withColumn("cid", F.xxhash64("rule", "lits", "is_hard", "weight")))
    active, _ = g.active_closure(clauses)
    return out.join(active.groupBy("rule").agg(F.count("*").alias("active")), "rule", "left").withColumn("active", F.coalesce("active", F.lit(0)))


def accuracy(guessed: DataFrame, known: DataFrame, key: str, label: str) -> DataFrame:
    """``n, told, accuracy``: of the rows of ``known`` (``key, label``), how many have a guess, and the share that is right.

    Several guesses for a key count as right if they are one and that one is right.
    """
    one = guessed.groupBy(key).agg(F.min(label).alias("g"), F.countDistinct(label).alias("several"))
    met = known.select(key, label).join(one, key, "left")
    right = F.count_if((F.col("several") == 1) & (F.col("g") == F.col(label)))
    return met.agg(F.count("*").alias("n"), F.count("g").alias("told"), F.round(right / F.count("*"), 6).alias("accuracy"))


def precision_recall(guessed: DataFrame, known: DataFrame, key: str, label: str) -> DataFrame:
    """``label, precision, recall`` over the keys of ``known``."""
    met = known.select(key, F.col(label).alias("t")).join(guessed.select(key, F.col(label).alias("g")), key, "left")
    by_guess = met.filter("g IS NOT NULL").groupBy(F.col("g").alias("label")).agg(F.round(F.avg((F.col("g") == F.col("t")).cast("double")), 6).alias("precision"))
    by_truth = met.groupBy(F.col("t").alias("label")).agg(F.round(F.avg(F.coalesce((F.col("g") == F.col("t")).cast("double"), F.lit(0.0))), 6).alias("recall"))
    return by_truth.join(by_guess, "label", "left").select("label", "precision", "recall")


class Phases:
    """Seconds by phase: ``with phases.timed("ground"): ...`` around an action that ends it."""

    def __init__(self):
        self.seconds: dict[str, float] = {}

    @contextmanager
    def timed(self, name: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began


def neighbours(clauses: DataFrame) -> DataFrame:
    """``aid, neighbours``: how many other atoms share a clause with each atom."""
    lit = clauses.select("cid", F.explode(F.transform("lits", lambda x: F.abs(x))).alias("aid"), F.transform("lits", lambda x: F.abs(x)).alias("all"))
    return lit.select("aid", F.explode("all").alias("other")).filter("aid <> other").groupBy("aid").agg(F.countDistinct("other").alias("neighbours"))
