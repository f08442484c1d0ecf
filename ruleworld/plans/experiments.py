"""The experiments as tables: partitioning on and off, time-cost curves, loading, size bounds, memory, table search, chains.

Each takes workload makers' results, ``(program, evidence)``, and returns a small DataFrame of what was measured. Costs are
sums over the whole field, evidence included. Times are wall-clock seconds of the session at hand.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleworld.operators import chain, kernel, split
from ruleworld.operators import field as views
from ruleworld.plans import ground as g
from ruleworld.plans import solve
from ruleworld.sources.scratch import settle

Made = tuple[g.Program, dict[str, DataFrame]]


def _spark(made: Made) -> SparkSession:
    return next(iter(made[1].values())).sparkSession


def partitioning(workloads: dict[str, Made], total: int = 10**5, seed: int = 0) -> DataFrame:
    """Cost after equal flips: one walk over all, one walk with the best kept by component, and a walk for each component."""
    out = []
    for name, made in workloads.items():
        spark = _spark(made)
        for how, kw in (("whole", {"partition": False}), ("whole, best by component", {"partition": False, "best": "component"}), ("by component", {})):
            r = solve.solve_map(*made, total=total, tries=1, seed=seed, **kw)
            out.append((name, how, r.hard, r.soft, r.flips, r.seconds["ground"], r.seconds["search"]))
    return spark.createDataFrame(out, "workload string, search string, hard long, soft double, flips long, ground_seconds double, search_seconds double")


def loading(made: Made, flips: int = 2000, capacity: int = 20_000) -> DataFrame:
    """Seconds to search all components: a load each in one worker, packed loads in one worker, packed loads in parallel."""
    spark, fld = _spark(made), g.ground(*made)
    comps = settle(views.components(fld.clauses))
    out = []
    for how, packing, parallel in (("one by one", "single", 1), ("packed, one worker", "ffd", 1), ("packed, parallel", "ffd", None)):
        began = time.perf_counter()
        found = settle(solve.search_components(fld.clauses, comps, 1, budget="fixed", flips=flips, packing=packing, capacity=capacity, parallel=parallel))
        seconds = time.perf_counter() - began
        r = found.groupBy("comp").agg(F.max("soft").alias("soft"), F.max("flips").alias("flips")).agg(F.sum("soft").alias("soft"), F.sum("flips").alias("flips")).first()
        out.append((how, seconds, float(r.soft or 0), int(r.flips or 0), (r.flips or 0) / seconds))
    return spark.createDataFrame(out, "loading string, seconds double, soft double, flips long, flips_per_second double")


def size_bounds(field_of: Made, betas: list[int], sweeps: int = 3, flips: int = 2000, seed: int = 0, total: int | None = None) -> DataFrame:
    """Costs of alternating search over size bounds, with the pieces and the cut that each bound makes; the last, no bound."""
    spark, fld = _spark(field_of), g.ground(*field_of)
    comps = settle(views.components(fld.clauses))
    out = []
    for beta in [*betas, None]:
        pieces = settle(split.split_bounded(fld.clauses, comps, beta))
        cut = views.cut_stats(fld.clauses, pieces).first()
        world, costs, made = solve.alternate(fld, pieces, sweeps, flips, seed=seed, total=total)
        n = pieces.select("piece").distinct().count()
        gain, loss = split.partition_benefit(n, sweeps, cut.cut_clauses, cut.clauses)
        out.append((beta, n, cut.cut_clauses, float(cut.cut_share or 0), gain, loss, costs[0][1], costs[-1][0], costs[-1][1], made))
    return spark.createDataFrame(out, "beta long, pieces long, cut_clauses long, cut_share double, log2_gain double, loss double, first_soft double, hard long, soft double, flips long")


def memory(workloads: dict[str, Made]) -> DataFrame:
    """Bytes of clause tables and searches by workload, next to what grounding in memory would hold."""
    out = None
    for name, (program, evidence) in workloads.items():
        raw = settle(g.ground_raw(program, g.load_atoms(program, evidence)))
        fld = g.ground(program, evidence)
        row = views.memory(fld.clauses, settle(views.components(fld.clauses)), raw).select(F.lit(name).alias("workload"), "*")
        out = row if out is None else out.unionByName(row)
    return out


def over_budget(made: Made, budget: int, total: int = 10**4) -> DataFrame:
    """Under a declared budget: the whole-field search refuses, the engine chooses a path that fits."""
    spark = _spark(made)
    try:
        r = solve.solve_map(*made, budget=budget, partition=False, refuse=True, total=total)
        out = [("whole", r.path, r.hard, r.soft)]
    except solve.OverBudget:
        out = [("whole", "refused", None, None)]
    r = solve.solve_map(*made, budget=budget, total=total, sweeps=2)
    out.append(("engine", r.path, r.hard, r.soft))
    return spark.createDataFrame(out, "search string, path string, hard long, soft double")


def table_search(made: Made, flips: int = 5, total: int = 10**4, latency: float = 0.01) -> DataFrame:
    """Flips a second inside tables, in memory, and the ceiling that one random access a flip sets."""
    spark, fld = _spark(made), g.ground(*made)
    rates = [("table", solve.table_walk(fld.clauses, flips)[2]), ("table, sorted by atom", solve.table_walk(fld.clauses, flips, clustered=True)[2])]
    r = solve.search_whole(fld.clauses, flips=total).agg(F.max("flips").alias("flips"), F.max("ms").alias("ms")).first()
    rates += [("memory", r.flips / max(r.ms / 1e3, 1e-9)), ("disk ceiling", split.flip_ceiling(latency))]
    return spark.createDataFrame(rates, "search string, flips_per_second double")


def identical_components(spark: SparkSession, sizes: list[int]) -> DataFrame:
    """Expected steps of one walk over n two-atom components, of a walk for each, and the bounds on their ratio."""
    rows = [((1,), 1.0, False), ((2,), 1.0, False), ((1, 2), -1.0, False)]
    return identical_kinds(spark, [(kernel.Clauses.build(rows), max(sizes))], sizes)


def identical_kinds(spark: SparkSession, kinds: list[tuple[kernel.Clauses, int]], sizes: list[int]) -> DataFrame:
    """The same for n components of each kind that a field holds so many of."""
    out = []
    for cl, held in kinds:
        for policy in ("listed", "repairing"):
            one = chain.lump(cl, policy)
            fall, rise, _ = kernel.step_profile(cl, policy)
            alone = kernel.hitting_time(cl, policy)[0]
            for n in sizes:
                if n <= held:
                    whole, least = chain.lumped_hitting(one, n)
                    out.append((policy, n, round(whole, 6), round(n * alone, 6), round(least[1], 6), round(split.gap_bound([(fall, rise)] * n)[2], 6)))
    return spark.createDataFrame(out, "policy string, n long, whole_steps double, component_steps double, last_component_steps double, log2_bound double")
