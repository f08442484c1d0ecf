"""From a field to its cheapest world: path choice, component-wise search, splitting with alternating search, sampling.

Clauses travel to tasks by bin (a load of components within a size); tasks return worlds and costs. Nothing here
collects atoms or clauses; the driver sees counts by component size, colours of pieces, and costs.
"""

from __future__ import annotations

import json
import time
import zlib
from collections import Counter
from dataclasses import dataclass, field
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ruleworld.operators import kernel, split
from ruleworld.operators import field as views
from ruleworld.operators.rank import running_total
from ruleworld.plans.ground import Field, ground
from ruleworld.plans.program import Program
from ruleworld.sources.scratch import settle

WORLD = "comp bigint, aid bigint, value boolean"
FOUND = "comp bigint, aid bigint, value boolean, hard bigint, soft double, flips bigint, tries bigint, ms double"


def _seed(comp: int, seed: int, turn: int = 0) -> int:
    return zlib.crc32(f"{comp},{seed},{turn}".encode())


def _by_unit(t: pa.Table, unit: str):
    """Clauses of each unit of a group, in a fixed order."""
    rows: dict[int, list] = {}
    for u, cid, *r in zip(*(t.column(c).to_pylist() for c in (unit, "cid", "lits", "weight", "is_hard", "multiplicity")), strict=True):
        rows.setdefault(u, []).append((cid, tuple(r)))
    for u in sorted(rows):
        yield u, [r for _, r in sorted(rows[u], key=lambda x: x[0])]


def _table(rows: list[tuple], schema: str) -> pa.Table:
    kinds = {"bigint": pa.int64(), "double": pa.float64(), "boolean": pa.bool_()}
    names = [x.split() for x in schema.split(", ")]
    cols = list(zip(*rows, strict=True)) or [[]] * len(names)
    return pa.table({n: pa.array(c, kinds[k]) for (n, k), c in zip(names, cols, strict=True)})


def budgets(sizes: DataFrame, total: int) -> DataFrame:
    """``comp, atoms, flips``: flips in proportion to atoms, at least one each."""
    whole = sizes.agg(F.sum("atoms").alias("all"))
    return sizes.crossJoin(F.broadcast(whole)).select("comp", "atoms", F.greatest(F.lit(1), F.ceil(F.lit(total) * F.col("atoms") / F.col("all"))).cast("long").alias("flips"))


def binned(clauses: DataFrame, comps: DataFrame, **loading) -> DataFrame:
    """Clauses with ``comp``, ``bin`` and the component's ``flips``; ``loading`` as in ``loads``."""
    bins, share = loads(clauses, comps, **loading)
    return views.with_component(clauses, comps).join(bins, "comp").join(share, "comp")


def loads(clauses: DataFrame, comps: DataFrame, packing: str = "ffd", capacity: int = 20_000, budget: str = "weighted", total: int = 10**6, flips: int = 10**4) -> tuple[DataFrame, DataFrame]:
    """``comp, bin`` and ``comp, flips``. ``packing``: ``ffd`` loads, or ``single``, a load a component."""
    if packing not in ("ffd", "single"):
        raise ValueError(f"packing is 'ffd' or 'single', not {packing!r}")
    sizes = settle(views.component_sizes(clauses, comps).withColumn("size", F.col("atoms") + F.col("literals")))
    if packing == "ffd":
        bins = split.pack_components(sizes.select("comp", "size"), capacity).select("comp", "bin")
    else:
        bins = sizes.select("comp", F.col("comp").alias("bin"))
    share = budgets(sizes, total).select("comp", "flips") if budget == "weighted" else sizes.select("comp", F.lit(flips).cast("long").alias("flips"))
    return bins, share


#: Tasks that loads are dealt to at least, where workers are not given.
LOAD_TASKS = 64
LOAD = ["bin", "comp", "flips", "cid", "lits", "weight", "is_hard", "multiplicity"]


def by_load(rows: DataFrame, run, schema: str, parallel: int | None = None) -> DataFrame:
    """``run`` on the clauses of each load. ``parallel`` workers take turns at the loads, one in memory at a time; None: as many as there are."""
    rows = rows.select(*LOAD)
    if parallel is None:  # dealt by number, for walks are long and their clauses few bytes
        tasks = max(LOAD_TASKS, 4 * rows.sparkSession.sparkContext.defaultParallelism)
        return rows.repartition(tasks, "bin").groupBy("bin").applyInArrow(run, schema)

    def stream(batches):
        held: list[pa.RecordBatch] = []
        for b in batches:
            bins = b.column(0).to_numpy()
            edges = [0, *(np.flatnonzero(bins[1:] != bins[:-1]) + 1).tolist(), len(bins)]
            for i, j in zip(edges[:-1], edges[1:], strict=True):
                if i == j:
                    continue
                if held and held[-1].column(0)[0].as_py() != bins[i]:
                    yield from run(pa.Table.from_batches(held)).to_batches()
                    held = []
                held.append(b.slice(i, j - i))
        if held:
            yield from run(pa.Table.from_batches(held)).to_batches()

    return rows.repartition(parallel, "bin").sortWithinPartitions("bin").mapInArrow(stream, schema)


def _target(cl: kernel.Clauses, prove: bool) -> tuple[int, float] | None:
    return kernel.least_cost(cl) if prove else None


#: Flips of all tries of a component from which on each try is a load of its own.
APART = 500_000
TRY = "comp bigint, turn bigint, world array<struct<aid: bigint, value: boolean>>, hard bigint, soft double, flips bigint, ms double, ended boolean"


def _tries_apart(rows: DataFrame, tries: int, noise: float, policy: str, seed: int, prove: bool) -> DataFrame:
    """``FOUND`` of components whose tries run in tasks of their own: the best of the tries up to the one that ended the search."""
    each = rows.withColumn("turn", F.explode(F.sequence(F.lit(0), F.lit(tries - 1)))).withColumn("bin", F.col("comp") * tries + F.col("turn"))

    def run(t: pa.Table) -> pa.Table:
        (comp, clauses), = _by_unit(t, "comp")
        cl, turn = kernel.Clauses.build(clauses), t.column("bin")[0].as_py() % tries
        w = kernel.walk(cl, t.column("flips")[0].as_py(), tries, noise, policy, _seed(comp, seed), target=_target(cl, prove), only=turn)
        world = pa.StructArray.from_arrays([pa.array(cl.ids, pa.int64()), pa.array([bool(v) for v in w.world], pa.bool_())], ["aid", "value"])
        one = {"comp": [comp], "turn": [turn], "world": pa.ListArray.from_arrays(pa.array([0, len(cl.ids)], pa.int32()), world), "hard": [w.hard], "soft": [w.soft], "flips": [w.flips], "ms": [w.ms], "ended": [w.ended]}
        return pa.table({k: v if isinstance(v, pa.Array) else pa.array(v, {"soft": pa.float64(), "ms": pa.float64(), "ended": pa.bool_()}.get(k, pa.int64())) for k, v in one.items()})

    told = by_load(each, run, TRY)
    last = F.min(F.when(F.col("ended"), F.col("turn")))
    best = told.groupBy("comp").agg(F.min_by("world", F.struct("hard", "soft", "turn")).alias("world"), F.min(F.struct("hard", "soft")).alias("cost"), F.coalesce(last, F.lit(tries - 1)).alias("last"), F.collect_list(F.struct("turn", "flips", "ms")).alias("made"))
    made = F.filter("made", lambda x: x["turn"] <= F.col("last"))
    summed = [F.aggregate(made.getField(c), F.lit(0).cast(kind), lambda s, x: s + x).alias(c) for c, kind in (("flips", "long"), ("ms", "double"))]
    out = best.select("comp", "cost", (F.col("last") + 1).cast("long").alias("tries"), *summed, F.explode("world").alias("x"))
    return out.select("comp", "x.aid", "x.value", "cost.hard", "cost.soft", "flips", "tries", "ms")


def search_components(clauses: DataFrame, comps: DataFrame, tries: int = 3, noise: float = 0.5, policy: str = "listed", seed: int = 0, schedule: str = "in_turn", quantum: int = 200, seconds: float | None = None, parallel: int | None = None, prove: bool = False, **loading) -> DataFrame:
    """``FOUND``: the best world of every component, found on its own, with its costs on each row.

    With ``prove`` the walk of a component ends once it has the least cost that elimination proves (``kernel.least_cost``): worlds
    and costs are those of the whole walk, which finds nothing better, with fewer flips.

    ``schedule`` orders the components of a load: ``in_turn`` one after another, ``round_robin`` a ``quantum`` of flips each by
    turns, ``weighted`` a quantum in proportion to atoms. The worlds are the same; under a time limit (``seconds`` a load, or a
    component where they come in turn) round robin gives every component its share of it.

    Where they come in turn and without a time limit, tries of a component with more than ``APART`` flips are loads of their own:
    each draws what it draws after the tries before it, so the result is that of one walk.
    """
    if schedule not in ("in_turn", "round_robin", "weighted"):
        raise ValueError(f"unknown schedule {schedule!r}")

    def run(t: pa.Table) -> pa.Table:
        flips = dict(zip(t.column("comp").to_pylist(), t.column("flips").to_pylist(), strict=True))
        built = [(comp, kernel.Clauses.build(rows)) for comp, rows in _by_unit(t, "comp")]
        if schedule == "in_turn":
            walks = (kernel.walk(cl, flips[comp], tries, noise, policy, _seed(comp, seed), seconds=seconds, target=_target(cl, prove)) for comp, cl in built)
        else:
            turn = [max(1, quantum * (len(cl.ids) if schedule == "weighted" else 1)) for _, cl in built]
            walks = kernel.take_turns([kernel.walking(cl, flips[comp], tries, noise, policy, _seed(comp, seed), quantum=q, target=_target(cl, prove)) for (comp, cl), q in zip(built, turn, strict=True)], seconds)
        out = []
        for (comp, cl), w in zip(built, walks, strict=True):
            out += [(comp, a, bool(v), w.hard, w.soft, w.flips, w.tries, w.ms) for a, v in zip(cl.ids, w.world, strict=True)]
        return _table(out, FOUND)

    bins, share = loads(clauses, comps, **loading)
    rows, long = views.with_component(clauses, comps).join(bins, "comp").join(share, "comp"), F.col("flips") * tries > APART
    if tries < 2 or schedule != "in_turn" or seconds is not None or parallel is not None or share.filter(long).isEmpty():
        return by_load(rows, run, FOUND, parallel)
    return by_load(rows.filter(~long), run, FOUND).unionByName(_tries_apart(rows.filter(long), tries, noise, policy, seed, prove))


TRACE = "comp bigint, try bigint, flip bigint, ms double, hard bigint, soft double"


def trace_components(clauses: DataFrame, comps: DataFrame, tries: int = 3, noise: float = 0.5, policy: str = "listed", seed: int = 0, seconds: float | None = None, prove: bool = False, **loading) -> DataFrame:
    """``TRACE``: each time a component's best cost fell. ``seconds`` stops the search of each component by the clock, ``prove`` as in ``search_components``."""

    def run(t: pa.Table) -> pa.Table:
        flips = dict(zip(t.column("comp").to_pylist(), t.column("flips").to_pylist(), strict=True))
        out = []
        for comp, rows in _by_unit(t, "comp"):
            cl = kernel.Clauses.build(rows)
            w = kernel.walk(cl, flips[comp], tries, noise, policy, _seed(comp, seed), seconds=seconds, target=_target(cl, prove))
            out += [(comp, *x) for x in w.trace]
        return _table(out, TRACE)

    return by_load(binned(clauses, comps, **loading), run, TRACE)


def time_cost_curve(trace: DataFrame, points: int = 100, by: str = "flip", after: float = 0.0) -> DataFrame:
    """``at, hard, soft``: the field's best cost, summed over components, on a grid of at most ``points`` steps of ``by``.

    Components start at their first world's cost. ``after`` is added to ``at`` (grounding time: no cost before it).
    """
    seq = Window.partitionBy("comp").orderBy("try", "flip")
    fall = [(F.col(c) - F.coalesce(F.lag(c).over(seq), F.lit(0))).alias(c) for c in ("hard", "soft")]
    steps = trace.select(F.col(by).cast("double").alias("at"), *fall)
    top = trace.agg(F.max(by).cast("double").alias("top"))
    cell = F.when(F.col("top") > 0, F.ceil(F.col("at") * (points - 1) / F.col("top"))).otherwise(0).cast("int")
    summed = steps.crossJoin(F.broadcast(top)).groupBy(cell.alias("cell"), "top").agg(F.sum("hard").alias("hard"), F.sum("soft").alias("soft"))
    run = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)  # at most ``points`` rows
    at = F.col("cell") * F.col("top") / (points - 1) + after
    return summed.select(at.alias("at"), F.sum("hard").over(run).cast("long").alias("hard"), F.round(F.sum("soft").over(run), 9).alias("soft"))


def search_whole(clauses: DataFrame, comps: DataFrame | None = None, flips: int = 10**5, tries: int = 1, noise: float = 0.5, policy: str = "listed", seed: int = 0) -> DataFrame:
    """One walk over the whole field in one task. With ``comps`` the best state is remembered for each component apart."""
    each = comps is not None
    rows = views.with_component(clauses, comps) if each else clauses.withColumn("comp", F.lit(0).cast("long"))

    def run(t: pa.Table) -> pa.Table:
        names = {abs(x): c for c, lits in zip(t.column("comp").to_pylist(), t.column("lits").to_pylist(), strict=True) for x in lits}
        rows = [r for _, r in sorted(zip(t.column("cid").to_pylist(), zip(*(t.column(c).to_pylist() for c in ("lits", "weight", "is_hard", "multiplicity")), strict=True), strict=True), key=lambda x: x[0])]
        cl = kernel.Clauses.build(rows)
        order = {c: k for k, c in enumerate(sorted(set(names.values())))}
        parts = [order[names[a]] for a in cl.ids] if each else None
        w = kernel.walk(cl, flips, tries, noise, policy, _seed(0, seed), parts=parts)
        return _table([(names[a], a, bool(v), w.hard, w.soft, w.flips, w.tries, w.ms) for a, v in zip(cl.ids, w.world, strict=True)], FOUND)

    return rows.withColumn("bin", F.lit(0)).select("bin", "comp", "cid", "lits", "weight", "is_hard", "multiplicity").groupBy("bin").applyInArrow(run, FOUND)


def enumerate_components(clauses: DataFrame, comps: DataFrame, most: int = 16) -> DataFrame:
    """``comp, atoms, hard, soft, optima`` of every component with at most ``most`` atoms."""
    schema = "comp bigint, atoms bigint, hard bigint, soft double, optima bigint"

    def run(t: pa.Table) -> pa.Table:
        out = []
        for comp, rows in _by_unit(t, "comp"):
            cl = kernel.Clauses.build(rows)
            if len(cl.ids) <= most:
                out.append((comp, len(cl.ids), *kernel.optimum(cl)))
        return _table(out, schema)

    rows = binned(clauses, comps, budget="fixed")
    return rows.select("bin", "comp", "cid", "lits", "weight", "is_hard", "multiplicity").groupBy("bin").applyInArrow(run, schema)


def component_kinds(clauses: DataFrame, comps: DataFrame) -> list[tuple[kernel.Clauses, int]]:
    """The kinds of components, equal but for the atoms' names, and how many there are of each. The driver sees a component a kind."""
    schema = "kind string, n bigint"

    def run(t: pa.Table) -> pa.Table:
        met = Counter()
        for _, rows in _by_unit(t, "comp"):
            cl = kernel.Clauses.build(rows)
            met[json.dumps(sorted(zip(cl.lits, cl.weight, cl.hard, strict=True)))] += 1
        return pa.table({"kind": pa.array(list(met), pa.string()), "n": pa.array(list(met.values()), pa.int64())})

    rows = binned(clauses, comps, budget="fixed")
    told = rows.select("bin", "comp", "cid", "lits", "weight", "is_hard", "multiplicity").groupBy("bin").applyInArrow(run, schema)
    out = []
    for r in told.groupBy("kind").agg(F.sum("n").alias("n")).orderBy("kind").collect():
        lits, weight, hard = map(list, zip(*json.loads(r["kind"]), strict=True))
        out.append((kernel.Clauses(list(range(1, max(x >> 1 for c in lits for x in c) + 2)), lits, weight, hard), r["n"]))
    return out


def marginals(clauses: DataFrame, comps: DataFrame, samples: int = 1000, burn_in: int = 100, seed: int = 0, exact: bool = False, most: int = 16) -> DataFrame:
    """``comp, aid, p, samples, stalls``: by slice sampling, or by enumeration of components of at most ``most`` atoms."""
    schema = "comp bigint, aid bigint, p double, samples bigint, stalls bigint"

    def run(t: pa.Table) -> pa.Table:
        out = []
        for comp, rows in _by_unit(t, "comp"):
            cl = kernel.Clauses.build(rows)
            if exact and len(cl.ids) > most:
                continue
            p, stalls = (kernel.exact_marginals(cl)[0], 0) if exact else kernel.mc_sat(cl, samples, burn_in, _seed(comp, seed))
            out += [(comp, a, float(x), 0 if exact else samples, stalls) for a, x in zip(cl.ids, p, strict=True)]
        return _table(out, schema)

    rows = binned(clauses, comps, budget="fixed")
    return rows.select("bin", "comp", "cid", "lits", "weight", "is_hard", "multiplicity").groupBy("bin").applyInArrow(run, schema)


def marginal_error(got: DataFrame, exact: DataFrame) -> DataFrame:
    joined = got.select("aid", F.col("p").alias("a")).join(exact.select("aid", F.col("p").alias("b")), "aid")
    return joined.agg(F.max(F.abs(F.col("a") - F.col("b"))).alias("max_error"), F.avg(F.abs(F.col("a") - F.col("b"))).alias("mean_error"))


def _none_larger(comps: DataFrame, most: int) -> None:
    n = comps.groupBy("comp").count().agg(F.max("count")).first()[0] or 0
    if n > most:
        raise OverBudget(f"a component has {n} atoms, at most {most} can be enumerated")


def profiles(clauses: DataFrame, comps: DataFrame, policy: str = "listed", most: int = 12) -> DataFrame:
    """``comp, a, b, opt_cost`` of every component. Raises ``OverBudget`` where one has more than ``most`` atoms."""
    _none_larger(comps, most)
    schema = "comp bigint, a double, b double, opt_cost double"

    def run(t: pa.Table) -> pa.Table:
        out = []
        for comp, rows in _by_unit(t, "comp"):
            cl = kernel.Clauses.build(rows)
            out.append((comp, *kernel.step_profile(cl, policy)))
        return _table(out, schema)

    rows = binned(clauses, comps, budget="fixed")
    return rows.select("bin", "comp", "cid", "lits", "weight", "is_hard", "multiplicity").groupBy("bin").applyInArrow(run, schema)


# Pieces --------------------------------------------------------------------------------------------------------------


def residual(clauses: DataFrame, pieces: DataFrame, state: DataFrame, chosen: DataFrame) -> DataFrame:
    """Clauses of the ``chosen`` pieces given all other atoms' values: ``piece, cid, lits, weight, is_hard, multiplicity``.

    What outside atoms satisfy is dropped (weights over zero) or constant (under zero); literals of outside atoms go.
    """
    lit = views.literals(clauses).join(pieces.select("aid", "piece"), "aid").join(state.select("aid", "value"), "aid")
    lit = lit.withColumn("true", F.col("value") == F.col("positive")).withColumn("x", F.when(F.col("positive"), F.col("aid")).otherwise(-F.col("aid")))
    by_piece = lit.groupBy("cid", "piece").agg(F.array_sort(F.collect_list("x")).alias("own"), F.max("true").alias("true"))
    met = by_piece.groupBy("cid").agg(F.count_if("true").alias("true_pieces"))
    open_ = by_piece.join(chosen.select("piece"), "piece", "left_semi").join(met, "cid").filter(F.col("true_pieces") - F.col("true").cast("int") == 0)
    return open_.join(clauses.select("cid", "weight", "is_hard", "multiplicity"), "cid").select("piece", "cid", F.col("own").alias("lits"), "weight", "is_hard", "multiplicity")


def start_state(pieces: DataFrame, seed: int = 0) -> DataFrame:
    return pieces.select("aid", (F.pmod(F.xxhash64("aid", F.lit(seed)), F.lit(2)) == 1).alias("value"))


def piece_colours(clauses: DataFrame, pieces: DataFrame, order: str) -> DataFrame:
    """``piece, colour``: pieces of a colour share no clause; in ``sequential`` order every piece has its own."""
    names = settle(pieces.select(F.col("piece").alias("node")).distinct())
    if order == "sequential":
        return running_total(names, ["node"], F.lit(1).cast("long"), "colour").select(F.col("node").alias("piece"), (F.col("colour") - 1).cast("int").alias("colour"))
    at = settle(views.literals(clauses).join(pieces.select("aid", "piece"), "aid").select("cid", "piece").distinct())
    pair = at.alias("x").join(at.alias("y"), (F.col("x.cid") == F.col("y.cid")) & (F.col("x.piece") < F.col("y.piece")))
    return split.colours(names, pair.select(F.col("x.piece").alias("u"), F.col("y.piece").alias("v")).distinct()).withColumnRenamed("node", "piece")


class Alternation(NamedTuple):
    """A world (``aid, value``), the whole cost after each sweep, first the start's, and the flips made."""

    world: DataFrame
    costs: list[tuple[int, float]]
    flips: int


def alternate(fld: Field, pieces: DataFrame, sweeps: int = 3, flips: int = 2000, order: str = "coloured", noise: float = 0.5, policy: str = "listed", seed: int = 0, total: int | None = None) -> Alternation:
    """Block-alternating search: each piece is searched from its present state given the newest states of the others.

    ``flips`` are those of a piece in a sweep; with a ``total``, pieces and sweeps share that in proportion to atoms
    instead. Each piece's clauses are dealt out once a step and meet the states of their atoms, the piece's and its
    neighbours', in one task by cogroup; no clause is copied for other pieces' atoms. Stops when a sweep gains nothing.
    """
    clauses = fld.clauses
    state = settle(start_state(pieces, seed))
    colours = settle(piece_colours(clauses, pieces, order))
    n = colours.agg(F.max("colour")).first()[0]
    lit = views.literals(clauses).join(pieces.select("aid", "piece"), "aid")
    homes = lit.select("cid", "piece").distinct().join(colours, "piece")
    held = settle(homes.join(clauses.select("cid", "lits", "weight", "is_hard", "multiplicity"), "cid"))
    touch = settle(held.select("piece", "colour", F.explode("lits").alias("x")).select("piece", "colour", F.abs("x").alias("aid")).distinct())
    owner = pieces.select("aid", F.col("piece").alias("owner"))
    share = pieces.groupBy("piece").agg(F.count("*").alias("atoms"))
    if total is None:
        share = share.select("piece", F.lit(flips).cast("long").alias("flips"))
    else:
        every = F.lit(max(1, pieces.count()))
        share = share.select("piece", F.greatest(F.lit(1), F.ceil(F.lit(total / sweeps) * F.col("atoms") / every)).cast("long").alias("flips"))
    share = settle(share)

    def cost(world):
        r = views.world_cost(fld, world).first()
        return int(r.hard), round(float(r.soft), 9)

    costs, made = [cost(state)], 0
    for sweep in range(sweeps):
        for c in range((n if n is not None else -1) + 1):
            mine = held.filter(F.col("colour") == c).join(share, "piece").drop("colour")
            seen = touch.filter(F.col("colour") == c).join(state, "aid").join(owner, "aid").select("piece", "aid", "value", (F.col("owner") == F.col("piece")).alias("own"))
            run = _piece_search(noise, policy, seed, sweep)
            moved = settle(mine.groupBy("piece").cogroup(seen.groupBy("piece")).applyInArrow(run, "piece bigint, aid bigint, new boolean, flips bigint"))
            made += moved.groupBy("piece").agg(F.max("flips").alias("f")).agg(F.coalesce(F.sum("f"), F.lit(0))).first()[0]
            state = settle(state.join(moved.select("aid", "new"), "aid", "left").select("aid", F.coalesce("new", "value").alias("value")))
        costs.append(cost(state))
        if costs[-1] == costs[-2] or costs[-1] == (0, 0.0):
            break
    return Alternation(state, costs, int(made))


def _piece_search(noise: float, policy: str, seed: int, sweep: int):
    """Clauses of a piece and states of their atoms become the piece's new states."""

    def run(mine: pa.Table, seen: pa.Table) -> pa.Table:
        schema = "piece bigint, aid bigint, new boolean, flips bigint"
        if not mine.num_rows or not seen.num_rows:
            return _table([], schema)
        value, own = {}, set()
        for a, v, o in zip(*(seen.column(c).to_pylist() for c in ("aid", "value", "own")), strict=True):
            value[a] = v
            if o:
                own.add(a)
        left = []
        for _, rows in _by_unit(mine, "piece"):
            for lits, weight, hard, many in rows:  # what outside atoms satisfy is constant; literals of outside atoms go
                if not any(value[abs(x)] == (x > 0) for x in lits if abs(x) not in own):
                    left.append((tuple(x for x in lits if abs(x) in own), weight, hard, many))
        piece, flips = mine.column("piece")[0].as_py(), mine.column("flips")[0].as_py()
        if not left:
            return _table([], schema)
        cl = kernel.Clauses.build(left)
        w = kernel.walk(cl, flips, 1, noise, policy, _seed(piece, seed, sweep), start=[value[a] for a in cl.ids])
        return _table([(piece, a, bool(v), w.flips) for a, v in zip(cl.ids, w.world, strict=True)], schema)

    return run


def condition_on(clauses: DataFrame, boundary: list[int], most: int = 16) -> DataFrame:
    """``hard, soft``: the least cost by trying all values of a few boundary atoms and solving what falls apart exactly.

    Raises ``OverBudget`` where a component of more than ``most`` atoms is left.
    """
    spark, best = clauses.sparkSession, None
    every = views.literals(clauses).select("aid").distinct()
    fixed = spark.createDataFrame([(b,) for b in boundary], "aid long")
    inner = every.join(fixed, "aid", "left_anti")
    pieces = inner.select("aid", F.lit(1).cast("long").alias("piece")).unionByName(fixed.select("aid", F.lit(0).cast("long").alias("piece")))
    for setting in range(1 << len(boundary)):
        values = spark.createDataFrame([(b, bool(setting >> k & 1)) for k, b in enumerate(boundary)], "aid long, value boolean")
        state = inner.select("aid", F.lit(False).alias("value")).unionByName(values)
        rest = settle(residual(clauses, pieces, state, spark.createDataFrame([(1,)], "piece long")).drop("piece").withColumn("rule", F.lit("")))
        held = views.judged(clauses, values.unionByName(inner.select("aid", F.lit(False).alias("value"))))
        gone = held.join(rest.select("cid"), "cid", "left_anti").filter("violated").agg(F.coalesce(F.sum(F.when(F.col("is_hard"), F.col("multiplicity"))), F.lit(0)).alias("h"), F.coalesce(F.sum(F.when(~F.col("is_hard"), F.abs("weight"))), F.lit(0.0)).alias("s")).first()
        comps = settle(views.components(rest))
        _none_larger(comps, most)
        inside = enumerate_components(rest, comps, most).agg(F.coalesce(F.sum("hard"), F.lit(0)).alias("h"), F.coalesce(F.sum("soft"), F.lit(0.0)).alias("s")).first()
        cost = (int(gone.h + inside.h), float(gone.s + inside.s))
        best = cost if best is None else min(best, cost)
    return spark.createDataFrame([best], "hard long, soft double")


# Search with table operations alone ----------------------------------------------------------------------------------


def table_walk(clauses: DataFrame, flips: int, noise: float = 0.5, seed: int = 0, clustered: bool = False, keep_every: int = 10) -> tuple[DataFrame, list[tuple[int, float]], float]:
    """The walk as table operations: each flip scans the clauses. World, costs along the way, and flips a second.

    ``clustered`` keeps a second copy of the literals sorted by atom, which each flip's scoring reads.
    """
    spark = clauses.sparkSession
    chance = np.random.default_rng(seed)
    world = settle(views.constant_world(clauses, False))
    lit = views.literals(clauses)
    index = settle(lit.repartition("aid").sortWithinPartitions("aid")) if clustered else lit
    best, best_world, costs, began, done = None, world, [], time.perf_counter(), 0
    flipped: dict[int, bool] = {}
    for step in range(flips + 1):
        changed = spark.createDataFrame(sorted(flipped.items()) or [], "aid long, new boolean")
        now = world.join(F.broadcast(changed), "aid", "left").select("aid", F.coalesce("new", "value").alias("value"))
        bad = views.violated(clauses, now)
        told = bad.agg(F.coalesce(F.sum(F.when(F.col("is_hard"), F.col("multiplicity"))), F.lit(0)).alias("h"), F.coalesce(F.sum(F.when(~F.col("is_hard"), F.abs("weight"))), F.lit(0.0)).alias("s"), F.min_by("lits", F.xxhash64("cid", F.lit(step), F.lit(seed))).alias("lits")).first()
        cost = (int(told.h), round(float(told.s), 9))
        costs.append(cost)
        if best is None or cost < best:
            best, best_world = cost, settle(now)
        if told.lits is None or step == flips:
            break
        atoms = sorted(abs(x) for x in told.lits)
        if len(atoms) > 1 and chance.random() >= noise:
            near = clauses.join(index.filter(F.col("aid").isin(atoms)).select("cid").distinct(), "cid", "left_semi")
            a = views.flip_delta(near, now).filter(F.col("aid").isin(atoms)).orderBy("hard_delta", "delta", "aid").first().aid
        else:
            a = atoms[int(chance.random() * len(atoms))]
        if a in flipped:
            flipped[a] = not flipped[a]
        else:
            flipped[a] = not world.filter(F.col("aid") == a).first().value
        done += 1
        if len(flipped) >= keep_every:
            world, flipped = settle(now.withColumn("value", F.when(F.col("aid") == a, ~F.col("value")).otherwise(F.col("value")))), {}
    return best_world, costs, done / (time.perf_counter() - began)


# Whole runs ----------------------------------------------------------------------------------------------------------


def choose_path(whole: int, largest: int, budget: int, may_split: bool = True) -> str:
    """How to search: ``memory`` (all fits at once), ``components``, ``pieces``, or ``table`` when splitting is off."""
    if whole <= budget:
        return "memory"
    return "components" if largest <= budget else "pieces" if may_split else "table"


class OverBudget(MemoryError):
    """A field that one task of the declared budget cannot hold."""


@dataclass
class MapResult:
    program: Program
    field: Field
    world: DataFrame
    hard: int
    soft: float
    path: str
    seconds: dict[str, float] = field(default_factory=dict)
    flips: int = 0

    def filled(self, pred: str) -> DataFrame:
        """The true rows of an open predicate: evidence, and atoms that the world makes true."""
        t = self.field.atoms.tables[pred]
        true = F.when(F.col("truth") >= 0, F.col("truth") == 1).otherwise(F.coalesce("value", F.lit(False)))
        return t.join(self.world.select("aid", "value"), "aid", "left").filter(true).select(*self.program.predicates[pred].columns)

    def register_views(self) -> None:
        for name, p in self.program.predicates.items():
            (self.filled(name) if p.open else self.field.atoms.tables[name]).createOrReplaceTempView(name)


def solve_map(program: Program, evidence: dict[str, DataFrame], budget: int = 10**7, partition: bool = True, may_split: bool = True, total: int = 10**6, flips_per_atom: int | None = None, tries: int = 3, policy: str = "listed", seed: int = 0, sweeps: int = 3, refuse: bool = False, lesion: str = "none", best: str = "global", **loading) -> MapResult:
    """Ground, choose a path for a budget (atoms + literals that one task may hold), search, and account costs relationally.

    ``total`` flips are shared in proportion to atoms on the paths by component and by piece, the same total on all paths (a
    component or piece gets one a try or sweep at least); ``flips_per_atom`` sets the total by the size of the field. The
    result tells the flips made. ``partition=False`` is the whole-field search; with ``refuse`` it raises
    ``OverBudget`` where the field is too large.
    """
    t0 = time.perf_counter()
    fld = ground(program, evidence, lesion)
    t1 = time.perf_counter()
    comps = settle(views.components(fld.clauses)) if partition or best == "component" else None
    if comps is not None:
        r = views.component_sizes(fld.clauses, comps).agg(F.coalesce(F.sum(F.col("atoms") + F.col("literals")), F.lit(0)).alias("whole"), F.coalesce(F.max(F.col("atoms") + F.col("literals")), F.lit(0)).alias("largest")).first()
        whole, largest = r.whole, r.largest
    else:
        r = fld.clauses.agg(F.coalesce(F.sum(F.size("lits")), F.lit(0)).alias("n")).first()
        whole = largest = r.n + views.literals(fld.clauses).select("aid").distinct().count()
    if not partition:
        if whole > budget and (refuse or not may_split):
            if refuse:
                raise OverBudget(f"the field has size {whole}, the budget is {budget}")
            path = "table"
        else:
            path = "whole"
    else:
        path = choose_path(whole, largest, budget, may_split)
        path = "components" if path == "memory" else path
    t2 = time.perf_counter()
    if flips_per_atom is not None:
        total = max(1, flips_per_atom * views.literals(fld.clauses).select("aid").distinct().count())
    if path == "table":
        world, costs, _ = table_walk(fld.clauses, total, seed=seed)
        flips = len(costs) - 1
    elif path == "pieces":
        pieces = settle(split.split_bounded(fld.clauses, comps, budget))
        world, _, flips = alternate(fld, pieces, sweeps, policy=policy, seed=seed, total=total * tries)
    else:
        found = search_whole(fld.clauses, comps if best == "component" else None, total, tries, policy=policy, seed=seed) if path == "whole" else search_components(fld.clauses, comps, tries, policy=policy, seed=seed, total=total, **loading)
        found = settle(found)
        flips = found.groupBy("comp").agg(F.max("flips").alias("f")).agg(F.sum("f") if path != "whole" else F.max("f")).first()[0] or 0
        world = found.select("aid", "value")
    cost = views.world_cost(fld, world).first()
    t3 = time.perf_counter()
    return MapResult(program, fld, world, int(cost.hard), float(cost.soft), path, {"ground": t1 - t0, "partition": t2 - t1, "search": t3 - t2}, int(flips))
