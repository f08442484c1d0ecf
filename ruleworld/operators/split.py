"""Packing of components into loads, bounded splitting of large ones, and estimates that choose between splits."""

from __future__ import annotations

import math
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ruleworld.operators.rank import running_total
from ruleworld.sources.scratch import settle

PIECES = "aid bigint, comp bigint, piece bigint"
#: Atoms and literals of a component that one task splits; larger ones are cut into blocks first.
TASK_SIZE = 2_000_000


def first_fit(sizes: list[tuple[int, int]], capacity: int) -> list[tuple[int, int]]:
    """``(key, bin)`` by first-fit decreasing; what is larger than the capacity gets a bin of its own."""
    room: list[int] = []
    out = []
    for key, size in sorted(sizes, key=lambda kv: (-kv[1], kv[0])):
        at = next((k for k, r in enumerate(room) if r >= size), None) if size <= capacity else None
        if at is None:
            at = len(room)
            room.append(max(0, capacity - size))
        else:
            room[at] -= size
        out.append((key, at))
    return out


def fill_classes(counts: list[tuple[int, int]], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """First-fit decreasing on ``(size, how many)``: runs ``(size, from, to, first bin, per bin)`` of places in a size class.

    Place p of a run lies in bin ``first + (p - from) div per``. Bins of like content are one entry, so work and result
    follow the number of classes, not of components or bins.
    """
    groups: list[list[int]] = []  # first bin, bins, room of each
    out, bins = [], 0
    for size, many in sorted(counts, reverse=True):
        done = 0
        for g in list(groups):
            first, n, room = g
            fits = room // size if size else many
            if done == many or not fits:
                continue
            k = min(many - done, fits * n)
            full, rest = divmod(k, fits)
            out.append((size, done, done + k, first, fits))
            done += k
            g[1], g[2] = full, room - fits * size
            if rest:
                groups.append([first + full, 1, room - rest * size])
            groups.append([first + full + bool(rest), n - full - bool(rest), room])
            groups[:] = sorted((x for x in groups if x[1]), key=lambda x: x[0])
        per = max(1, capacity // size) if size else max(1, many)
        if done < many:
            full, rest = divmod(many - done, per)
            out.append((size, done, many, bins, per))
            groups += [g for g in ([bins, full, max(0, capacity - per * size)], [bins + full, int(rest > 0), max(0, capacity - rest * size)]) if g[1]]
            bins += full + (rest > 0)
    return out


def pack_components(sizes: DataFrame, capacity: int) -> DataFrame:
    """``comp, size, bin`` for a table ``comp, size``. The driver sees the number of components of each size only."""
    counts = [(r["size"], r["n"]) for r in sizes.groupBy("size").agg(F.count("*").alias("n")).collect()]
    runs = fill_classes(counts, capacity)
    plan = sizes.sparkSession.createDataFrame(runs, "p_size long, lo long, hi long, first long, per long")
    plan = F.broadcast(plan) if len(runs) <= 100_000 else plan
    placed = running_total(sizes.select("comp", "size"), ["size", "comp"], F.lit(1).cast("long"), "place", within=["size"])
    place = F.col("place") - 1
    joined = placed.join(plan, (F.col("size") == F.col("p_size")) & (place >= F.col("lo")) & (place < F.col("hi")))
    return joined.select("comp", "size", (F.col("first") + F.floor((place - F.col("lo")) / F.col("per"))).cast("long").alias("bin"))


def bin_stats(packed: DataFrame, capacity: int) -> DataFrame:
    """``loads, lower_bound, overfull, fill`` of ``comp, size, bin``: overfull are loads of several components above the capacity."""
    loads = packed.groupBy("bin").agg(F.sum("size").alias("size"), F.count("*").alias("n"))
    over = F.count_if((F.col("size") > capacity) & (F.col("n") > 1))
    fill = F.round(F.avg(F.least(F.col("size") / capacity, F.lit(1.0))), 6)
    return loads.agg(F.count("*").alias("loads"), F.ceil(F.coalesce(F.sum("size"), F.lit(0)) / capacity).cast("long").alias("lower_bound"), over.alias("overfull"), fill.alias("fill"))


# Splitting -----------------------------------------------------------------------------------------------------------


def plain_size(atoms: int, literals: int) -> int:
    return atoms + literals


def split_rows(rows: list[tuple[int, list[int], float, bool]], beta: float | None, size: Callable[[int, int], float] = plain_size) -> dict[int, int]:
    """Pieces of one component: clauses ``(cid, lits, weight, is_hard)`` in falling weight, hard ones first, are accepted
    while the group they make stays within ``beta`` by ``size``, any function of atoms and literals that grows with both;
    others are skipped. A piece is named by its least atom."""
    up: dict[int, int] = {}
    held: dict[int, tuple[int, int]] = {}

    def find(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for _, lits, _, _ in rows:
        for x in lits:
            if abs(x) not in up:
                up[abs(x)], held[abs(x)] = abs(x), (1, 0)
    for _, lits, _, _ in sorted(rows, key=lambda r: (not r[3], -abs(r[2]), r[0])):
        roots = sorted({find(abs(x)) for x in lits})
        atoms, literals = sum(held[r][0] for r in roots), sum(held[r][1] for r in roots) + len(lits)
        if beta is not None and size(atoms, literals) > beta:
            continue
        for r in roots[1:]:
            up[r] = roots[0]
        held[roots[0]] = atoms, literals
    return {a: find(a) for a in up}


def split_bounded(clauses: DataFrame, comps: DataFrame, beta: float | None, size: Callable[[int, int], float] = plain_size, task_size: int = TASK_SIZE) -> DataFrame:
    """``aid, comp, piece`` for all components.

    A component of at most ``task_size`` atoms and literals is split in one task. Larger ones are first cut into blocks
    of that size by ``blocks``, and each block is split in a task of its own; clauses between blocks are skipped. Without
    a bound such a component is one piece.
    """
    from ruleworld.operators.field import component_sizes, literals, with_component

    def run(t: pa.Table) -> pa.Table:
        rows = list(zip(*(t.column(c).to_pylist() for c in ("cid", "lits", "weight", "is_hard")), strict=True))
        piece = sorted(split_rows(rows, beta, size).items())
        return pa.table({"aid": pa.array([a for a, _ in piece], pa.int64()), "comp": pa.array([t.column("comp")[0].as_py()] * len(piece), pa.int64()), "piece": pa.array([p for _, p in piece], pa.int64())})

    sized = component_sizes(clauses, comps).select("comp", (F.col("atoms") + F.col("literals") > task_size).alias("large"))
    rows = settle(with_component(clauses, comps).join(sized, "comp").select("comp", "cid", "lits", "weight", "is_hard", "large"))
    small = rows.filter("NOT large").drop("large").withColumn("unit", F.col("comp"))
    large = rows.filter("large").drop("large")
    if large.isEmpty():
        return small.groupBy("unit").applyInArrow(run, PIECES)
    if beta is None:
        whole = comps.join(sized.filter("large").select("comp"), "comp", "left_semi").select("aid", "comp", F.col("comp").alias("piece"))
        return small.groupBy("unit").applyInArrow(run, PIECES).unionByName(whole)
    block = settle(blocks(large, task_size))
    ends = literals(large).join(block, "aid").groupBy("cid").agg(F.min("block").alias("unit"), F.max("block").alias("other"))
    inner = large.join(ends.filter("unit = other").select("cid", "unit"), "cid").select("comp", "cid", "lits", "weight", "is_hard", "unit")
    split = settle(small.unionByName(inner).groupBy("unit").applyInArrow(run, PIECES))
    # atoms of large components that no clause inside a block holds are pieces of their own
    own = block.join(comps, "aid").join(split.select("aid"), "aid", "left_anti").select("aid", "comp", F.col("aid").alias("piece"))
    return split.unionByName(own)


def cuts_as_due(clauses: DataFrame, comps: DataFrame, pieces: DataFrame, beta: float) -> DataFrame:
    """``as_due``, one row: clauses are cut in every component of more atoms than ``beta``, and in none whose atoms and literals are within it."""
    from ruleworld.operators.field import component_sizes, literals

    ends = literals(clauses).join(pieces.select("aid", "comp", "piece"), "aid").groupBy("comp", "cid").agg((F.min("piece") != F.max("piece")).alias("cut"))
    told = component_sizes(clauses, comps).join(ends.groupBy("comp").agg(F.bool_or("cut").alias("cut")), "comp")
    wrong = F.when(F.col("cut"), F.col("atoms") + F.col("literals") <= beta).otherwise(F.col("atoms") > beta)
    return told.agg((F.count_if(wrong) == 0).alias("as_due"))


def blocks(clauses: DataFrame, limit: int, rounds: int = 60) -> DataFrame:
    """``aid, block``: groups of atoms of at most ``limit`` (atoms and their literals), grown along the heaviest clauses.

    Each round every block takes the heaviest clause that joins it to others and whose blocks fit together; blocks that
    throw tails go over to one of that clause's that threw heads, heaviest first while there is room. Clauses that fit no more never
    will, for blocks only grow. A round is some shuffles of the clauses left; their number falls as blocks merge.
    """
    lit = clauses.select("cid", F.explode("lits").alias("x")).select("cid", F.abs("x").alias("aid"))
    place = settle(lit.groupBy("aid").agg((F.count("*") + 1).alias("size")).select("aid", F.col("aid").alias("block"), "size"))
    size = place.select("block", "size")
    key = F.struct("is_hard", F.abs("weight").alias("w"), (-F.col("cid")).alias("c"))
    open_ = settle(lit.join(place, "aid").select("cid", "block").distinct().join(clauses.select("cid", key.alias("key")), "cid"))
    idle = 0
    for turn in range(rounds):
        whole = open_.join(size, "block")
        fit = whole.groupBy("cid").agg(F.sum("size").alias("total"), F.count("*").alias("n")).filter((F.col("n") > 1) & (F.col("total") <= limit))
        open_ = settle(open_.join(fit.select("cid"), "cid", "left_semi"))
        if open_.isEmpty():
            break
        heads = F.pmod(F.xxhash64("block", F.lit(turn)), F.lit(2)) == 0
        best = open_.groupBy("block").agg(F.max("key").alias("key"), F.max_by("cid", "key").alias("cid"))
        target = open_.filter(heads).groupBy("cid").agg(F.min("block").alias("to"))
        moving = best.filter(~heads).join(target, "cid").join(size, "block").select("block", "to", "key", "size")
        order = Window.partitionBy("to").orderBy(F.desc("key"), "block").rowsBetween(Window.unboundedPreceding, 0)
        room = size.select(F.col("block").alias("to"), F.col("size").alias("has"))
        moved = settle(moving.withColumn("sum", F.sum("size").over(order)).join(room, "to").filter(F.col("sum") + F.col("has") <= limit).select("block", "to"))
        if moved.isEmpty():
            idle += 1
            if idle == 6:
                break
            continue
        idle = 0
        go = F.coalesce("to", "block").alias("block")
        place = settle(place.join(moved, "block", "left").select("aid", go, "size"))
        size = settle(place.groupBy("block").agg(F.sum("size").alias("size")))
        open_ = open_.join(moved, "block", "left").select("cid", go, "key").distinct()
    return place.select("aid", "block")


def colour(links: list[tuple[int, int]], nodes: list[int]) -> dict[int, int]:
    """Greedy colours, nodes of many links first: linked nodes differ."""
    near: dict[int, set[int]] = {n: set() for n in nodes}
    for a, b in links:
        near[a].add(b)
        near[b].add(a)
    out: dict[int, int] = {}
    for n in sorted(nodes, key=lambda n: (-len(near[n]), n)):
        used = {out[m] for m in near[n] if m in out}
        out[n] = next(k for k in range(len(nodes) + 1) if k not in used)
    return out


def colours(nodes: DataFrame, links: DataFrame, rounds: int = 200) -> DataFrame:
    """``node, colour`` of the table ``node``, linked nodes (``u, v``) differing; nothing leaves the executors.

    Each round the nodes whose hash is above that of all their uncoloured neighbours take the least colour no neighbour has.
    """
    both = settle(links.select("u", "v").unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v"))).filter("u <> v").distinct())
    rank = lambda c: F.struct(F.xxhash64(c), F.col(c))
    done = nodes.join(both, nodes["node"] == both["u"], "left_anti").select("node", F.lit(0).alias("colour"))
    left = settle(both.select(F.col("u").alias("node")).distinct())
    for _ in range(rounds):
        if left.isEmpty():
            return done
        open_ = both.join(left.select(F.col("node").alias("v")), "v", "left_semi")
        above = open_.filter(rank("v") > rank("u")).select(F.col("u").alias("node")).distinct()
        now = left.join(above, "node", "left_anti")
        taken = both.join(done.select(F.col("node").alias("v"), "colour"), "v").groupBy(F.col("u").alias("node")).agg(F.collect_set("colour").alias("taken"))
        taken = now.join(taken, "node", "left").withColumn("taken", F.coalesce("taken", F.array().cast("array<int>")))
        free = F.array_min(F.array_except(F.sequence(F.lit(0), F.size("taken")), "taken"))
        chosen = settle(taken.select("node", free.cast("int").alias("colour")))
        done = settle(done.unionByName(chosen))
        left = settle(left.join(chosen, "node", "left_anti"))
    raise RuntimeError(f"nodes are left without a colour after {rounds} rounds")


# Estimates -----------------------------------------------------------------------------------------------------------


def beta_from_budget(budget: int, bytes_each: int = 64) -> int:
    """Atoms and literals that a memory budget in bytes holds."""
    return max(1, budget // bytes_each)


def partition_benefit(n: int, t: int, cut: int, edges: int) -> tuple[float, float]:
    """What splitting gains and loses: log2 of 2^(n/3), and t * cut / edges."""
    return n / 3, t * cut / max(1, edges)


def benefit_columns(n: Column, t: Column, cut: Column, edges: Column) -> tuple[Column, Column]:
    """``partition_benefit`` of a table's columns."""
    return n / 3, t * cut / F.greatest(F.lit(1), edges)


def benefit_sign(n: int, t: int, cut: int, edges: int) -> bool:
    """Whether the gain is above the loss, compared in logarithms."""
    gain, loss = partition_benefit(n, t, cut, edges)
    return loss <= 0 or gain > math.log2(loss)


def choose_beta(clauses: DataFrame, comps: DataFrame, betas: list[float | None], sweeps: int = 3, rule: str = "estimate", size: Callable[[int, int], float] = plain_size) -> tuple[float | None, DataFrame]:
    """The best of several size bounds, and what was measured for each: ``beta, pieces, cut_clauses, log2_gain, log2_loss``.

    ``estimate`` takes the largest gain over loss, in logarithms, and no bound where none of the bounds gains. That is
    conservative, for it looks at the worst case of the cut; ``aggressive`` takes the bound with most pieces whose
    largest piece still holds a clause.
    """
    from ruleworld.operators.field import cut_stats

    if rule not in ("estimate", "aggressive"):
        raise ValueError(f"rule is 'estimate' or 'aggressive', not {rule!r}")
    rows = []
    for beta in betas:
        pieces = settle(split_bounded(clauses, comps, beta, size))
        cut, n = cut_stats(clauses, pieces).first(), pieces.select("piece").distinct().count()
        gain, loss = partition_benefit(n, sweeps, cut.cut_clauses, cut.clauses)
        rows.append((None if beta is None else float(beta), n, cut.cut_clauses, gain, math.log2(max(loss, 1e-9)) if cut.cut_clauses else -math.inf, cut.cut_clauses < cut.clauses))
    table = clauses.sparkSession.createDataFrame([r[:5] for r in rows], "beta double, pieces long, cut_clauses long, log2_gain double, log2_loss double")
    if rule == "aggressive":
        able = [r for r in rows if r[5]]
        return (max(able, key=lambda r: r[1])[0] if able else None), table
    able = [r for r in rows if r[3] > r[4]]
    return (max(able, key=lambda r: (r[3] - max(r[4], 0.0), -(r[0] or math.inf)))[0] if able else None), table


def gap_bound(profiles: list[tuple[float, float]]) -> tuple[int, float, float]:
    """``(h, r, log2 of the steps saved)``: the best set H of components by thresholds on their profiles (a, b)."""
    best = (0, 0.0, 0.0)
    for top in sorted({a for a, _ in profiles}):
        rest = sorted((b for a, b in profiles if a <= top), reverse=True)
        for h, b in enumerate(rest, 1):
            r = b / top if top else 0.0
            if h >= 2 and r > 0 and (gain := h * r / (2 + r)) > best[2]:
                best = (h, r, gain)
    return best


def example_gap(n: int) -> float:
    """log2 of the binomial coefficient (n - 1 over n / 2)."""
    return (math.lgamma(n) - math.lgamma(n // 2 + 1) - math.lgamma(n - n // 2)) / math.log(2)


def flip_ceiling(latency: float) -> float:
    """Flips a second when each needs one random access of ``latency`` seconds."""
    return 1 / latency


def speedup(serial: float, parallel: float, fixed: float = 0.0) -> float:
    """Ratio of two run times, net of what both spend beforehand (grounding and partitioning)."""
    if min(serial, parallel) <= fixed:
        raise ValueError("a run cannot take less than its fixed part")
    return (serial - fixed) / (parallel - fixed)


def phase_share(seconds: dict[str, float]) -> dict[str, float]:
    """Share of each phase in the whole run."""
    whole = sum(seconds.values())
    return {k: v / whole if whole else 0.0 for k, v in seconds.items()}


def min_bisection(edges: list[tuple[int, int]], nodes: list[int]) -> int:
    """Least number of edges between equal halves, by trying all; for at most 16 nodes."""
    from itertools import combinations

    if len(nodes) > 16:
        raise ValueError("too many nodes to try all halves")
    return min(sum((a in side) != (b in side) for a, b in edges) for side in map(set, combinations(nodes, len(nodes) // 2)))
