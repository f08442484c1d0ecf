"""Measures and views of a ground field: costs, flips, degrees, components, cuts."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.operators.connect import connect


def literals(clauses: DataFrame) -> DataFrame:
    """``cid, aid, positive``, one row a literal."""
    return clauses.select("cid", F.explode("lits").alias("x")).select("cid", F.abs("x").alias("aid"), (F.col("x") > 0).alias("positive"))


def constant_world(clauses: DataFrame, value: bool) -> DataFrame:
    return literals(clauses).select("aid").distinct().withColumn("value", F.lit(value))


def judged(clauses: DataFrame, world: DataFrame) -> DataFrame:
    """Every clause with ``n_true`` literals and whether the world violates it; atoms not in the world are false."""
    hit = literals(clauses).join(world.select("aid", "value"), "aid", "left")
    true = F.coalesce(F.col("value"), F.lit(False)) == F.col("positive")
    counts = hit.groupBy("cid").agg(F.count_if(true).alias("n_true"))
    return clauses.join(counts, "cid").withColumn("violated", F.when(F.col("weight") > 0, F.col("n_true") == 0).otherwise(F.col("n_true") > 0))


def violated(clauses: DataFrame, world: DataFrame) -> DataFrame:
    return judged(clauses, world).filter("violated")


def _costs():
    soft = F.coalesce(F.sum(F.when(~F.col("is_hard"), F.abs("weight"))), F.lit(0.0))
    return F.coalesce(F.sum(F.when(F.col("is_hard"), F.col("multiplicity"))), F.lit(0)).cast("long").alias("hard"), soft.alias("soft")


def world_cost(field, world: DataFrame) -> DataFrame:
    """``hard, soft``: violated hard clauses, and the cost including what evidence decided."""
    own = violated(field.clauses, world).agg(*_costs())
    base = field.constants.agg(F.coalesce(F.sum("hard_contradictions"), F.lit(0)).alias("h"), F.coalesce(F.sum("constant_cost"), F.lit(0.0)).alias("s"))
    return own.crossJoin(base).select((F.col("hard") + F.col("h")).alias("hard"), (F.col("soft") + F.col("s")).alias("soft"))


def cost_by_rule(field, world: DataFrame) -> DataFrame:
    """``rule, hard, soft`` without constants, and the total under the null rule."""
    return violated(field.clauses, world).rollup("rule").agg(*_costs())


def log_odds(field, a: DataFrame, b: DataFrame) -> DataFrame:
    """How much more likely, in logarithm, world a is than world b."""
    x, y = world_cost(field, a).select(F.col("soft").alias("sa")), world_cost(field, b).select(F.col("soft").alias("sb"))
    return x.crossJoin(y).select((F.col("sb") - F.col("sa")).alias("log_odds"))


def flip_delta(clauses: DataFrame, world: DataFrame) -> DataFrame:
    """Per atom: soft cost that a flip makes and breaks, and their difference; hard clauses likewise as counts."""
    state = judged(clauses, world).select("cid", "weight", "is_hard", "multiplicity", "n_true", "violated")
    lit = literals(clauses).join(world.select("aid", "value"), "aid", "left")
    lit = lit.withColumn("true", F.coalesce(F.col("value"), F.lit(False)) == F.col("positive")).join(state, "cid")
    after = F.when(F.col("true"), F.col("n_true") - 1).otherwise(F.col("n_true") + 1)
    bad = F.when(F.col("weight") > 0, after == 0).otherwise(after > 0)
    cost = F.when(F.col("is_hard"), 0.0).otherwise(F.abs("weight"))
    hard = F.when(F.col("is_hard"), F.col("multiplicity")).otherwise(0)
    turn = [(bad & ~F.col("violated"), "make"), (~bad & F.col("violated"), "mend")]
    out = lit.groupBy("aid").agg(*[F.sum(F.when(c, cost).otherwise(0.0)).alias(n) for c, n in turn], *[F.sum(F.when(c, hard).otherwise(0)).cast("long").alias(f"hard_{n}") for c, n in turn])
    return out.withColumn("delta", F.col("make") - F.col("mend")).withColumn("hard_delta", F.col("hard_make") - F.col("hard_mend"))


def why(clauses: DataFrame, world: DataFrame, aid: int) -> DataFrame:
    """Clauses that touch an atom, and whether the world violates them."""
    return judged(clauses.filter(F.exists("lits", lambda x: F.abs(x) == aid)), world)


def diff_worlds(a: DataFrame, b: DataFrame) -> DataFrame:
    joined = a.select("aid", F.col("value").alias("before")).join(b.select("aid", F.col("value").alias("after")), "aid", "full")
    return joined.filter(~F.col("before").eqNullSafe(F.col("after")))


def degrees(clauses: DataFrame) -> DataFrame:
    lit = literals(clauses)
    size = lit.groupBy("cid").agg(F.count("*").alias("n"))
    return lit.join(size, "cid").groupBy("aid").agg(F.count("*").alias("clauses"), F.sum(F.col("n") - 1).alias("links"))


def atom_links(clauses: DataFrame) -> DataFrame:
    """Each clause's first atom with each other one: enough to connect it."""
    first = F.abs(F.element_at("lits", 1))
    return clauses.filter(F.size("lits") > 1).select(first.alias("u"), F.explode(F.slice("lits", 2, F.size("lits") - 1)).alias("x")).select("u", F.abs("x").alias("v"))


def components(clauses: DataFrame) -> DataFrame:
    """``aid, comp`` for all atoms in clauses; the component's name is its least atom."""
    roots = connect(atom_links(clauses))
    every = literals(clauses).select("aid").distinct()
    return every.join(roots.select(F.col("node").alias("aid"), "root"), "aid", "left").select("aid", F.coalesce("root", "aid").alias("comp"))


def components_local(links: list[tuple[int, int]]) -> dict[int, int]:
    """The same by union-find in one process, for small fields and as a check."""
    up: dict[int, int] = {}

    def find(x):
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {x: find(x) for x in up}


def component_sizes(clauses: DataFrame, comps: DataFrame) -> DataFrame:
    """``comp, atoms, clauses, literals``."""
    atoms = comps.groupBy("comp").agg(F.count("*").alias("atoms"))
    own = with_component(clauses, comps).groupBy("comp").agg(F.count("*").alias("clauses"), F.sum(F.size("lits")).alias("literals"))
    return atoms.join(own, "comp")


def with_component(clauses: DataFrame, comps: DataFrame) -> DataFrame:
    first = clauses.withColumn("aid", F.abs(F.element_at("lits", 1)))
    return first.join(comps, "aid").drop("aid")


def component_histogram(comps: DataFrame) -> DataFrame:
    return comps.groupBy("comp").agg(F.count("*").alias("atoms")).groupBy("atoms").agg(F.count("*").alias("components"))


def query_field(clauses: DataFrame, wanted: DataFrame) -> DataFrame:
    """The smallest sub-field that a query needs: clauses reachable from its atoms (column ``aid``)."""
    comps = components(clauses)
    reached = comps.join(comps.join(wanted.select("aid"), "aid", "left_semi").select("comp").distinct(), "comp", "left_semi")
    return clauses.withColumn("aid", F.abs(F.element_at("lits", 1))).join(reached.select("aid"), "aid", "left_semi").drop("aid")


def cut(clauses: DataFrame, pieces: DataFrame) -> DataFrame:
    """Clauses that touch more than one piece."""
    spread = literals(clauses).join(pieces.select("aid", "piece"), "aid").groupBy("cid").agg(F.countDistinct("piece").alias("n_pieces"))
    return clauses.join(spread.filter("n_pieces > 1"), "cid")


def cut_stats(clauses: DataFrame, pieces: DataFrame) -> DataFrame:
    every = clauses.agg(F.count("*").alias("clauses"))
    crossing = cut(clauses, pieces).agg(F.count("*").alias("cut_clauses"), F.coalesce(F.sum(F.abs("weight")), F.lit(0.0)).alias("cut_weight"))
    return crossing.crossJoin(every).withColumn("cut_share", F.round(F.col("cut_clauses") / F.col("clauses"), 6))


def home_pieces(clauses: DataFrame, pieces: DataFrame) -> DataFrame:
    """``cid, home_piece, is_cut``: a clause lives with its least atom."""
    home = clauses.select("cid", F.abs(F.element_at("lits", 1)).alias("aid")).join(pieces, "aid").select("cid", F.col("piece").alias("home_piece"))
    return home.join(cut(clauses, pieces).select("cid", F.lit(True).alias("c")), "cid", "left").select("cid", "home_piece", F.coalesce("c", F.lit(False)).alias("is_cut"))


def piece_stats(clauses: DataFrame, pieces: DataFrame) -> DataFrame:
    """Atoms and literals by piece, of clauses inside it and of all clauses that live there, and the ratio to the mean."""
    atoms = pieces.groupBy("piece").agg(F.count("*").alias("atoms"))
    own = home_pieces(clauses, pieces).join(clauses.select("cid", F.size("lits").alias("n")), "cid")
    sums = own.groupBy(F.col("home_piece").alias("piece")).agg(F.sum(F.when(~F.col("is_cut"), F.col("n")).otherwise(0)).alias("inner"), F.sum("n").alias("assigned"))
    sized = atoms.join(sums, "piece", "left").select("piece", "atoms", (F.col("atoms") + F.coalesce("inner", F.lit(0))).alias("size"), (F.col("atoms") + F.coalesce("assigned", F.lit(0))).alias("assigned_size"))
    mean = sized.agg(F.avg("size").alias("mean"))
    return sized.crossJoin(F.broadcast(mean)).withColumn("balance", F.col("size") / F.col("mean")).drop("mean")


def memory(clauses: DataFrame, comps: DataFrame, raw: DataFrame | None = None) -> DataFrame:
    """Bytes, by formula: the clause table, the search of the whole field and of its largest component, and, given
    instances before merging (``raw``), what a solver that grounds in memory holds at once.

    A literal takes 8 bytes in the table; in a search 16 and an atom 40, a clause 64.
    """
    sizes = component_sizes(clauses, comps)
    held = F.col("atoms") * 40 + F.col("clauses") * 64 + F.col("literals") * 16
    out = sizes.agg(*[F.coalesce(x, F.lit(0)).cast("long").alias(n) for x, n in ((F.sum(F.col("literals") * 8 + F.col("clauses") * 33), "clause_bytes"), (F.sum(held), "whole_bytes"), (F.max(held), "largest_bytes"))])
    if raw is None:
        return out
    peak = raw.agg(F.coalesce(F.sum(F.size("lits") * 16 + 64), F.lit(0)).cast("long").alias("instance_bytes"))
    return out.crossJoin(peak).withColumn("in_memory_peak_bytes", F.col("instance_bytes") + F.col("whole_bytes"))


def program_stats(program, atoms) -> dict[str, int]:
    """Relations, rules, distinct values by argument domain, rows that evidence decides, and unknown atoms."""
    opened = [t for t in atoms.tables.values() if "aid" in t.columns]
    values: dict[str, list[DataFrame]] = {}
    for name, p in program.predicates.items():
        for (domain, _), c in zip(p.args, p.columns, strict=True):
            values.setdefault(domain, []).append(atoms.tables[name].select(F.col(c).cast("string").alias("v")))
    return {
        "entities": sum(reduce(DataFrame.unionByName, parts).distinct().count() for parts in values.values()),
        "relations": len(program.predicates),
        "rules": len(program.clauses),
        "evidence": sum(t.filter("truth <> -1").count() for t in atoms.tables.values()),
        "query_atoms": sum(t.filter("truth = -1").count() for t in opened),
    }


def check_field(clauses: DataFrame) -> DataFrame:
    """Counts of rows that break the form of a clause table; all are zero in a sound one."""
    lits = F.col("lits")
    return clauses.agg(
        F.count_if(F.size(lits) == 0).alias("empty"),
        F.count_if(F.exists(lits, lambda x: x == 0)).alias("zero"),
        F.count_if(F.exists(lits, lambda x: F.array_contains(lits, -x))).alias("tautologies"),
        F.count_if(F.size(F.array_distinct(F.transform(lits, lambda x: F.abs(x)))) < F.size(lits)).alias("repeated"),
        F.count_if(F.isnan("weight") | F.col("weight").isNull()).alias("weights"),
        (F.coalesce(F.max("cid"), F.lit(0)) - F.count("*")).alias("gaps"),
    )
