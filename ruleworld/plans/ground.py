"""Bottom-up grounding: every rule is one relational query over atom tables; Catalyst plans it.

Atom tables hold ``a1..an, truth`` (1 true, 0 false, -1 unknown, never null); those of open predicates also ``aid``,
dense over all open predicates in the order of (predicate, arguments). A clause is an array of signed atom ids. What
evidence decides is left out of the clauses and kept as constants, so costs stay absolute.
"""

from __future__ import annotations

import json
from contextlib import contextmanager
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleworld.operators.rank import running_total
from ruleworld.plans.program import Clause, Literal, Predicate, Program, ProgramError, Term
from ruleworld.sources.scratch import settle

CLAUSE = "rule string, lits array<bigint>, weight double, is_hard boolean, state string"


class EvidenceError(ValueError):
    """Evidence that contradicts itself or the program."""


@dataclass
class Atoms:
    """Tables by predicate."""

    program: Program
    tables: dict[str, DataFrame] = field(default_factory=dict)
    rows: dict[str, int] = field(default_factory=dict)  # of open predicates, where they were counted

    def open_rows(self) -> DataFrame:
        """``aid, pred, args, truth`` of all open predicates, arguments as one string."""
        parts = [t.select("aid", F.lit(n).alias("pred"), F.concat_ws(",", *self.program.predicates[n].columns).alias("args"), "truth") for n, t in sorted(self.tables.items()) if "aid" in t.columns]
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out


def evidence_rows(p: Predicate, given: DataFrame) -> DataFrame:
    """Evidence in the columns of atom tables; rows without a ``truth`` column are true."""
    args = [c for c in given.columns if c != "truth"]
    if len(args) != len(p.args):
        raise EvidenceError(f"{p.name} takes {len(p.args)} arguments; its evidence has {args}")
    cols = [F.col(c).cast(kind).alias(a) for c, (_, kind), a in zip(args, p.args, p.columns, strict=True)]
    return given.select(*cols, F.col("truth").cast("tinyint") if "truth" in given.columns else F.lit(1).cast("tinyint").alias("truth"))


def load_atoms(program: Program, evidence: dict[str, DataFrame]) -> Atoms:
    """Atom tables from evidence: for closed predicates the true rows; for open ones candidates with a ``truth`` column."""
    atoms, base = Atoms(program), 0
    for name, p in sorted(program.predicates.items()):
        if name not in evidence:
            raise EvidenceError(f"no evidence for {name}")
        rows = evidence_rows(p, evidence[name])
        if not p.open:
            atoms.tables[name] = rows.filter("truth = 1").distinct()
            continue
        single = rows.groupBy(*p.columns).agg(F.max("truth").alias("truth"), F.min(F.when(F.col("truth") >= 0, F.col("truth"))).alias("low"))
        numbered = settle(running_total(single, p.columns, F.lit(1).cast("long"), "aid"))
        told = numbered.agg(F.count("*").alias("n"), F.count_if((F.col("truth") == 1) & (F.col("low") == 0)).alias("clash"), F.count_if(sum((F.col(c).isNull().cast("int") for c in p.columns), F.lit(0)) > 0).alias("nulls")).first()
        if told.clash or told.nulls:
            raise EvidenceError(f"{name}: {told.clash} rows are both true and false, {told.nulls} have a null argument")
        atoms.tables[name] = numbered.select(*p.columns, "truth", (F.col("aid") + base).cast("long").alias("aid"))
        atoms.rows[name] = told.n
        base += told.n
    return atoms


def query_atoms(domains: list[DataFrame], evidence: DataFrame | None = None) -> DataFrame:
    """Candidates of an open predicate: the product of one-column domains, with the truth that evidence gives."""
    out = domains[0].distinct()
    for d in domains[1:]:
        out = out.join(d.distinct())  # the grounding domain is a product by definition
    if evidence is None:
        return out.withColumn("truth", F.lit(-1).cast("tinyint"))
    return out.join(evidence, out.columns, "left").withColumn("truth", F.coalesce(F.col("truth").cast("tinyint"), F.lit(-1).cast("tinyint")))


# One clause ---------------------------------------------------------------------------------------------------------


def _constants(x: Literal, columns: list[str]) -> Column:
    cond = F.lit(True)
    seen: dict[str, str] = {}
    for t, c in zip(x.terms, columns, strict=True):
        if not t.variable:
            cond = cond & (F.col(c) == F.lit(t.value))
        elif t.value in seen:
            cond = cond & (F.col(c) == F.col(seen[t.value]))
        else:
            seen[t.value] = c
    return cond


def literal_scan(atoms: Atoms, x: Literal, k: int, weight: float, prune: bool = True) -> DataFrame:
    """Rows of a literal that leave the clause undecided: columns for its variables, ``t{k}`` truth and ``l{k}`` signed id."""
    p = atoms.program.predicates[x.pred]
    rows = atoms.tables[x.pred].filter(_constants(x, p.columns))
    if p.open and weight > 0 and prune:
        rows = rows.filter(F.col("truth") != (1 if x.positive else 0))
    names = {}
    for t, c in zip(x.terms, p.columns, strict=True):
        if t.variable:
            names.setdefault(t.value, c)
    out = [F.col(c).alias(f"v_{v}") for v, c in names.items()]
    if p.open:
        truth = F.col("truth") if x.positive else F.when(F.col("truth") >= 0, 1 - F.col("truth")).otherwise(-1)
        out += [truth.cast("tinyint").alias(f"t{k}"), (F.col("aid") if x.positive else -F.col("aid")).alias(f"l{k}")]
    return rows.select(*out)


def _value(t: Term) -> Column:
    return F.col(f"v_{t.value}") if t.variable else F.lit(t.value)


#: Cells that nested loops deal rows to by the values that must be equal; a row is compared with all rows of its cell.
CELLS = 4096


def _cells(left: DataFrame, right: DataFrame, shared: list[str]) -> Column | None:
    """That two rows are in one cell; None if no shared column is of a type that surely has one hash for equal values."""
    kinds = dict(left.dtypes), dict(right.dtypes)
    same = [c for c in shared if kinds[0][c] == kinds[1][f"_{c}"] and kinds[0][c] in ("tinyint", "smallint", "int", "bigint", "string", "date", "boolean")]
    if not same:
        return None
    here, there = (F.pmod(F.xxhash64(*[F.col(f"{mark}{c}") for c in same]), F.lit(CELLS).cast("long")) for mark in ("", "_"))
    return here == there


def _join(left: DataFrame | None, right: DataFrame, lesion: str) -> DataFrame:
    if left is None:
        return right
    if lesion in ("merge", "broadcast", "shuffle_hash"):
        right = right.hint(lesion)
    shared = [c for c in left.columns if c in right.columns and c.startswith("v_")]
    if lesion == "nested_loop":
        right = right.select(*[F.col(c).alias(f"_{c}") if c in shared else F.col(c) for c in right.columns])
        cells = _cells(left, right, shared)
        right = right.hint("shuffle_replicate_nl" if cells is None else "merge")
        cond = F.lit(True) if cells is None else cells
        for c in shared:
            cond = cond & (F.col(c) <= F.col(f"_{c}")) & (F.col(c) >= F.col(f"_{c}"))
        return left.join(right, cond).drop(*[f"_{c}" for c in shared])
    return left.join(right, shared) if shared else left.crossJoin(right)


#: Rows that a task makes by a join that is dealt out, about; tasks of such a join at most; rows of a side that it broadcasts.
DEALT_ROWS, DEALT_TASKS, DEALT_SIDE = 400_000, 4_000, 500_000


def _bushy(scans: list[DataFrame]) -> DataFrame:
    """The join of three literals or more, two sides at a time, those first that make least by counts of rows and of values.

    A join that makes more rows than it reads is dealt to tasks by what it makes, not by the bytes it reads: the larger side by
    number with the other broadcast, so that frequent values spread too, or, above ``DEALT_SIDE`` rows, both by their values. What
    such a join makes is not shuffled to meet a side of up to ``BROADCAST_ATOMS`` rows.
    """
    shared = lambda a, b: [v for v in a if v in b and v.startswith("v_")]
    counts = [s.agg(F.count("*").alias("n"), *[F.approx_count_distinct(v).alias(v) for v in s.columns if v.startswith("v_")]) for s in scans]
    told = [json.loads(r.j) for r in _stacked([c.select(F.lit(k).alias("k"), F.to_json(F.struct("*")).alias("j")) for k, c in enumerate(counts)]).orderBy("k").collect()]
    sides = [(s, float(x.pop("n")), {v: float(max(n, 1)) for v, n in x.items()}, 0) for s, x in zip(scans, told, strict=True)]

    def made(a, b) -> float:
        n = a[1] * b[1]
        for v in shared(a[2], b[2]):
            n /= max(a[2][v], b[2][v])
        return n

    while len(sides) > 1:
        _, _, i, j = min((not shared(sides[i][2], sides[j][2]), made(sides[i], sides[j]), i, j) for j in range(len(sides)) for i in range(j))
        a, b = sides[i], sides[j]
        on, n = shared(a[2], b[2]), made(a, b)
        few, many = sorted((a, b), key=lambda x: x[1])
        left, right = many[0], few[0]
        grows = n > max(DEALT_ROWS, many[1])
        made_of = max(many[3], few[3])  # 0 a literal, 1 a join, 2 one that grew
        if grows and made_of < 2:
            tasks = int(min(DEALT_TASKS, max(n / DEALT_ROWS, 4 * left.sparkSession.sparkContext.defaultParallelism)))
            if few[1] <= DEALT_SIDE or not on:
                left, right = left.repartition(tasks), F.broadcast(right) if few[1] <= BROADCAST_ATOMS else right
            else:
                left, right = left.repartition(tasks, *on), right.repartition(tasks, *on)
        elif made_of and few[1] <= BROADCAST_ATOMS:
            right = F.broadcast(right)
        whole = left.join(right, on) if on else left.crossJoin(right)
        values = {v: max(1.0, min(a[2].get(v, n), b[2].get(v, n), n)) for v in {**a[2], **b[2]}}
        sides = [s for k, s in enumerate(sides) if k not in (i, j)] + [(whole, n, values, 2 if grows else max(1, made_of))]
    return sides[0][0]


def _stacked(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


#: Rules of one shape up to which their constants are a broadcast table.
SHAPE_RULES = 100_000
#: Atoms of a predicate that the third and later literals of a rule broadcast (some 100 bytes each).
BROADCAST_ATOMS = 2_000_000
_RULE, _WEIGHT = "k_rule", "k_weight"


def _shape(c: Clause) -> tuple:
    """What rules have in common that differ in name, constants of literals and size of weight only."""
    lits = tuple((x.pred, x.positive, tuple((t.value, True) if t.variable else (type(t.value).__name__, False) for t in x.terms)) for x in c.literals)
    return lits, c.equals, c.exists, c.hard, c.weight > 0


def rule_groups(clauses: list[Clause]) -> list[list[Clause]]:
    """Rules of one shape together, in the order of their first."""
    groups: dict[tuple, list[Clause]] = {}
    for c in clauses:
        groups.setdefault(_shape(c), []).append(c)
    return list(groups.values())


def ground_shape(atoms: Atoms, rules: list[Clause], lesion: str = "none") -> DataFrame:
    """Instances of several rules of one shape by one plan: their constants are a small table that the literals join.

    So the number of scans follows the number of shapes, not of rules. Shapes without a constant in a literal that lists
    values (an open or a body one) are ground rule by rule.
    """
    first, preds = rules[0], atoms.program.predicates
    names: dict[tuple[int, int], str] = {}
    listed = False
    for k, x in enumerate(first.literals):
        for j, t in enumerate(x.terms):
            if not t.variable:
                names[k, j] = f"k{k}_{j}"
                listed = listed or (preds[x.pred].open or not x.positive) and not x.variables() & first.exists
    if len(rules) == 1 or not listed:
        out = ground_rule(atoms, rules[0], lesion)
        for c in rules[1:]:
            out = out.unionByName(ground_rule(atoms, c, lesion))
        return out
    kinds = [preds[first.literals[k].pred].args[j][1] for k, j in names]
    rows = [(c.id, float(c.weight), *(c.literals[k].terms[j].value for k, j in names)) for c in rules]
    spark = next(iter(atoms.tables.values())).sparkSession
    texts = spark.createDataFrame([(r[0], r[1], *map(str, r[2:])) for r in rows], ", ".join([f"{_RULE} string", f"{_WEIGHT} double", *[f"v_{n} string" for n in names.values()]]))
    table = texts.select(_RULE, _WEIGHT, *[F.col(f"v_{n}").cast(kind).alias(f"v_{n}") for n, kind in zip(names.values(), kinds, strict=True)])
    literals = tuple(replace(x, terms=tuple(Term(names[k, j], True) if (k, j) in names else t for j, t in enumerate(x.terms))) for k, x in enumerate(first.literals))
    return ground_rule(atoms, replace(first, literals=literals), lesion, constants=F.broadcast(table) if len(rules) <= SHAPE_RULES and lesion == "none" else table)


def ground_rule(atoms: Atoms, c: Clause, lesion: str = "none", constants: DataFrame | None = None, prune: bool = True) -> DataFrame:
    """Undecided instances of a clause, one row each, as ``CLAUSE``; ``state`` is free, lost or won (with weight under zero).

    ``constants`` binds variables of the clause by rule (columns ``k_rule``, ``k_weight``, ``v_...``). Without ``prune``
    instances that evidence satisfies are rows too, with state won.
    """
    spark = next(iter(atoms.tables.values())).sparkSession
    preds = atoms.program.predicates
    now, lits, guards, wit, joined, scans = constants, [], [], [], 0, []
    rule, weight = (F.col(_RULE), F.col(_WEIGHT)) if constants is not None else (F.lit(c.id), F.lit(float(c.weight)))
    named = [rule.alias("rule"), weight.alias("weight")]
    for k, x in enumerate(c.literals):
        if x.variables() & c.exists:
            wit.append((k, x))
        elif not preds[x.pred].open and x.positive:
            guards.append((k, x))
        else:
            right = literal_scan(atoms, x, k, c.weight, prune)
            scans.append(right)
            if joined > 1 and lesion == "none" and atoms.rows.get(x.pred, BROADCAST_ATOMS + 1) <= BROADCAST_ATOMS:
                right = F.broadcast(right)  # what two literals make is larger than a literal, and is not shuffled
            now, joined = _join(now, right, lesion), joined + 1
            if preds[x.pred].open:
                lits.append(k)
    if constants is None and lesion == "none" and len(scans) > 2:
        now = _bushy(scans)
    if now is None:
        if c.weight < 0 or not (guards or wit):
            raise ProgramError(f"{c.id}: nothing to ground")
        now = spark.range(1).select(F.lit(1).alias("v__one"))
    won = F.lit(False)
    for e in c.equals:
        same = _value(e.left) == _value(e.right)
        met = same if e.positive else ~same
        if c.weight > 0 and prune:
            now = now.filter(~met)
        else:
            won = won | met
    for k, x in guards:
        p = preds[x.pred]
        true = atoms.tables[x.pred].filter(_constants(x, p.columns))
        keys = {t.value: col for t, col in zip(x.terms, p.columns, strict=True) if t.variable}
        true = true.select(*[F.col(col).alias(f"v_{v}") for v, col in keys.items()]).distinct()
        right, cond = _looped(true, [f"v_{v}" for v in keys], lesion)
        if c.weight > 0 and prune:
            now = now.join(right, cond, "left_anti")
        else:
            now = now.join(right.withColumn(f"g{k}", F.lit(True)), cond, "left")
            won = won | F.coalesce(F.col(f"g{k}"), F.lit(False))
    array = F.array(*[F.when(F.col(f"t{k}") == -1, F.col(f"l{k}")) for k in lits]).cast("array<bigint>") if lits else F.array().cast("array<bigint>")
    for k in lits:
        won = won | (F.col(f"t{k}") == 1)
    if wit:
        now = _witnessed(atoms, c, now, wit, prune)
        if not prune:
            won = won | F.col("w_met")
        array = F.concat(array, F.coalesce("w_ids", F.array().cast("array<bigint>")))
    if 0 < len(lits) <= INLINE_LITERALS and not wit:
        out = _inlined(now, named, lits, won, c.hard)
    else:
        free = F.array_distinct(F.array_compact(array))
        body = now.select(*named, free.alias("f"), won.alias("won"))
        clash = F.exists("f", lambda x: F.array_contains("f", -x))
        state = F.when(F.col("won") | clash, "won").when(F.size("f") == 0, "lost").otherwise("free")
        ordered = F.array_sort("f", lambda a, b: F.when(F.abs(a) < F.abs(b), -1).when(F.abs(a) > F.abs(b), 1).otherwise(0))
        out = body.select("rule", ordered.alias("lits"), "weight", F.lit(c.hard).alias("is_hard"), state.alias("state"))
    if c.hard and c.weight < 0:  # must be false: every free literal's negation is a hard unit
        units = out.filter("state = 'free'").select("rule", F.explode("lits").alias("x"), F.lit(1.0).alias("weight"), "is_hard", "state")
        units = units.select("rule", F.array(-F.col("x")).alias("lits"), "weight", "is_hard", "state")
        bad = out.filter("state = 'won'").select("rule", F.array().cast("array<bigint>").alias("lits"), F.lit(1.0).alias("weight"), "is_hard", F.lit("lost").alias("state"))
        return units.unionByName(bad)
    return out


#: Open literals of a rule up to which its instances are put in order without functions on arrays' elements, which Spark interprets.
INLINE_LITERALS = 4
_KNOWN = 1 << 62


#: Places that are compared and exchanged in turn to sort so many values.
_EXCHANGES = {1: [], 2: [(0, 1)], 3: [(0, 1), (1, 2), (0, 1)], 4: [(0, 1), (2, 3), (0, 2), (1, 3), (1, 2)]}


def _inlined(now: DataFrame, named: list[Column], lits: list[int], won: Column, hard: bool) -> DataFrame:
    """Instances as ``CLAUSE``: unknown literals as ``2 * atom + (1 if positive)``, sorted, told apart by place, and signed again.

    The state follows from the unsorted numbers, so a filter on it, which Spark moves below, neither sorts nor makes arrays.
    """
    n, one = len(lits), F.lit(1).cast("long")
    coded = [F.when(F.col(f"t{k}") == -1, F.abs(F.col(f"l{k}")) * 2 + (F.col(f"l{k}") > 0).cast("long")).otherwise(F.lit(_KNOWN)).alias(f"c{i}") for i, k in enumerate(lits)]
    known, clash = F.lit(True), F.lit(False)
    for i in range(n):
        known = known & (F.col(f"c{i}") == _KNOWN)
        for j in range(i):
            clash = clash | (F.col(f"c{i}").bitwiseXOR(one) == F.col(f"c{j}"))
    state = F.when(F.col("won") | clash, "won").when(known, "lost").otherwise("free")
    body = now.select(*named, *coded, won.alias("won")).select("rule", "weight", state.alias("state"), *[f"c{i}" for i in range(n)])
    for i, j in _EXCHANGES[n]:
        body = body.select("rule", "weight", "state", *[{i: F.least, j: F.greatest}[k](f"c{i}", f"c{j}").alias(f"c{k}") if k in (i, j) else F.col(f"c{k}") for k in range(n)])
    signed = []
    for k in range(n):
        x = F.col(f"c{k}")
        gone = x == _KNOWN if not k else (x == _KNOWN) | (x == F.col(f"c{k - 1}"))
        atom = F.shiftright(x, 1)
        signed.append(F.when(gone, F.lit(0).cast("long")).when(x.bitwiseAND(one) == 1, atom).otherwise(-atom))
    free = F.array_remove(F.array(*signed), F.lit(0).cast("long"))
    return body.select("rule", free.alias("lits"), "weight", F.lit(hard).alias("is_hard"), "state")


def _looped(right: DataFrame, keys: list[str], lesion: str):
    """The right side and condition of a guard's join; without equal keys where only nested loops are allowed."""
    if lesion != "nested_loop" or not keys:
        return right, keys
    right = right.select(*[F.col(c).alias(f"_{c}") if c in keys else F.col(c) for c in right.columns])
    cond = F.lit(True)
    for c in keys:
        cond = cond & (F.col(c) <= F.col(f"_{c}")) & (F.col(c) >= F.col(f"_{c}"))
    return right, cond


def _witnessed(atoms: Atoms, c: Clause, now: DataFrame, wit: list[tuple[int, Literal]], prune: bool = True) -> DataFrame:
    """One row an outer binding, with the ids of unknown witnesses; bindings with a true witness go, or are marked ``w_met``."""
    now = now if prune else now.withColumn("w_met", F.lit(False))
    for k, x in wit:
        p = atoms.program.predicates[x.pred]
        rows = atoms.tables[x.pred].filter(_constants(x, p.columns))
        keys = {t.value: col for t, col in zip(x.terms, p.columns, strict=True) if t.variable and t.value not in c.exists}
        ids = F.col("aid") if p.open else F.lit(None).cast("long")
        rows = rows.select(*[F.col(col).alias(f"v_{v}") for v, col in keys.items()], "truth", ids.alias("w"))
        found = rows.groupBy(*[f"v_{v}" for v in keys]).agg(F.max(F.col("truth") == 1).alias("met"), F.array_sort(F.collect_list(F.when(F.col("truth") == -1, F.col("w")))).alias(f"w{k}"))
        now = now.join(found, [f"v_{v}" for v in keys], "left") if keys else now.crossJoin(found)
        now = now.filter(~F.coalesce("met", F.lit(False))).drop("met") if prune else now.withColumn("w_met", F.col("w_met") | F.coalesce("met", F.lit(False))).drop("met")
        ids = F.coalesce(f"w{k}", F.array().cast("array<bigint>"))
        now = now.withColumn("w_ids", F.concat("w_ids", ids) if "w_ids" in now.columns else ids)
    return now


# Programs ------------------------------------------------------------------------------------------------------------

#: Session settings that take a strategy away from the optimizer.
LESIONS = {
    "order": {"spark.sql.optimizer.excludedRules": "org.apache.spark.sql.catalyst.optimizer.ReorderJoin,org.apache.spark.sql.catalyst.optimizer.CostBasedJoinReorder"},
    "no_pushdown": {
        "spark.sql.optimizer.excludedRules": ",".join(f"org.apache.spark.sql.catalyst.optimizer.{r}" for r in ("PushDownPredicates", "PushPredicateThroughJoin", "PushPredicateThroughNonJoin", "CombineFilters")),
        "spark.sql.parquet.filterPushdown": "false",
    },
}


@contextmanager
def lesioned(spark: SparkSession, lesion: str):
    """Settings of a lesion, for plans that run inside."""
    put = LESIONS.get(lesion, {})
    was = {k: spark.conf.get(k, None) for k in put}
    try:
        for k, v in put.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in was.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


@dataclass
class Field:
    """Ground clauses over open atoms, and what evidence decided."""

    atoms: Atoms
    clauses: DataFrame  # cid, rule, lits, weight, is_hard, multiplicity
    constants: DataFrame  # rule, constant_cost, hard_contradictions


def ground_raw(program: Program, atoms: Atoms, lesion: str = "none") -> DataFrame:
    """Undecided, lost and won instances of all rules, before merging; one plan for the rules of each shape."""
    parts = [ground_shape(atoms, rules, lesion) for rules in rule_groups(program.clauses)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def canonicalise(raw: DataFrame) -> DataFrame:
    """Equal clauses of a rule merged: weights added, instances counted. Signs and hard rules stay apart."""
    free = raw.filter("state = 'free'")
    merged = free.groupBy("rule", "lits", "is_hard", (F.col("weight") > 0).alias("up")).agg(F.sum("weight").alias("weight"), F.count("*").alias("multiplicity"))
    return merged.select("rule", "lits", F.when(F.col("is_hard"), F.lit(1.0)).otherwise(F.col("weight")).alias("weight"), "is_hard", "multiplicity")


def constants_of(raw: DataFrame) -> DataFrame:
    """Cost by rule that no world avoids, and the number of hard instances that evidence breaks."""
    costs = ((F.col("state") == "lost") & (F.col("weight") > 0)) | ((F.col("state") == "won") & (F.col("weight") < 0))
    return raw.filter(costs).groupBy("rule").agg(F.sum(F.when(F.col("is_hard"), 0.0).otherwise(F.abs("weight"))).alias("constant_cost"), F.sum(F.col("is_hard").cast("long")).alias("hard_contradictions"))


def ground(program: Program, evidence: dict[str, DataFrame], lesion: str = "none", merge: bool = True) -> Field:
    """Atoms, clauses with dense ids in the order of (rule, literals), and constants."""
    atoms = load_atoms(program, evidence)
    spark = next(iter(atoms.tables.values())).sparkSession
    with lesioned(spark, lesion):
        raw = settle(ground_raw(program, atoms, lesion))
    clauses = canonicalise(raw) if merge else raw.filter("state = 'free'").select("rule", "lits", "weight", "is_hard", F.lit(1).cast("long").alias("multiplicity"))
    numbered = settle(running_total(clauses, ["rule", "lits", "is_hard", "weight"], F.lit(1).cast("long"), "cid"))
    return Field(atoms, numbered.select("cid", "rule", "lits", "weight", "is_hard", "multiplicity"), settle(constants_of(raw)))


def active_closure(clauses: DataFrame, rounds: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Active clauses and atoms: a clause is active if some setting of the active atoms, all others false, violates it.

    ``rounds`` looks ahead so many times beyond the clauses that are active from the start; None goes to the fixpoint.
    Each round is one join with the atoms of the round before.
    """
    literal = clauses.select("cid", "weight", F.explode("lits").alias("x")).select("cid", "weight", F.abs("x").alias("aid"), (F.col("x") > 0).alias("up"))
    literal = settle(literal)
    spark = clauses.sparkSession
    active, was, done = spark.createDataFrame([], "aid bigint"), 0, 0
    while True:
        now = literal.join(active.withColumn("on", F.lit(True)), "aid", "left")
        on = F.coalesce("on", F.lit(False))
        blocked = F.max(~F.col("up") & ~on)  # a negative literal of an inactive atom is true
        moved = F.max(~F.col("up") | on)
        chosen = now.groupBy("cid").agg(F.first("weight").alias("weight"), blocked.alias("blocked"), moved.alias("moved"))
        chosen = settle(chosen.filter(F.when(F.col("weight") > 0, ~F.col("blocked")).otherwise(F.col("moved"))).select("cid"))
        active = settle(literal.join(chosen, "cid").select("aid").distinct())
        n = active.count()
        if n == was or rounds is not None and done >= rounds:
            return clauses.join(chosen, "cid", "left_semi"), active
        was, done = n, done + 1


def rule_sql(program: Program, c: Clause) -> str:
    """The rule's query over tables named as the predicates, as SQL text (rules of positive weight without witnesses)."""
    frm, where, lits, first = [], [], [], {}
    for k, x in enumerate(c.literals):
        p = program.predicates[x.pred]
        if not p.open and x.positive:
            cond = [f"n.{col} = {first[t.value] if t.variable else _sql(t.value)}" for t, col in zip(x.terms, p.columns, strict=True)]
            where.append(f"NOT EXISTS (SELECT 1 FROM {x.pred} n WHERE {' AND '.join(cond)})")
            continue
        frm.append(f"{x.pred} x{k}")
        for t, col in zip(x.terms, p.columns, strict=True):
            here = f"x{k}.{col}"
            if not t.variable:
                where.append(f"{here} = {_sql(t.value)}")
            elif t.value in first:
                where.append(f"{here} = {first[t.value]}")
            else:
                first[t.value] = here
        if p.open:
            where.append(f"x{k}.truth <> {1 if x.positive else 0}")
            lits.append(f"CASE WHEN x{k}.truth = -1 THEN {'' if x.positive else '-'}x{k}.aid END")
    for e in c.equals:
        a, b = (first[t.value] if t.variable else _sql(t.value) for t in (e.left, e.right))
        where.append(f"{a} {'<>' if e.positive else '='} {b}")
    return f"SELECT array_compact(array({', '.join(lits)})) AS lits\nFROM {', '.join(frm)}\nWHERE {' AND '.join(where) or 'true'}"


def explain_grounding(program: Program, atoms: Atoms, c: Clause) -> str:
    """The rule's query as SQL text (where it has one) and the plan that Catalyst makes of its grounding."""
    text = rule_sql(program, c) if c.weight > 0 and not c.exists else "(no SQL text: a rule of negative weight or with witnesses)"
    run = ground_rule(atoms, c)._jdf.queryExecution()
    return f"{text}\n\n{run.explainString(_formatted(atoms))}"


def _formatted(atoms: Atoms):
    """Spark's formatted explain mode."""
    spark = next(iter(atoms.tables.values())).sparkSession
    return spark._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted")


def _sql(v) -> str:
    return "'" + v.replace("'", "''") + "'" if isinstance(v, str) else str(v).lower() if isinstance(v, bool) else str(v)
