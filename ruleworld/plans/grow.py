"""Fields that grow: new evidence is folded into a ground field, and only what it touches is ground and searched again.

New truths of known atoms shorten or settle the clauses that hold them. New rows of a relation are joined once in each
place where a rule reads it (places before it read the old rows, places after it all rows), so no old instance is made
again. Rules that read the relation through an anti-join or a witness can lose instances; those are ground anew.
Ids of atoms and clauses stay; new ones follow the largest, so ids may have gaps.
"""

from __future__ import annotations

from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.operators import field as views
from ruleworld.operators.rank import running_total
from ruleworld.plans import ground as g
from ruleworld.plans import solve
from ruleworld.plans.program import Clause, Program
from ruleworld.sources.scratch import settle

SHAPE = ["rule", "lits", "weight", "is_hard", "multiplicity"]


@dataclass
class Grown:
    field: g.Field
    dirty: DataFrame  # aid: atoms whose clauses changed


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _fold(clauses: DataFrame, fresh: DataFrame) -> DataFrame:
    """``clauses`` and ``fresh`` (with ``cid`` or null), equal ones merged. Only clauses that begin with an atom of fresh ones are looked at."""
    head = F.abs(F.element_at("lits", 1))
    heads = settle(fresh.select(head.alias("head")).distinct())
    placed = clauses.withColumn("head", head)
    near, far = (placed.join(heads, "head", how).select("cid", *SHAPE) for how in ("left_semi", "left_anti"))
    merged = near.unionByName(fresh.select("cid", *SHAPE)).groupBy("rule", "lits", "is_hard", (F.col("weight") > 0).alias("up"))
    merged = merged.agg(F.sum("weight").alias("weight"), F.sum("multiplicity").alias("multiplicity"), F.min("cid").alias("cid"))
    merged = settle(merged.withColumn("weight", F.when(F.col("is_hard"), 1.0).otherwise(F.col("weight"))).select("cid", *SHAPE))
    last = clauses.agg(F.coalesce(F.max("cid"), F.lit(0)).alias("n")).first().n
    added = running_total(merged.filter("cid IS NULL").drop("cid"), ["rule", "lits", "is_hard", "weight"], F.lit(1).cast("long"), "cid")
    return settle(_union([far, merged.filter("cid IS NOT NULL"), added.withColumn("cid", F.col("cid") + last).select("cid", *SHAPE)]))


def _add_constants(a: DataFrame, b: DataFrame) -> DataFrame:
    both = a.unionByName(b.select(*a.columns))
    return settle(both.groupBy("rule").agg(F.sum("constant_cost").alias("constant_cost"), F.sum("hard_contradictions").alias("hard_contradictions")))


def condition(fld: g.Field, news: DataFrame) -> Grown:
    """The field once atoms are known: ``news`` has ``aid, truth`` (0 or 1) of atoms unknown so far. Atom tables follow."""
    news = settle(news.select("aid", F.col("truth").cast("tinyint").alias("told")))
    hit = views.literals(fld.clauses).join(news, "aid")
    hit = hit.groupBy("cid").agg(F.max((F.col("told") == 1) == F.col("positive")).alias("won"), F.collect_set("aid").alias("known"))
    rows = fld.clauses.join(hit, "cid").withColumn("lits", F.filter("lits", lambda x: ~F.array_contains("known", F.abs(x))))
    state = F.when(F.col("won"), "won").when(F.size("lits") == 0, "lost").otherwise("free")
    rows = settle(rows.withColumn("state", state).select("cid", *SHAPE, "state"))
    decided = rows.filter("(state = 'lost' AND weight > 0) OR (state = 'won' AND weight < 0)").groupBy("rule")
    decided = decided.agg(F.sum(F.when(F.col("is_hard"), 0.0).otherwise(F.abs("weight"))).alias("constant_cost"), F.sum(F.when(F.col("is_hard"), F.col("multiplicity")).otherwise(0)).alias("hard_contradictions"))
    kept = fld.clauses.join(rows.select("cid"), "cid", "left_anti")
    clauses = _fold(kept, rows.filter("state = 'free'"))
    tables = {}
    for name, t in fld.atoms.tables.items():
        if "aid" in t.columns:
            order = t.columns
            t = settle(t.join(news, "aid", "left").withColumn("truth", F.coalesce("told", "truth")).select(*order))
        tables[name] = t
    dirty = settle(views.literals(rows).select("aid").distinct())
    return Grown(g.Field(g.Atoms(fld.atoms.program, tables), clauses, _add_constants(fld.constants, decided)), dirty)


def _sorted_evidence(fld: g.Field, more: dict[str, DataFrame]) -> tuple[list[DataFrame], dict[str, DataFrame]]:
    """Truths of known atoms (``aid, truth``), and new rows by predicate."""
    news, fresh = [], {}
    opened = [t for t in fld.atoms.tables.values() if "aid" in t.columns]
    last = _union([t.agg(F.max("aid").alias("n")) for t in opened]).agg(F.coalesce(F.max("n"), F.lit(0)).alias("n")).first().n if opened else 0
    for name, given in sorted(more.items()):
        p = fld.atoms.program.predicates[name]
        rows, have = g.evidence_rows(p, given), fld.atoms.tables[name]
        if not p.open:
            fresh[name] = settle(rows.filter("truth = 1").distinct().join(have, p.columns, "left_anti"))
            continue
        single = rows.groupBy(*p.columns).agg(F.max("truth").alias("truth"), F.min(F.when(F.col("truth") >= 0, F.col("truth"))).alias("low"))
        met = settle(single.join(have.withColumnRenamed("truth", "was"), p.columns, "left"))
        clash = (F.col("truth") == 1) & (F.col("low") == 0) | (F.col("was") >= 0) & (F.col("truth") >= 0) & (F.col("was") != F.col("truth"))
        bad = met.agg(F.count_if(clash).alias("clash"), F.count_if(reduce(lambda a, b: a | b, (F.col(c).isNull() for c in p.columns))).alias("nulls")).first()
        if bad.clash or bad.nulls:
            raise g.EvidenceError(f"{name}: {bad.clash} rows are both true and false, {bad.nulls} have a null argument")
        news.append(met.filter("was = -1 AND truth >= 0").select("aid", "truth"))
        new = settle(running_total(met.filter("aid IS NULL").select(*p.columns, "truth"), p.columns, F.lit(1).cast("long"), "aid").withColumn("aid", F.col("aid") + last))
        last += new.count()
        fresh[name] = new
    return news, fresh


def _places(program: Program, c: Clause, grown: set[str]) -> list[int] | None:
    """Literals of a clause that read grown relations by a join; None if one reads them otherwise."""
    out = []
    for k, x in enumerate(c.literals):
        if x.pred in grown:
            if x.variables() & c.exists or x.positive and not program.predicates[x.pred].open:
                return None
            out.append(k)
    return out


def reground(fld: g.Field, more: dict[str, DataFrame]) -> Grown:
    """The field with more evidence, as ``ground`` would make it from all evidence at once but for the ids of new atoms and clauses."""
    program = fld.atoms.program
    news, fresh = _sorted_evidence(fld, more)
    now, dirty = fld, []
    if news:
        step = condition(fld, _union(news))
        now, dirty = step.field, [step.dirty]
    fresh = {n: t for n, t in fresh.items() if not t.isEmpty()}
    if fresh:
        old = now.atoms.tables
        full = old | {n: settle(old[n].unionByName(t.select(*old[n].columns))) for n, t in fresh.items()}
        names = dict(program.predicates)
        tables = dict(full)
        for n, t in fresh.items():
            for mark, rows in (("+", t), ("-", old[n])):
                names[n + mark] = replace(program.predicates[n], name=n + mark)
                tables[n + mark] = rows
        wide = g.Atoms(replace(program, predicates=names), tables)
        parts, anew = [], []
        for c in program.clauses:
            places = _places(program, c, set(fresh))
            if places is None:
                anew.append(c.id)
                parts.append(g.ground_rule(wide, c))
                continue
            for i, k in enumerate(places):
                mark = {k: "+"} | dict.fromkeys(places[:i], "-")
                lits = tuple(replace(x, pred=x.pred + mark.get(j, "")) for j, x in enumerate(c.literals))
                parts.append(g.ground_rule(wide, replace(c, literals=lits)))
        atoms = g.Atoms(program, full)
        if parts:
            raw = settle(_union(parts))
            stale = F.col("rule").isin(anew)
            added = settle(g.canonicalise(raw).withColumn("cid", F.lit(None).cast("long")))
            clauses = _fold(now.clauses.filter(~stale), added)
            dirty += [views.literals(added.withColumn("cid", F.lit(0))).select("aid"), views.literals(now.clauses.filter(stale)).select("aid")]
            now = g.Field(atoms, clauses, _add_constants(now.constants.filter(~stale), g.constants_of(raw)))
        else:
            now = g.Field(atoms, now.clauses, now.constants)
    spark = fld.clauses.sparkSession
    return Grown(now, settle(_union(dirty).distinct()) if dirty else spark.createDataFrame([], "aid bigint"))


def resolve(grown: Grown, world: DataFrame, **how) -> DataFrame:
    """``aid, value``: components with a dirty atom are searched, all others keep the values of ``world``."""
    clauses = grown.field.clauses
    comps = settle(views.components(clauses))
    touched = settle(comps.join(grown.dirty.select("aid"), "aid", "left_semi").select("comp").distinct())
    part = settle(comps.join(touched, "comp", "left_semi").select("aid", "comp"))
    own = settle(views.with_component(clauses, part).drop("comp"))
    found = solve.search_components(own, part, **how).select("aid", "value")
    kept = world.select("aid", "value").join(comps.join(part.select("aid"), "aid", "left_anti"), "aid", "left_semi")
    return settle(kept.unionByName(found))
