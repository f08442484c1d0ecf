"""Groups of entities that rules can tie together, found on the evidence before any grounding.

An atom belongs to the entities among its arguments. Every component of the ground field lies in one group, so groups can
be ground and searched apart.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.operators.connect import connect
from ruleworld.plans.ground import evidence_rows
from ruleworld.plans.program import Program, ProgramError

NODE = "domain string, entity string"


def _keys(program: Program, x, domains: set[str]) -> list[int]:
    return [k for k, (d, _) in enumerate(program.predicates[x.pred].args) if d in domains]


def binding_predicates(program: Program, domains: set[str]) -> set[str]:
    """Relations whose rows tie entities: those that rules with several ground atoms join.

    Raises ``ProgramError`` for a rule whose atoms no entity holds together; such a rule ties everything to everything.
    """
    out = set()
    for c in program.clauses:
        joined = [x for x in c.literals if program.predicates[x.pred].open or not x.positive]
        atoms = [x for x in joined if program.predicates[x.pred].open]
        if len(atoms) < 2 and not any(x.variables() & c.exists for x in atoms):
            continue
        shared = {id(x): {x.terms[k].value for k in _keys(program, x, domains) if x.terms[k].variable and x.terms[k].value not in c.exists} for x in joined}
        reached, todo = set(), [atoms[0]]
        while todo:
            x = todo.pop()
            reached.add(id(x))
            todo += [y for y in joined if id(y) not in reached and shared[id(x)] & shared[id(y)]]
        if any(id(x) not in reached or not shared[id(x)] for x in atoms):
            raise ProgramError(f"{c.id}: its atoms share no entity of {sorted(domains)}")
        out |= {x.pred for x in joined}
    return out


def entity_groups(program: Program, evidence: dict[str, DataFrame], domains: set[str]) -> DataFrame:
    """``domain, entity, grp`` for the entities of ``domains`` (argument names of declarations) that atoms or binding rows
    hold; ``grp`` is the least ``domain:entity`` of the group. Null arguments are no entities."""
    binding = binding_predicates(program, domains)
    nodes, links = [], []
    for name, p in program.predicates.items():
        keys = [(d, c) for (d, _), c in zip(p.args, p.columns, strict=True) if d in domains]
        if not keys or not (p.open or name in binding):
            continue
        rows = evidence_rows(p, evidence[name])
        rows = rows if p.open else rows.filter("truth = 1")
        label = [F.concat(F.lit(f"{d}:"), F.col(c).cast("string")) for d, c in keys]
        nodes += [rows.select(F.lit(d).alias("domain"), F.col(c).cast("string").alias("entity"), x.alias("node")) for (d, c), x in zip(keys, label, strict=True)]
        if name in binding:
            links += [rows.select(label[0].alias("u"), x.alias("v")) for x in label[1:]]
    every = reduce(DataFrame.unionByName, nodes).filter("node IS NOT NULL").distinct()
    if not links:
        return every.select("domain", "entity", F.col("node").alias("grp"))
    roots = connect(reduce(DataFrame.unionByName, links).filter("u IS NOT NULL AND v IS NOT NULL"))
    return every.join(roots, "node", "left").select("domain", "entity", F.coalesce("root", "node").alias("grp"))
