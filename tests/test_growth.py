"""Growing fields against grounding at once, entity groups, lumped chains, SQL functions, sources, curves, experiments."""

import pytest
from pyspark.sql import functions as F

from ruleworld.functions import sql
from ruleworld.operators import chain, kernel
from ruleworld.operators import field as views
from ruleworld.plans import entities, experiments, grow, solve, workloads
from ruleworld.plans import ground as g
from ruleworld.plans.program import Program, ProgramError
from ruleworld.sources import evidence as source
from ruleworld.streaming.evidence import LiveWorld

D = "/root/testdata/sf0.001"
TWIN = [((1,), 1.0, False), ((2,), 1.0, False), ((1, 2), -1.0, False)]

RULES = """
@closed e(n bigint, n bigint)
@closed barred(n bigint)
@open on(n bigint)
2: on(x) & e(x, y) => on(y)
-0.5: on(x)
hard: on(x) & e(x, y) & e(y, z) => on(z) | barred(x)
1: on(x) => exists y: e(x, y)
-1.5: on(1)
"""


def named(fld):
    """Clauses with atoms by their arguments, constants, and truths: what a field says, without ids."""
    at = {r.aid: f"{r.pred}({r.args})" for r in fld.atoms.open_rows().collect()}
    clauses = sorted((r.rule, tuple(sorted((at[abs(x)], x > 0) for x in r.lits)), r.weight, r.is_hard, r.multiplicity) for r in fld.clauses.collect())
    constants = sorted((r.rule, r.constant_cost, r.hard_contradictions) for r in fld.constants.collect())
    return clauses, [c for c in constants if c[1] or c[2]], sorted((r.pred, r.args, r.truth) for r in fld.atoms.open_rows().collect())


def evidence(spark, edges, barred, on):
    return {
        "e": spark.createDataFrame(edges, "a bigint, b bigint"),
        "barred": spark.createDataFrame([(b,) for b in barred], "a bigint"),
        "on": spark.createDataFrame(on, "a bigint, truth int"),
    }


OLD = ([(1, 2), (2, 3), (4, 5)], [4], [(k, -1) for k in range(1, 7)])


@pytest.mark.parametrize(
    "edges,barred,on",
    [
        ([(3, 1), (5, 6), (1, 2)], [], []),
        ([], [1], [(2, 1), (3, 0)]),
        ([(7, 1), (2, 7)], [6], [(7, -1), (8, 1), (1, 0)]),
        ([], [], []),
    ],
)
def test_grown_field_equals_field_of_all(spark, edges, barred, on):
    program = Program.parse(RULES)
    begun = g.ground(program, evidence(spark, *OLD))
    grown = grow.reground(begun, evidence(spark, edges, barred, on)).field
    told = dict(OLD[2]) | dict(on)
    whole = g.ground(program, evidence(spark, OLD[0] + edges, OLD[1] + barred, sorted(told.items())))
    assert named(grown) == named(whole)
    assert grown.clauses.select("cid").distinct().count() == grown.clauses.count()


def test_growth_refuses_contradictions(spark):
    program = Program.parse("@open on(n bigint)\n1: on(x)")
    fld = g.ground(program, {"on": spark.createDataFrame([(1, 1), (2, -1)], "a bigint, truth int")})
    with pytest.raises(g.EvidenceError, match="1 rows are both"):
        grow.reground(fld, {"on": spark.createDataFrame([(1, 0)], "a bigint, truth int")})


def test_stream_of_evidence_searches_dirty_components_only(spark):
    made = workloads.running_example(spark)
    live = LiveWorld(solve.solve_map(*made, total=2000), "topic", tries=3, budget="fixed", flips=200)
    schema = "doc string, area string, truth int"
    live.apply(spark.createDataFrame([("P1", "DB", 0)], schema), 0)
    live.apply(spark.createDataFrame([("P1", "DB", 1)], schema), 0)  # the same batch again: ignored, no contradiction
    known = spark.createDataFrame([("P2", "DB", 1), ("P1", "DB", 0)], schema)
    whole = g.ground(made[0], made[1] | {"topic": made[1]["topic"].filter("truth = -1 AND NOT (doc = 'P1' AND area = 'DB')").unionByName(known.withColumn("truth", F.col("truth").cast("tinyint")))})
    assert named(live.field) == named(whole)
    hard, soft = kernel.all_costs(kernel.Clauses.build([(tuple(r.lits), r.weight, r.is_hard) for r in whole.clauses.collect()]))
    base = whole.constants.agg(F.coalesce(F.sum("constant_cost"), F.lit(0.0))).first()[0]
    assert views.world_cost(live.field, live.world).first().soft == pytest.approx(min(soft) + base)


def test_components_lie_in_entity_groups(spark):
    program, ev = workloads.classify_docs(spark, D)
    groups = entities.entity_groups(program, ev, {"doc"}).select(F.col("entity").cast("long").alias("a1"), "grp")
    fld = g.ground(program, ev)
    at = views.components(fld.clauses).join(fld.atoms.tables["topic"], "aid").join(groups, "a1", "left")
    assert at.filter("grp IS NULL").count() == 0
    assert at.groupBy("comp").agg(F.countDistinct("grp").alias("n")).filter("n > 1").count() == 0
    assert groups.select("grp").distinct().count() > 1
    loose = Program.parse("@open on(n bigint)\n@open up(m bigint)\n1: on(x) => up(y)")
    with pytest.raises(ProgramError, match="share no entity"):
        entities.binding_predicates(loose, {"n", "m"})


@pytest.mark.parametrize("policy,steps,last", [("listed", [1.214, 4.078, 16.166], 9.135), ("repairing", [2.5, 11.175, 83.667], 61.5)])
def test_lumped_chain(policy, steps, last):
    cl = kernel.Clauses.build(TWIN)
    one, (fall, rise, _) = chain.lump(cl, policy), kernel.step_profile(cl, policy)
    assert [round(chain.lumped_hitting(one, n)[0], 3) for n in (1, 2, 4)] == steps
    for n in (4, 8, 12):
        least = chain.lumped_hitting(one, n)[1]
        gains = [b - a for a, b in zip(least, least[1:], strict=False)]
        assert all(gains[k - 1] >= gains[k] * rise / fall * (n - k) / k - 1e-6 for k in range(1, n))
    assert round(chain.lumped_hitting(one, 4)[1][1], 3) == last
    two = kernel.Clauses.build([*TWIN, ((3, 4), 1.0, False), ((3,), -1.0, False), ((4,), -1.0, False)])
    assert chain.lumped_hitting(chain.lump(cl), 1)[0] == pytest.approx(kernel.hitting_time(cl)[0])
    with pytest.raises(ValueError, match="differently"):
        chain.lump(two)


def test_sql_functions(spark):
    sql.register(spark)
    row = spark.sql("SELECT clause_violated(array(1L, -2L), 1D, array(2L)) AS a, clause_violated(array(1L, -2L), -1D, array(2L)) AS b, clause_violated(array(-2L), -1D, CAST(array() AS ARRAY<BIGINT>)) AS c").first()
    assert tuple(row) == (True, False, True)
    got = spark.sql("SELECT w.* FROM (SELECT array(array(1L), array(2L), array(1L, 2L)) AS l, array(1D, 1D, -1D) AS w), LATERAL enumerate_component(l, w) w")
    assert sorted((tuple(r.true_atoms), r.hard, r.soft) for r in got.collect()) == [((), 0, 2.0), ((1,), 0, 2.0), ((1, 2), 0, 1.0), ((2,), 0, 2.0)]


def test_sources_and_sinks(spark, tmp_path):
    program, ev = workloads.running_example(spark)
    (tmp_path / "p.txt").write_text("@open on(n bigint)\n1: on(x)")
    assert source.read_program(spark, f"file://{tmp_path}/p.txt").predicates["on"].open
    for kind in ("csv", "json"):
        ev["topic"].toDF("a1", "a2", "truth").write.format(kind).save(f"file://{tmp_path}/{kind}")
        back = source.read_evidence(spark, program.predicates["topic"], f"file://{tmp_path}/{kind}", kind)
        assert sorted(map(tuple, back.collect())) == sorted(map(tuple, ev["topic"].collect()))
    fld = g.ground(program, ev)
    source.write_field(fld, f"file://{tmp_path}/field")
    assert named(source.read_field(spark, program, f"file://{tmp_path}/field")) == named(fld)
    source.write_world(fld, views.constant_world(fld.clauses, True), f"file://{tmp_path}/world")
    assert spark.read.parquet(f"file://{tmp_path}/world").filter("value").count() == 5


def test_curve_ends_at_the_cost_found(spark):
    fld = g.ground(*workloads.twin_atoms(spark, D))
    comps = views.components(fld.clauses)
    curve = solve.time_cost_curve(solve.trace_components(fld.clauses, comps, budget="fixed", flips=50, tries=2), 10).orderBy("at").collect()
    assert [r.soft for r in curve] == sorted((r.soft for r in curve), reverse=True)
    assert curve[-1].soft == 25 and curve[-1].hard == 0 and len(curve) <= 10


def test_experiments_show_what_is_known(spark):
    twins = workloads.twin_atoms(spark, "/root/testdata/sf0.001", "supplier")
    rows = {r.search: r for r in experiments.partitioning({"ex1": twins}, 2000).collect()}
    assert rows["by component"].soft == 10 and rows["by component"].soft <= rows["whole"].soft
    assert rows["whole, best by component"].soft <= rows["whole"].soft
    told = {r.search: r.path for r in experiments.over_budget(workloads.bridged_rings(spark, D), 30, 500).collect()}
    assert told == {"whole": "refused", "engine": "pieces"}
    steps = experiments.identical_components(spark, [4, 8]).collect()
    assert all(r.whole_steps > r.component_steps * 2 and r.last_component_steps >= 2**r.log2_bound for r in steps)
