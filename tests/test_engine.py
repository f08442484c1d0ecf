"""The rule engine: worked example, identities over worlds, kernels against enumeration, distributed against local."""

import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from ruleworld.operators import field as views
from ruleworld.operators import kernel, split
from ruleworld.operators.connect import connect
from ruleworld.plans import ground as g
from ruleworld.plans import solve, workloads
from ruleworld.plans.program import Literal, Program, ProgramError, Term

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def example(spark):
    return g.ground(*workloads.running_example(spark))


def rows_of(clauses):
    return [(tuple(r.lits), r.weight, r.is_hard, r.multiplicity) for r in clauses.orderBy("cid").collect()]


def random_clauses(chance, atoms, n, hard=0.0):
    out = []
    for _ in range(n):
        picked = chance.sample(range(1, atoms + 1), chance.randint(1, min(3, atoms)))
        out.append((tuple(a if chance.random() < 0.5 else -a for a in sorted(picked)), chance.choice([-2.0, -1.0, 0.5, 1.0, 3.0]), False, 1))
        if chance.random() < hard:
            out[-1] = (out[-1][0], 1.0, True, 1)
    return out


# Program -------------------------------------------------------------------------------------------------------------


def test_parse_and_clause_form():
    p = Program.parse("@closed e(n bigint, n bigint)\n@open on(n bigint)\n# comment\n1.5: on(x) & e(x, y) => on(y) | x = y")
    c = p.clauses[0]
    assert [(x.pred, x.positive) for x in c.literals] == [("on", False), ("e", False), ("on", True)]
    assert c.weight == 1.5 and c.equals[0].positive


@pytest.mark.parametrize(
    "text,message",
    [
        ("1: on(x)", "line 1: on is not declared"),
        ("@open on(n bigint)\n1: on(x, y)", "takes 1 arguments"),
        ("@open on(n bigint)\n1: on('a')", "is no bigint"),
        ("@open on(n bigint)\n@closed c(n bigint)\n1: on(x) => c(y)", "unsafe"),
        ("@open on(n bigint)\nfoo", "line 2"),
        ("@open on(n bigint)\n@closed c(n bigint)\n-1: c(x) => on(x)", "negative weight"),
        ("@open on(n nothing)", "unknown type"),
        ("@open on(n bigint)\n@open on(n bigint)", "twice"),
    ],
)
def test_program_errors(text, message):
    with pytest.raises(ProgramError, match=message):
        Program.parse(text)


# Worked example ------------------------------------------------------------------------------------------------------


def test_running_example(spark, example):
    p, e = workloads.running_example(spark)
    raw = g.ground_raw(p, g.load_atoms(p, e))
    assert {r["rule"]: r["count"] for r in raw.filter("state = 'free'").groupBy("rule").count().collect()} == {"r1": 6, "r2": 3, "r3": 2, "r5": 3}
    assert example.clauses.count() == 11
    assert tuple(views.world_cost(example, views.constant_world(example.clauses, True)).first()) == (0, 33.0)
    cl = kernel.Clauses.build(rows_of(example.clauses))
    hard, soft = kernel.all_costs(cl)
    assert sorted(soft)[:4] == [0, 1, 1, 2] and hard.max() == 0
    p, log_z = kernel.exact_marginals(cl)
    assert math.exp(log_z) == pytest.approx(2.0880470549807355)
    assert p.tolist() == pytest.approx([0.567586627, 0.015227175, 6.741897e-06, 0.658342734, 0.097442221], abs=1e-8)


def test_active_closure_of_example(example):
    first, _ = g.active_closure(example.clauses, 0)
    every, atoms = g.active_closure(example.clauses)
    assert first.count() == 1 and every.count() == 2 and atoms.count() == 2


def test_solved_example(spark):
    r = solve.solve_map(*workloads.running_example(spark), total=5000)
    assert (r.hard, r.soft, r.path) == (0, 0.0, "components")
    assert {tuple(x) for x in r.filled("topic").collect()} == {("P1", "DB"), ("P2", "DB"), ("P3", "DB")}
    r.register_views()
    assert spark.sql("SELECT count(*) FROM topic JOIN cites ON topic.a1 = cites.a1").first()[0] == 1


def test_sql_text_equals_plan(spark):
    p, e = workloads.running_example(spark)
    atoms = g.load_atoms(p, e)
    for n, t in atoms.tables.items():
        t.createOrReplaceTempView(n)
    for c in p.clauses[:3]:
        want = sorted(sorted(r.lits) for r in g.ground_rule(atoms, c).filter("state = 'free'").collect())
        text = spark.sql(g.rule_sql(p, c)).filter("NOT exists(lits, x -> array_contains(lits, -x))")
        assert sorted(sorted(set(r.lits)) for r in text.collect()) == want


# Grounding against every substitution --------------------------------------------------------------------------------


def exhaustive_cost(program, domains, truth, world):
    """Cost of a full world by trying every substitution; truth and world map (pred, args) to a value."""
    hard, soft = 0, 0.0
    value = lambda x, sub: world[(x.pred, tuple(sub[t.value] if t.variable else t.value for t in x.terms))]
    for c in program.clauses:
        kinds = {}
        for x in c.literals:
            for t, (d, _) in zip(x.terms, program.predicates[x.pred].args):
                if t.variable:
                    kinds[t.value] = d
        outer = sorted(v for v in kinds if v not in c.exists)
        for combo in itertools.product(*(domains[kinds[v]] for v in outer)):
            sub = dict(zip(outer, combo))
            true = any((sub.get(e.left.value, e.left.value) == sub.get(e.right.value, e.right.value)) == e.positive for e in c.equals)
            for x in c.literals:
                inner = sorted(x.variables() & c.exists)
                for more in itertools.product(*(domains[kinds[v]] for v in inner)):
                    true = true or value(x, sub | dict(zip(inner, more))) == x.positive
            bad = true if c.weight < 0 else not true
            if c.hard:
                hard += bad
            else:
                soft += abs(c.weight) * bad
    return hard, soft


def test_pruned_equals_exhaustive(spark):
    chance = random.Random(8)
    p = Program.parse(
        """
        @closed e(n int, n int)
        @open on(n int)
        @open hot(n int)
        1.5: on(x) & e(x, y) => on(y)
        2: on(x) & hot(x) => x = 1
        -1: on(x) | hot(x)
        0.5: on(x) => exists y: e(x, y)
        hard: on(x) => exists y: hot(y)
        -inf: hot(2)
        0.75: !e(x, x) | on(x) | hot(x)
        """
    )
    nodes = [1, 2, 3]
    for _ in range(3):
        edges = [(a, b) for a in nodes for b in nodes if chance.random() < 0.4]
        truth = {(n, a): chance.choice([-1, -1, 0, 1]) for n in ("on", "hot") for a in nodes}
        evidence = {"e": spark.createDataFrame(edges, "a int, b int")}
        evidence |= {n: spark.createDataFrame([(a, truth[n, a]) for a in nodes], "a int, truth int") for n in ("on", "hot")}
        f = g.ground(p, evidence)
        rows, ids = rows_of(f.clauses), {}
        for n in ("on", "hot"):
            ids |= {r.aid: (n, r.a1) for r in f.atoms.tables[n].collect()}
        const = f.constants.agg(F.coalesce(F.sum("hard_contradictions"), F.lit(0)), F.coalesce(F.sum("constant_cost"), F.lit(0.0))).first()
        free = [k for k, v in ids.items() if truth[v] == -1]
        for bits in itertools.product([0, 1], repeat=len(free)):
            setting = dict(zip(free, bits))
            world = {("e", (a, b)): (a, b) in edges for a in nodes for b in nodes}
            world |= {(n, (a,)): bool(setting.get(k, truth[n, a] == 1)) for k, (n, a) in ids.items()}
            hard = soft = 0
            for lits, w, is_hard, many in rows:
                true = any(setting[abs(x)] == (x > 0) for x in lits)
                if true == (w < 0):
                    hard += many if is_hard else 0
                    soft += 0 if is_hard else abs(w)
            assert (hard + const[0], soft + const[1]) == exhaustive_cost(p, {"n": nodes}, truth, world)


def test_evidence_errors(spark):
    p = Program.parse("@open on(n int)\n1: on(x)")
    with pytest.raises(g.EvidenceError, match="both"):
        g.load_atoms(p, {"on": spark.createDataFrame([(1, 1), (1, 0)], "a int, truth int")})
    with pytest.raises(g.EvidenceError, match="null"):
        g.load_atoms(p, {"on": spark.createDataFrame([(None, 1)], "a int, truth int")})
    with pytest.raises(g.EvidenceError, match="no evidence"):
        g.load_atoms(p, {})


@pytest.mark.parametrize("lesion", ["order", "nested_loop", "merge", "broadcast", "shuffle_hash", "no_pushdown"])
def test_lesions_change_nothing(spark, example, lesion):
    assert rows_of(g.ground(*workloads.running_example(spark), lesion=lesion).clauses) == rows_of(example.clauses)


# Components, costs, flips --------------------------------------------------------------------------------------------


@pytest.mark.parametrize("n,m", [(1, 1), (40, 25), (300, 280), (200, 199)])
def test_connect_equals_union_find(spark, n, m):
    chance = random.Random(n)
    links = [(k, k + 1) for k in range(199)] if n == 200 else [(chance.randrange(n), chance.randrange(n)) for _ in range(m)]
    got = {r.node: r.root for r in connect(spark.createDataFrame(links, "a long, b long")).collect()}
    want = views.components_local([x for x in links if x[0] != x[1]])
    assert got == want


def test_component_costs_add_up(spark):
    f = g.ground(*workloads.classify_docs(spark, D))
    c = views.components(f.clauses)
    world = views.literals(f.clauses).select("aid").distinct().withColumn("value", F.pmod(F.xxhash64("aid"), F.lit(2)) == 1)
    whole = views.world_cost(f, world).first().soft
    parts = views.with_component(views.violated(f.clauses, world), c).groupBy("comp").agg(F.sum(F.abs("weight")).alias("s")).agg(F.sum("s")).first()[0]
    base = f.constants.agg(F.sum("constant_cost")).first()[0]
    assert whole == pytest.approx(parts + base)
    flips = views.flip_delta(f.clauses, world).orderBy(F.desc("delta"), "aid").limit(3).collect()
    for r in flips:
        turned = world.withColumn("value", F.when(F.col("aid") == r.aid, ~F.col("value")).otherwise(F.col("value")))
        assert views.world_cost(f, turned).first().soft == pytest.approx(whole + r.delta)
    assert all(v == 0 for v in views.check_field(f.clauses).first())


# Kernels -------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("policy", ["listed", "repairing"])
def test_walk_reaches_optimum(policy):
    chance = random.Random(3)
    for k in range(15):
        cl = kernel.Clauses.build(random_clauses(chance, 7, 14, hard=0.1))
        h, s, _ = kernel.optimum(cl)
        w = kernel.walk(cl, 1500, 3, policy=policy, seed=k)
        assert (w.hard, w.soft) == (h, pytest.approx(s)) and cl.cost(w.world) == (h, pytest.approx(s))
        costs = [t[3:] for t in w.trace]
        assert costs[:0] == [] and min(costs) == costs[-1]
        assert kernel.walk(cl, 200, 2, policy=policy, seed=k).world == kernel.walk(cl, 200, 2, policy=policy, seed=k).world


def test_best_by_component_is_no_worse():
    rows = [r for k in range(12) for r in (((2 * k + 1,), 1.0, False), ((2 * k + 2,), 1.0, False), ((2 * k + 1, 2 * k + 2), -1.0, False))]
    cl = kernel.Clauses.build(rows)
    parts = [(a - 1) // 2 for a in cl.ids]
    plain, apart = kernel.walk(cl, 400, seed=5), kernel.walk(cl, 400, seed=5, parts=parts)
    assert apart.soft <= plain.soft and cl.cost(apart.world)[1] == apart.soft


def test_step_chains():
    twin = kernel.Clauses.build([((1,), 1.0, False), ((2,), 1.0, False), ((1, 2), -1.0, False)])
    assert kernel.hitting_time(twin)[0] == pytest.approx(1.2142857)
    assert kernel.hitting_time(twin, "repairing") == (pytest.approx(2.5), pytest.approx(4.0))
    assert kernel.step_profile(twin)[:2] == (pytest.approx(1.75), pytest.approx(1.0))
    assert kernel.step_profile(twin, "repairing")[:2] == (pytest.approx(1.0), pytest.approx(1.0))
    two = kernel.Clauses.build([((a,), 1.0, False) for a in (1, 2, 3, 4)] + [((1, 2), -1.0, False), ((3, 4), -1.0, False)])
    assert kernel.hitting_time(two)[0] == pytest.approx(4.078, abs=1e-3)
    assert kernel.hitting_time(two, "repairing")[0] == pytest.approx(11.175, abs=1e-3)


def test_gap_bound():
    h, r, gain = split.gap_bound([(1.75, 1.0)] * 9)
    assert (h, r) == (9, pytest.approx(4 / 7)) and gain == pytest.approx(2)
    assert split.gap_bound([(2.0, 1.0)] * 1196)[2] == pytest.approx(239.2)
    assert split.gap_bound([(0.0, 0.0)] * 5)[2] == 0
    assert split.example_gap(10) == pytest.approx(math.log2(math.comb(9, 5)))


def test_slice_sampling():
    chance = random.Random(9)
    for k in range(3):
        cl = kernel.Clauses.build(random_clauses(chance, 5, 7))
        exact, _ = kernel.exact_marginals(cl)
        got, _ = kernel.mc_sat(cl, 5000, 100, seed=k)
        assert abs(got - exact).max() < 0.06


# Packing and splitting -----------------------------------------------------------------------------------------------


def test_class_packing_equals_first_fit():
    chance = random.Random(6)
    for _ in range(60):
        counts = {chance.randint(1, 30): chance.randint(1, 12) for _ in range(chance.randint(1, 6))}
        fills = {}
        seen = {s: [] for s in counts}
        for size, lo, hi, first, per in split.fill_classes(list(counts.items()), 20):
            for place in range(lo, hi):
                b = first + (place - lo) // per
                fills[b] = fills.get(b, 0) + size
                seen[size].append(place)
        assert all(sorted(v) == list(range(counts[s])) for s, v in seen.items())
        assert all(f <= 20 or f in counts for f in fills.values())
        plain = split.first_fit([(k, s) for k, s in enumerate(s for s, n in counts.items() for _ in range(n))], 20)
        assert len(fills) == len({b for _, b in plain})


def test_split_keeps_its_bound():
    chance = random.Random(7)
    for beta in (4, 12, 40, None):
        rows = [(k, r[0], r[1], r[2]) for k, r in enumerate(random_clauses(chance, 25, 40))]
        piece = split.split_rows(rows, beta)
        if beta is None:
            links = [(abs(r[1][0]), abs(x)) for r in rows for x in r[1]]
            assert piece == views.components_local(links)
        else:
            size = {}
            for a, p in piece.items():
                size[p] = size.get(p, 0) + 1
            for _, lits, _, _ in rows:
                own = {piece[abs(x)] for x in lits}
                assert len(own) > 1 or size[own.pop()] <= beta or len(lits) == 1


def test_splitting_and_conditioning(spark):
    f = g.ground(*workloads.bridged_rings(spark, D))
    c = views.components(f.clauses)
    best = solve.enumerate_components(f.clauses, c).first()
    pieces = split.split_bounded(f.clauses, c, 24)
    assert pieces.select("piece").distinct().count() == 2
    for order in ("coloured", "sequential"):
        _, costs, made = solve.alternate(f, pieces, 2, 800, order=order)
        assert 0 < made <= 2 * 2 * 800
        assert all(a >= b for a, b in zip(costs, costs[1:])) and costs[-1][1] == pytest.approx(best.soft)
    end = f.atoms.tables["on"].agg(F.min("aid")).first()[0]
    assert solve.condition_on(f.clauses, [end]).first().soft == pytest.approx(best.soft)
    stats = views.cut_stats(f.clauses, pieces).first()
    assert 0 < stats.cut_clauses < stats.clauses


def test_no_component_is_left_out(spark):
    f = g.ground(*workloads.bridged_rings(spark, D))
    end = f.atoms.tables["on"].agg(F.min("aid")).first()[0]
    with pytest.raises(solve.OverBudget, match="component"):
        solve.condition_on(f.clauses, [end], most=3)
    with pytest.raises(solve.OverBudget, match="component"):
        solve.profiles(f.clauses, views.components(f.clauses), most=3)
    chain = [(k, [-k, k + 1], 1.0, False, 1, "r") for k in range(1, 20)] + [(20, [1], 9.0, False, 1, "r"), (21, [-20], 9.0, False, 1, "r")]
    rows = spark.createDataFrame(chain, "cid bigint, lits array<bigint>, weight double, is_hard boolean, multiplicity bigint, rule string")
    with pytest.raises(solve.OverBudget, match="component"):
        solve.condition_on(rows, [1])
    assert solve.condition_on(rows, [1, 10]).first().soft == 1.0


def test_graph_is_its_field(spark):
    edges = workloads.nation_flows(spark, D)
    f = g.ground(*workloads.graph_program(edges))
    assert f.clauses.count() == edges.filter("x <> y").count()


def test_paths_and_budgets(spark):
    assert [solve.choose_path(*x) for x in ((5, 5, 9), (50, 5, 9), (50, 20, 9), (50, 20, 9, False))] == ["memory", "components", "pieces", "table"]
    with pytest.raises(solve.OverBudget):
        solve.solve_map(*workloads.bridged_rings(spark, D), budget=5, partition=False, refuse=True)
    split_up = solve.solve_map(*workloads.bridged_rings(spark, D), budget=24, total=2000)
    assert split_up.path == "pieces" and split_up.soft == pytest.approx(3.75) and 0 < split_up.flips <= 3 * 2000 + 6


def test_table_path_runs_and_reports_its_flips(spark, monkeypatch):
    asked = []
    monkeypatch.setattr(solve, "table_walk", lambda clauses, flips, seed: asked.append(flips) or (views.constant_world(clauses, False), [(0, 1.0)] * (flips + 1), 1.0))
    r = solve.solve_map(*workloads.running_example(spark), budget=1, may_split=False, total=70)
    assert (r.path, r.flips, asked) == ("table", 70, [70])


def test_table_search(spark):
    f = g.ground(*workloads.twin_atoms(spark, D, "nation", 2))
    world, costs, rate = solve.table_walk(f.clauses, 3, clustered=True)
    assert rate > 0 and views.world_cost(f, world).first().soft == min(c[1] for c in costs)


def test_hard_rules_and_contradictions(spark):
    f = g.ground(*workloads.order_lines(spark, D, hard=False))
    missing = f.constants.filter("rule = 'r1'").first()
    hard = g.ground(*workloads.order_lines(spark, D)).constants.filter("rule = 'r1'").first()
    assert missing.constant_cost == 2 * hard.hard_contradictions


def test_stream_equals_batch(spark, tmp_path):
    from ruleworld.streaming import evidence

    events = spark.read.parquet(f"{D}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    ordered = events.orderBy("ts")
    ordered.unionByName(ordered.limit(20)).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = evidence.event_stream(spark, str(tmp_path / "in"), late="60 days")
    q = evidence.rates(stream).writeStream.format("memory").queryName("rates").outputMode("complete").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(map(tuple, spark.table("rates").collect())) == sorted(map(tuple, evidence.rates(events.withColumn("ts", F.col("ts").cast("timestamp"))).collect()))


def test_literal_and_term_are_values():
    assert Literal("p", (Term("x", True),), True) == Literal("p", (Term("x", True),), True)
