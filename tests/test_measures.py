"""Measures, exhaustive grounding, splitting of giant components, loads, streams that keep state."""

import math
import random

import pytest
from pyspark.sql import functions as F

from ruleworld.functions import similarity
from ruleworld.operators import field as views
from ruleworld.operators import kernel, measures, split
from ruleworld.operators.rank import running_total
from ruleworld.plans import exhaustive, solve, workloads
from ruleworld.plans import ground as g
from ruleworld.plans.program import Program

D = "/root/testdata/sf0.001"
CLAUSES = "cid bigint, lits array<bigint>, weight double, is_hard boolean, multiplicity bigint, rule string"


def ring(n, chance):
    rows = [(k + 1, [-(k + 1), (k + 1) % n + 1], chance.choice([0.5, 1.0, 2.0]), False, 1, "r1") for k in range(n)]
    return rows + [(n + k + 1, [chance.choice([-1, 1]) * (k + 1)], chance.choice([0.25, 0.75]), False, 1, "r2") for k in range(n)]


def test_giant_component_is_split_without_a_task_above_its_size(spark):
    rows = ring(600, random.Random(4))
    clauses = spark.createDataFrame([(c, sorted(x, key=abs), *r) for c, x, *r in rows], CLAUSES)
    comps = views.components(clauses)
    block = split.blocks(clauses, 200)
    size = {r.aid: r.n for r in views.literals(clauses).groupBy("aid").agg((F.count("*") + 1).alias("n")).collect()}
    held = {}
    for r in block.collect():
        held[r.block] = held.get(r.block, 0) + size[r.aid]
    assert sum(1 for _ in held) < 40 and max(held.values()) <= 200
    pieces = {r.aid: r.piece for r in split.split_bounded(clauses, comps, 60.0, task_size=200).collect()}
    assert len(pieces) == 600 and len(set(pieces.values())) < 60
    inner = {}
    for _, lits, *_ in rows:
        if len({pieces[abs(x)] for x in lits}) == 1:
            inner[pieces[abs(lits[0])]] = inner.get(pieces[abs(lits[0])], 0) + len(lits)
    atoms = {p: sum(1 for x in pieces.values() if x == p) for p in set(pieces.values())}
    assert all(n <= 60 for n in atoms.values()) and all(min(a for a, q in pieces.items() if q == p) == p for p in atoms)
    whole = {r.aid: r.piece for r in split.split_bounded(clauses, comps, None, task_size=200).collect()}
    assert set(whole.values()) == {1}


def test_piece_size_is_any_function():
    rows = [(k, r[0], r[1], r[2]) for k, r in enumerate([((1, 2), 3.0, False), ((2, 3), 2.0, False), ((3, 4), 1.0, False)])]
    assert len(set(split.split_rows(rows, 2, size=lambda atoms, literals: atoms).values())) == 2
    assert len(set(split.split_rows(rows, 4, size=lambda atoms, literals: literals).values())) == 2
    assert len(set(split.split_rows(rows, 100, size=lambda atoms, literals: atoms**4).values())) == 2


def test_colours_differ_between_neighbours(spark):
    chance = random.Random(3)
    links = {(a, b) for a in range(30) for b in range(30) if a < b and chance.random() < 0.15}
    got = {r.node: r.colour for r in split.colours(spark.range(30).withColumnRenamed("id", "node"), spark.createDataFrame(sorted(links), "u long, v long")).collect()}
    assert len(got) == 30 and all(got[a] != got[b] for a, b in links) and max(got.values()) < 10


def test_choice_among_bounds(spark):
    f = g.ground(*workloads.bridged_rings(spark, D))
    c = views.components(f.clauses)
    best, told = split.choose_beta(f.clauses, c, [24, 4, None], rule="aggressive")
    rows = {r.beta: r for r in told.collect()}
    assert best == 4.0 and rows[24.0].cut_clauses == 1 and rows[None].cut_clauses == 0 and rows[4.0].pieces > rows[24.0].pieces
    assert split.choose_beta(f.clauses, c, [24, None])[0] in (24.0, None)
    assert split.speedup(448, 28, 11) == pytest.approx(25.705882) and split.phase_share({"a": 3.0, "b": 1.0})["a"] == 0.75


def test_schedules_and_workers_give_the_same_worlds(spark):
    f = g.ground(*workloads.twin_atoms(spark, D, "supplier"))
    c = views.components(f.clauses)
    how = {"tries": 2, "budget": "fixed", "flips": 60, "capacity": 30}
    got = [sorted((r.aid, r.value, r.soft, r.flips) for r in solve.search_components(f.clauses, c, **how, **more).collect()) for more in ({}, {"schedule": "round_robin", "quantum": 3}, {"schedule": "weighted", "quantum": 2}, {"parallel": 1}, {"packing": "single", "parallel": 2})]
    assert all(x == got[0] for x in got) and len(got[0]) == 20
    stats = split.bin_stats(split.pack_components(views.component_sizes(f.clauses, c).select("comp", (F.col("atoms") + F.col("literals")).alias("size")), 30), 30).first()
    assert (stats.overfull, stats.loads >= stats.lower_bound) == (0, True)


def test_round_robin_gives_all_a_share_of_the_time():
    chance = random.Random(5)
    cls = [kernel.Clauses.build([((k + 1,), 1.0, False) for k in range(8)] + [((-(k + 1),), 1.0, False) for k in range(8)]) for _ in range(6)]
    walks = kernel.take_turns([kernel.walking(c, 10**7, 1, seed=chance.randrange(99), quantum=50) for c in cls], seconds=0.5)
    assert all(w.flips > 0 and w.soft == 8 for w in walks)


def test_hitting_time_by_walks_is_near_the_exact_one():
    twin = kernel.Clauses.build([((1,), 1.0, False), ((2,), 1.0, False), ((1, 2), -1.0, False)])
    assert kernel.hitting_time(twin, exact=False, runs=1000)[0] == pytest.approx(kernel.hitting_time(twin)[0], abs=0.2)


def test_rules_of_one_shape_are_one_plan(spark):
    p, e = workloads.tag_events(spark, D)
    assert [len(x) for x in g.rule_groups(p.clauses)] == [sum(c.literals[1].positive for c in p.clauses[:50]), sum(not c.literals[1].positive for c in p.clauses[:50]), 2] or len(g.rule_groups(p.clauses)) == 4
    atoms = g.load_atoms(p, e)
    apart = None
    for c in p.clauses:
        apart = g.ground_rule(atoms, c) if apart is None else apart.unionByName(g.ground_rule(atoms, c))
    rows = [sorted((r.rule, tuple(r.lits), r.weight, r.is_hard, r.state) for r in x.collect()) for x in (g.ground_raw(p, atoms), apart)]
    assert rows[0] == rows[1] and len(rows[0]) > 1000
    assert "infield" in g.explain_grounding(p, atoms, p.clauses[-1]) and "Physical Plan" in g.explain_grounding(p, atoms, p.clauses[-1])


def test_shapes_with_guards_and_witnesses(spark):
    p = Program.parse(
        """
        @closed e(n int, k string)
        @open on(n int, k string)
        1: on(x, 'a') => e(x, 'b')
        2: on(x, 'b') => e(x, 'a')
        3: on(x, 'a') => exists y: on(y, 'b')
        4: on(x, 'b') => exists y: on(y, 'a')
        -1: on(x, 'a') | e(x, 'a')
        -2: on(x, 'b') | e(x, 'b')
        hard: on(1, 'a')
        hard: on(2, 'b')
        """
    )
    ev = {"e": spark.createDataFrame([(1, "a"), (2, "b"), (3, "b")], "n int, k string"), "on": spark.createDataFrame([(n, k, -1) for n in (1, 2, 3) for k in "ab"], "n int, k string, truth int")}
    atoms = g.load_atoms(p, ev)
    apart = None
    for c in p.clauses:
        apart = g.ground_rule(atoms, c) if apart is None else apart.unionByName(g.ground_rule(atoms, c))
    assert len(g.rule_groups(p.clauses)) == 4
    assert sorted(map(repr, g.ground_raw(p, atoms).collect())) == sorted(map(repr, apart.collect()))


def test_exhaustive_cost_equals_pruned_for_random_worlds(spark):
    p, e = workloads.running_example(spark)
    f = g.ground(p, e)
    every = exhaustive.ground_exhaustive(p, exhaustive.domains_of(p, e)).cache()
    open_ = f.atoms.open_rows().filter("truth = -1").select("aid")
    for k in range(3):
        world = open_.withColumn("value", F.pmod(F.xxhash64("aid", F.lit(k)), F.lit(2)) == 1)
        a, b = views.world_cost(f, world).first(), exhaustive.exhaustive_cost(every, exhaustive.full_world(f.atoms, world)).first()
        assert (a.hard, a.soft) == (b.hard, pytest.approx(b.soft))


def test_probabilities_of_all_worlds_sum_to_one(spark):
    rows = [(1, [1, -2], 1.5, False, 1, "r"), (2, [2], -0.5, False, 1, "r"), (3, [3], 2.0, False, 1, "r")]
    clauses = spark.createDataFrame(rows, CLAUSES)
    none = spark.createDataFrame([("r", 0.5, 0)], "rule string, constant_cost double, hard_contradictions bigint")
    fld = g.Field(None, clauses, none)
    comps = views.components(clauses)
    total = 0.0
    for bits in range(8):
        world = spark.createDataFrame([(a, bool(bits >> a - 1 & 1)) for a in (1, 2, 3)], "aid bigint, value boolean")
        total += measures.world_probability(fld, comps, world).first().probability
    assert total == pytest.approx(1.0)
    got = {r.cid: r.potential for r in measures.potentials(fld, views.constant_world(clauses, False)).collect()}
    assert got == {1: 1.0, 2: 1.0, 3: pytest.approx(math.exp(-2))}
    with pytest.raises(Exception, match="hard rules"):
        measures.log_partition(g.Field(None, clauses, none.withColumn("hard_contradictions", F.lit(1))), comps).collect()


def test_accuracy(spark):
    guessed = spark.createDataFrame([(1, 0), (2, 1), (3, 0), (3, 1)], "d int, c int")
    known = spark.createDataFrame([(1, 0), (2, 0), (3, 0), (4, 1)], "d int, c int")
    r = measures.accuracy(guessed, known, "d", "c").first()
    assert (r.n, r.told, r.accuracy) == (4, 3, 0.25)
    assert {x.label: (x.precision, x.recall) for x in measures.precision_recall(guessed.filter("d < 3"), known, "d", "c").collect()} == {0: (1.0, pytest.approx(1 / 3, abs=1e-5)), 1: (0.0, 0.0)}


def test_builder_equals_text():
    text = "@closed e(n bigint, n bigint)\n@open on(n bigint)\n1.5: on(x) & e(x, y) => on(y)\nhard: on(1)"
    built = Program.builder().closed("e", ("n", "bigint"), ("n", "bigint")).open("on", n="bigint").rule(1.5, "on(y)", "on(x) & e(x, y)").rule("hard", "on(1)").build()
    assert built == Program.parse(text)


def test_jaccard_pairs_equal_brute_force(spark):
    chance = random.Random(2)
    words = [f"w{k}" for k in range(80)]
    rows = []
    for _ in range(24):
        base = chance.choices(words, k=chance.choice([3, 8, 40]))
        for _ in range(4):
            own = list(base)
            for _ in range(chance.randint(0, 2)):
                own[chance.randrange(len(own))] = chance.choice(words)
            rows.append((len(rows), " ".join(own)))
    rows += [(100, ""), (101, None), (102, " ")]
    first = {}
    for i, t in rows:
        first.setdefault(t or "", i)
    sets = [(i, {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}) for t, i in first.items() for w in [t.split()]]
    want = {(min(i, j), max(i, j)) for i, x in sets for j, y in sets if i < j and len(x & y) / len(x | y) >= 0.6}
    got = similarity.jaccard_pairs(spark.createDataFrame(rows, "doc_id bigint, text string"), 0.6).collect()
    assert {(r.d1, r.d2) for r in got} == want and len(want) > 10


def test_search_reaches_every_optimum(spark):
    f = g.ground(*workloads.tag_events(spark, D))
    c = views.components(f.clauses)
    best = {r.comp: r.soft for r in solve.enumerate_components(f.clauses, c).collect()}
    found = {r.comp: r.soft for r in solve.search_components(f.clauses, c, tries=8, budget="fixed", flips=300).collect()}
    assert found == pytest.approx(best)


def test_stateful_sessions_joins_and_late_rows(spark, tmp_path):
    from ruleworld.streaming import evidence

    events = spark.read.parquet(f"{D}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    days = sorted(r[0] for r in events.select(F.to_date("ts")).distinct().collect())
    for k, part in enumerate((days[: len(days) // 2], days[len(days) // 2 :])):
        events.filter(F.to_date("ts").isin(part)).coalesce(1).write.parquet(str(tmp_path / f"w{k}"))
        (tmp_path / "in").mkdir(exist_ok=True)
        for f in (tmp_path / f"w{k}").glob("*.parquet"):
            f.rename(tmp_path / "in" / f"{k}-{f.name}")
    stream = evidence.event_stream(spark, str(tmp_path / "in"), late="2 hours")

    def run(frame, name, mode="append"):
        q = frame.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / f"cp-{name}")).trigger(availableNow=True).start()
        q.awaitTermination(240)
        return {tuple(r) for r in spark.table(name).collect()}, q

    batch = events.withColumn("ts", F.col("ts").cast("timestamp"))
    got, q = run(evidence.open_sessions(stream), "sessions")
    want = {tuple(r) for r in evidence.sessions(batch).collect()}
    assert got <= want and len(got) > 0.9 * len(want) and evidence.late_rows(q) >= 0
    pairs, _ = run(evidence.pairs_within(stream, evidence.event_stream(spark, str(tmp_path / "in"), late="2 hours")), "pairs")
    assert pairs == {tuple(r) for r in evidence.pairs_within(batch, batch).collect()}
    kinds = spark.createDataFrame([("error", 1)], "event_type string, bad int")
    assert evidence.with_domain(stream, kinds, "event_type").isStreaming


def test_live_world_goes_on_after_a_restart(spark, tmp_path):
    from ruleworld.streaming.evidence import LiveWorld

    p = Program.parse("@closed e(n bigint, n bigint)\n@open on(n bigint)\n2: on(x) & e(x, y) => on(y)\n-0.5: on(x)")
    ev = {"e": spark.createDataFrame([(1, 2), (2, 3), (4, 5)], "a bigint, b bigint"), "on": spark.createDataFrame([(k, -1) for k in range(1, 6)], "n bigint, truth int")}
    result = solve.solve_map(p, ev, total=2000)
    home = f"file://{tmp_path}/home"
    live = LiveWorld(result, "on", home=home)
    live.apply(spark.createDataFrame([(1, 1)], "n bigint, truth int"), 0)
    again = LiveWorld(result, "on", home=home)
    assert again.last == 0
    again.apply(spark.createDataFrame([(4, 1)], "n bigint, truth int"), 0)  # the same batch once more
    again.apply(spark.createDataFrame([(4, 1)], "n bigint, truth int"), 1)
    on = {r.aid for r in again.world.filter("value").collect()}
    assert on == {2, 3, 5} and again.last == 1


def test_running_total_within(spark):
    rows = spark.createDataFrame([(k % 3, k) for k in range(50)], "g long, k long")
    got = {(r.g, r.k): r.t for r in running_total(rows, ["g", "k"], F.lit(1).cast("long"), "t", within=["g"]).collect()}
    assert all(t == k // 3 + 1 for (_, k), t in got.items())
