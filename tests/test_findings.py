"""Cases of reviewers' findings, each small enough to restate by hand."""

import random
import tracemalloc
from pathlib import Path

import duckdb
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from ruleworld.functions import similarity
from ruleworld.llm import language, near, packing, tokens
from ruleworld.operators import field as views
from ruleworld.operators import kernel, split
from ruleworld.plans import catalog, experiments, solve, workloads
from ruleworld.plans import ground as g
from ruleworld.plans.program import Program

D = "/root/testdata/sf0.001"
CLAUSES = "cid bigint, lits array<bigint>, weight double, is_hard boolean, multiplicity bigint, rule string"


def assert_same(rows, sql, sf_dir=D):
    """Rows equal those of the SQL over the tables of a folder."""
    con = duckdb.connect()
    for p in Path(sf_dir).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM read_parquet('{p}')")
    told = con.execute(sql)
    names = [d[0] for d in told.description]
    want = [tuple(r[names.index(c)] for c in rows.columns) for r in told.fetchall()]
    assert sorted(map(tuple, rows.collect())) == sorted(want)


def test_cuts_lie_where_a_bound_asks_for_them(spark):
    rows = [(1, [1, 2], 1.0), (2, [-2, 3], 1.0), (3, [4, 5], 1.0)]
    clauses = spark.createDataFrame([(*r, False, 1, "r1") for r in rows], CLAUSES)
    comps = views.components(clauses)

    def told(pieces, beta):
        at = spark.createDataFrame(list(pieces.items()), "aid bigint, piece bigint").join(comps, "aid")
        return split.cuts_as_due(clauses, comps, at, beta).first().as_due

    whole, cut = {1: 1, 2: 1, 3: 1, 4: 4, 5: 4}, {1: 1, 2: 1, 3: 3, 4: 4, 5: 4}
    assert told(whole, 500) and not told(cut, 500)  # all fits: nothing is to be cut
    assert told(cut, 2) and not told(whole, 2)  # three atoms do not fit
    assert told(whole, 4) and told(cut, 4)  # four atoms and literals fit, or not, by the clauses taken


def test_benefits_are_those_of_the_events(spark):
    rows = catalog.queries()["benefit_table"](spark, D)
    assert any("events.parquet" in f for f in rows.inputFiles())
    assert_same(rows, catalog.oracle_sql()["benefit_table"])
    one = spark.range(1).select(F.lit(30).alias("n"), F.lit(10).alias("t"), F.lit(4).alias("cut"), F.lit(0).alias("edges"))
    assert tuple(one.select(*split.benefit_columns(*map(F.col, one.columns))).first()) == split.partition_benefit(30, 10, 4, 0)


def test_exhaustive_counts_follow_the_tables(spark):
    rows = catalog.queries()["exhaustive_counts_fig1"](spark, D)
    assert any("customer.parquet" in f for f in rows.inputFiles())
    assert_same(rows, catalog.oracle_sql()["exhaustive_counts_fig1"])
    assert {r.rule: r.instances for r in rows.collect()}["r2"] == 5 * 25 * 25 * 5


def test_steps_are_of_components_that_a_table_holds(spark):
    fld = g.ground(*workloads.twin_atoms(spark, D, n=3))
    extra = [(901, [901, 902], 2.0, False, 1, "r9"), (902, [903, -904], 2.0, False, 1, "r9")]
    mixed = fld.clauses.unionByName(spark.createDataFrame(extra, CLAUSES))
    assert sorted(n for _, n in solve.component_kinds(mixed, views.components(mixed))) == [1, 1, 3]
    kinds = solve.component_kinds(fld.clauses, views.components(fld.clauses))
    assert [n for _, n in kinds] == [3]
    assert {r.n for r in experiments.identical_kinds(spark, kinds, [1, 2, 4]).collect()} == {1, 2}  # no four of them
    assert_same(catalog.queries()["lumped_steps_ex1"](spark, D), catalog.oracle_sql()["lumped_steps_ex1"])


def rules(chance, atoms, many):
    signed = lambda n: tuple(chance.choice([-1, 1]) * a for a in chance.sample(range(1, atoms + 1), min(n, atoms)))
    return [(signed(chance.randint(1, 3)), chance.choice([0.5, 1.0, 2.0, -1.0, -0.25]), chance.random() < 0.15, chance.randint(1, 2)) for _ in range(many)]


@pytest.mark.parametrize("policy", ["listed", "repairing"])
def test_walk_to_a_proven_cost_finds_what_the_whole_walk_finds(policy):
    chance, flips = random.Random(5), [0, 0]
    for seed in range(60):
        cl = kernel.Clauses.build(rules(chance, chance.randint(1, 9), chance.randint(1, 14)))
        hard, soft, _ = kernel.optimum(cl)
        assert kernel.least_cost(cl) == (hard, round(soft, 9))
        whole, short = (kernel.walk(cl, 300, 3, seed=seed, policy=policy, target=t) for t in (None, kernel.least_cost(cl)))
        told = [(w.world, w.hard, w.soft, [(*x[:2], *x[3:]) for x in w.trace]) for w in (whole, short)]
        assert told[0] == told[1]
        flips = [flips[0] + whole.flips, flips[1] + short.flips]
    assert flips[1] * 20 < flips[0]


def test_least_cost_of_long_chains_and_of_dense_components():
    chain = [((-k, k + 1), 2.0, False) for k in range(1, 3000)] + [((1,), 1.0, False), ((-3000,), 0.5, False)]
    assert kernel.least_cost(kernel.Clauses.build(chain)) == (0, 0.5)
    dense = [((a, b), 1.0, False) for a in range(1, 20) for b in range(1, a)]
    assert kernel.least_cost(kernel.Clauses.build(dense)) is None


@pytest.mark.parametrize("schedule", ["in_turn", "round_robin"])
def test_search_that_proves_costs_makes_fewer_flips(spark, schedule):
    fld = g.ground(*workloads.tag_events(spark, D))
    comps = views.components(fld.clauses)
    whole, short = ({r.aid: (r.value, r.hard, r.soft, r.flips) for r in solve.search_components(fld.clauses, comps, 2, budget="fixed", flips=60, schedule=schedule, prove=p).collect()} for p in (False, True))
    assert {a: r[:3] for a, r in whole.items()} == {a: r[:3] for a, r in short.items()}
    assert sum(r[3] for r in short.values()) * 5 < sum(r[3] for r in whole.values())


def test_instances_put_in_order_inline_are_those_of_array_functions(spark, monkeypatch):
    program = Program.parse("@open on(n bigint)\n@closed link(n bigint, n bigint)\n3: on(x) & on(y) & link(x, y) => on(z)\n-1: on(x) | !on(y)\n1: on(x) & link(x, y) => on(y)")
    nodes = spark.createDataFrame([(1, -1), (2, -1), (3, 1), (4, 0), (5, -1)], "n bigint, truth int")
    atoms = g.load_atoms(program, {"on": nodes, "link": spark.createDataFrame([(1, 1), (1, 2), (2, 3), (5, 4), (2, 5)], "x bigint, y bigint")})

    def rows():
        return sorted(map(repr, g.ground_raw(program, atoms).filter("state <> 'won'").collect())), g.ground_raw(program, atoms).filter("state = 'won'").count()

    now, plan = rows(), g.ground_rule(atoms, program.clauses[0])._jdf.queryExecution().optimizedPlan().toString()
    assert "lambda" not in plan and "strategy=broadcast" in plan
    monkeypatch.setattr(g, "INLINE_LITERALS", 0)
    monkeypatch.setattr(g, "BROADCAST_ATOMS", -1)
    assert now == rows()


def test_words_are_known_whatever_signs_and_lines_stand_around_them(monkeypatch):
    e = tokens.Encoder("byte_bpe_50k.json", memo=3000, probes=0)
    texts = ["Ab thingon eau.\nUnd schö!!, thingon\nthingon's 12\n\nx"] * 3
    assert e.encode(texts) == e.whole(texts)
    asked = []
    for name in ("_merged", "_lined", "_patterned"):
        monkeypatch.setattr(e, name, lambda part, *a, own=getattr(e, name): (asked.extend(part), own(part))[1])
    again = ["Ab eau, schö?\nUnd; thingon### schö.\nUnd!"]
    assert e.encode(again) == e.whole(again) and asked == []
    chance = random.Random(4)
    many = [" ".join("".join(chance.choices("abcdeé.\n", k=chance.randint(3, 9))) for _ in range(400)) for _ in range(20)]
    assert all(e.encode([t]) == e.whole([t]) for t in many)
    held = [e.young, e.elder]
    assert 3000 < sum(map(len, held)) < 8000
    assert sum(r.keys.nbytes + r.flat.nbytes + r.size.nbytes for r in held) < 80 * sum(map(len, held))


def test_packing_holds_few_texts_at_a_time(monkeypatch):
    seen = []

    class Counting:
        def stream(self, texts):
            seen.append(len(texts))
            return (b"\1\0\0\0" for _ in texts)

    monkeypatch.setattr(packing, "shared_encoder", lambda *a: Counting())
    batch = pa.RecordBatch.from_pydict({"doc_id": list(range(4500)), "pack_group": [0] * 4500, "body": ["a"] * 4500})
    assert sum(b.num_rows for b in packing._cutting("v", 2, 8)([batch])) == 4500
    assert seen == [2000, 2000, 500]


def test_packing_workers_get_small_batches(spark, monkeypatch):
    def sizes(*a):
        def run(batches):
            for b in batches:
                yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (0, 0, 1, 0, b.num_rows, 0)], names=[*packing._NAMES, "pack_group"])

        return run

    monkeypatch.setattr(packing, "_cutting", sizes)
    setting = "spark.sql.execution.arrow.maxRecordsPerBatch"
    own = spark.conf.get(setting)
    got = [r["doc_tokens"] for r in packing.pack(spark.range(0, 4500, 1, 1).selectExpr("id AS doc_id", "'a' AS text")).collect()]
    assert sum(got) == 4500 and max(got) <= 1000
    assert spark.conf.get(setting) == own


def test_pairs_are_told_once_for_a_stretch_of_shared_runs(monkeypatch):
    monkeypatch.setattr(near, "_whole_keys", lambda batches: (pa.Table.from_batches([b]) for b in batches))

    def shared(s):
        whole = [pa.array(x, pa.int64()) for x in ([s, s], [1, 2], [s, s], [100, 100], [1, 2])]
        earlier = pa.array([list(range(max(0, s - near.BEFORE), s))] * 2, pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([*whole, pa.array([bytes(64)] * 2), earlier], names=["s", "rid", "pos", "n", "root", "short", "before"])

    told = [(b.column(0).to_pylist(), b.column(1).to_pylist()) for b in near._pairing(4, 5)(shared(s) for s in range(20))]
    assert told == [([1], [2])]


def test_pairs_of_a_block_are_numbered_without_a_sort_of_pairs(spark):
    for sf in (D, "/root/testdata/sf0.01"):
        rows = catalog.queries()["atoms_er"](spark, sf)
        assert_same(rows, catalog.oracle_sql()["atoms_er"], sf)
    plan = rows._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Generate") < plan.index("Repartition") and "Sort" not in plan[: plan.index("Repartition")]
    odd = spark.createDataFrame([(5, "a"), (2, "a"), (9, None), (7, "b"), (1, "c"), (3, "a"), (8, "c"), (None, "c")], "k bigint, b string")
    want = [(2, 3), (2, 5), (3, 2), (3, 5), (5, 2), (5, 3)]
    want = sorted([*want, (1, 8), (8, 1)])
    for least in (1, 2, 256):
        assert sorted(map(tuple, workloads.blocked_pairs(odd, "k", ["b"], least).collect())) == [(n, *x) for n, x in enumerate(want, 1)]


def test_nested_loops_go_cell_by_cell(spark, monkeypatch):
    left = spark.createDataFrame([(k % 50, k) for k in range(300)] + [(None, 1)], "v_a int, l0 int")
    right = spark.createDataFrame([(k % 70, k) for k in range(200)] + [(None, 2)], "v_a int, l1 int")
    want = sorted(map(tuple, left.join(right, "v_a").select("v_a", "l0", "l1").collect()))
    plan = lambda rows: rows._jdf.queryExecution().executedPlan().toString()
    for cells in (1, 7, 4096):
        monkeypatch.setattr(g, "CELLS", cells)
        rows = g._join(left, right, "nested_loop")
        assert sorted(map(tuple, rows.select("v_a", "l0", "l1").collect())) == want
        assert "xxhash64" in plan(rows) and "Cartesian" not in plan(rows)
    wide = right.withColumn("v_a", F.col("v_a").cast("double"))  # equal values of two types may hash apart
    rows = g._join(left, wide, "nested_loop")
    assert sorted(map(tuple, rows.select("v_a", "l0", "l1").collect())) == want and "Cartesian" in plan(rows)


def test_runs_of_one_text_alone_are_not_written(spark, monkeypatch):
    put = []
    monkeypatch.setattr(similarity, "settle", lambda rows, own=similarity.settle: (put.append(own(rows)), put[-1])[1])
    docs = spark.createDataFrame([(k, f"a b c d e {k} " + " ".join(f"w{k}x{j}" for j in range(200))) for k in range(30)] + [(30, "a b c d e f g h i"), (31, "a b c d e f g h j"), (32, None), (33, "a b c d e f g h i")], "doc_id bigint, text string")
    assert [(r.d1, r.d2, r.n, r.sim) for r in similarity.jaccard_pairs(docs, 0.5).collect()] == [(30, 31, 4, 0.666667)]
    assert sum(r.count() for r in put) < 100  # of more than 6000 runs
    assert_same(similarity.doc_pairs(spark, "/root/testdata/sf0.01"), similarity.oracle_sql()["sim_jaccard_docs"], "/root/testdata/sf0.01")
    assert_same(catalog.queries()["ground_er2"](spark, D), catalog.oracle_sql()["ground_er2"])


def test_fit_of_languages_holds_few_wide_rows():
    chance = random.Random(3)
    rows = [(lang, " ".join("".join(chance.choices(letters, k=6)) for _ in range(80))) for lang, letters in (("aa", "abcdefgh"), ("bb", "hijklmno")) for _ in range(200)]
    tracemalloc.start()
    model = language.fit_centroids(rows)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert model.names == ["aa", "bb"] and peak < 140e6


def test_tries_of_a_large_component_are_loads_of_their_own(spark, monkeypatch):
    chance = random.Random(5)
    ring = [(k, [-(k % 60 + 1), (k + 1) % 60 + 1], 1.0) for k in range(60)] + [(60 + k, [chance.choice((-1, 1)) * (chance.randrange(60) + 1)], 0.75) for k in range(40)]
    rows = [*ring, (100, [70, 71], 1.0), (101, [-70, -71], 1.0), (102, [80], 0.5), (103, [-80], 0.25)]
    cl = kernel.Clauses.build([(r[1], r[2], False) for r in ring])
    whole = kernel.walk(cl, 700, 3, seed=9)
    alone = [kernel.walk(cl, 700, 3, seed=9, only=k) for k in range(3)]
    first = min(alone, key=lambda w: (w.hard, w.soft))
    assert (first.world, first.hard, first.soft) == (whole.world, whole.hard, whole.soft)
    assert sum(w.flips for w in alone) == whole.flips and [w.tries for w in alone] == [1, 2, 3]
    assert whole.soft == cl.cost(whole.world)[1] and (whole.hard, whole.soft) == whole.trace[-1][3:]
    clauses = spark.createDataFrame([(*r, False, 1, "r1") for r in rows], CLAUSES)
    comps = views.components(clauses)
    found = lambda **how: sorted(tuple(r)[:-1] for r in solve.search_components(clauses, comps, 3, budget="fixed", flips=700, **how).collect())
    for how in ({}, {"prove": True}):
        want = found(**how)
        for apart in (0, 1000):
            monkeypatch.setattr(solve, "APART", apart)
            assert found(**how) == want
        monkeypatch.undo()
    made = []
    monkeypatch.setattr(solve, "APART", 1000)
    monkeypatch.setattr(solve, "by_load", lambda rows, *a, own=solve.by_load: (made.append(rows.select("bin").distinct().count()), own(rows, *a))[1])
    found()
    assert sum(made) > 3  # three loads of the ring's tries and those of the rest


def test_large_joins_are_dealt_out_and_not_shuffled(spark, monkeypatch):
    chance = random.Random(11)
    program = Program.parse("@open same(p bigint, p bigint)\n3: same(p, q) & same(q, r) => same(p, r)")
    pairs = sorted({(chance.randrange(9), chance.randrange(9)) for _ in range(60)})
    rows = [(p, q, chance.choice((-1, -1, 0, 1))) for p, q in pairs]
    atoms = g.load_atoms(program, {"same": spark.createDataFrame(rows, "p bigint, q bigint, truth int")})
    rule, told = program.clauses[0], lambda: g.ground_rule(atoms, program.clauses[0])
    mine = lambda: sorted((r.state, tuple(r.lits)) for r in told().collect())
    aid, truth, want = {p: k for k, p in enumerate(pairs, 1)}, {(p, q): t for p, q, t in rows}, []
    for p, q in pairs:
        for r in range(9):
            three = [((p, q), False), ((q, r), False), ((p, r), True)]
            if all(x in truth for x, _ in three) and all(truth[x] != s for x, s in three):
                lits = {aid[x] if s else -aid[x] for x, s in three if truth[x] == -1}
                clash = any(-x in lits for x in lits)
                want.append(("won" if clash else "free" if lits else "lost", tuple(sorted(lits, key=lambda x: (abs(x), x)))))
    free = lambda rows: sorted(x for x in rows if x[0] != "won")
    assert rule.weight == 3 and free(mine()) == free(want) and len(mine()) == len(want)
    plain = mine()
    plan = lambda: told().filter("state = 'free'")._jdf.queryExecution().executedPlan().toString()
    for side in (0, 10**6):
        monkeypatch.setattr(g, "DEALT_ROWS", 7)
        monkeypatch.setattr(g, "DEALT_SIDE", side)
        assert mine() == plain
        joins = [x for x in plan().split("\n") if "Join" in x or "REPARTITION_BY_NUM" in x]
        assert "BroadcastHashJoin" in joins[0] and any("REPARTITION_BY_NUM" in x for x in joins[1:])  # dealt below, met by broadcast above
    assert "sort_array" not in plan() and plan().count("Exchange hashpartitioning") <= 2
    monkeypatch.setattr(g, "BROADCAST_ATOMS", 0)  # sides that are too large to broadcast meet by their values
    assert mine() == plain
    author = catalog.queries()["ground_rc_author"](spark, D)
    assert_same(author, catalog.oracle_sql()["ground_rc_author"])
    assert "transform" not in author._jdf.queryExecution().optimizedPlan().toString()
