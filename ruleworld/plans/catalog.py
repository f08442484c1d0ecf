"""The library's queries, each with the SQL that restates it where SQL can.

Fields are grounded once a session and table folder and kept in the shared scratch folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ruleworld.functions import similarity
from ruleworld.operators import field as views
from ruleworld.operators import split
from ruleworld.plans import entities, experiments, grow, solve, workloads
from ruleworld.plans import ground as g
from ruleworld.plans import oracles as o
from ruleworld.sources.scratch import settle, table
from ruleworld.streaming import evidence as stream

_kept: dict = {}


def _once(spark: SparkSession, sf_dir: str, name: str, make):
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


MAKERS = {
    "rc": workloads.classify_docs,
    "rc_author": lambda s, d: workloads.classify_docs(s, d, author_rule=True),
    "ie": workloads.tag_events,
    "ie2": workloads.tag_turns,
    "lp": workloads.link_customers,
    "er": workloads.dedup_parts,
    "er2": workloads.dedup_docs,
    "er3": workloads.dedup_vectors,
    "ex1": workloads.twin_atoms,
    "ex2": workloads.bridged_rings,
    "fig1": lambda s, d: workloads.running_example(s),
    "flows": workloads.nations_example,
    "bis": lambda s, d: workloads.graph_program(workloads.nation_flows(s, d)),
    "orders_hard": workloads.order_lines,
    "orders_soft": lambda s, d: workloads.order_lines(s, d, hard=False),
}


def program(spark, sf_dir, name):
    return _once(spark, sf_dir, f"program {name}", lambda: MAKERS[name](spark, sf_dir))


def atoms(spark, sf_dir, name) -> g.Atoms:
    return _once(spark, sf_dir, f"atoms {name}", lambda: g.load_atoms(*program(spark, sf_dir, name)))


def field(spark, sf_dir, name) -> g.Field:
    return _once(spark, sf_dir, f"field {name}", lambda: g.ground(*program(spark, sf_dir, name)))


def comps(spark, sf_dir, name) -> DataFrame:
    return _once(spark, sf_dir, f"comps {name}", lambda: settle(views.components(field(spark, sf_dir, name).clauses)))


def _text(rows: DataFrame) -> DataFrame:
    return rows.withColumn("lits", F.concat_ws(",", F.col("lits").cast("array<string>")))


def _atoms_of(name: str, pred: str, args: list[str]):
    def query(spark, sf_dir):
        t = atoms(spark, sf_dir, name).tables[pred]
        return t.select("aid", *[F.col(f"a{k}").alias(a) for k, a in enumerate(args, 1)], F.col("truth").cast("int").alias("truth"))

    return query


def atoms_er(spark, sf_dir):
    """Candidates of ``same``, numbered as atom tables are, without a sort of them; parts with a key twice take the way of other atoms."""
    part = table(spark, sf_dir, "part")
    n = part.agg(F.count("p_partkey").alias("rows"), F.countDistinct("p_partkey").alias("keys")).first()
    if n.rows > n.keys:
        return _atoms_of("er", "same", ["p", "q"])(spark, sf_dir)
    return workloads.blocked_pairs(part, "p_partkey", ["p_name", "p_type"]).withColumn("truth", F.lit(-1))


def _raw(name: str, *rules: str):
    def query(spark, sf_dir):
        prog, at = program(spark, sf_dir, name)[0], atoms(spark, sf_dir, name)
        rows = None
        for c in prog.clauses:
            if c.id in rules:
                own = g.ground_rule(at, c).filter("state = 'free'").select("rule", "lits", "weight")
                rows = own if rows is None else rows.unionByName(own)
        return _text(rows)

    return query


def _canonical(name: str, lesion: str = "none"):
    def query(spark, sf_dir):
        if lesion == "none":
            clauses = field(spark, sf_dir, name).clauses
        else:
            clauses = g.ground(*program(spark, sf_dir, name), lesion=lesion).clauses
        return _text(clauses.select("rule", "lits", "weight", "multiplicity"))

    return query


def rc_constants(spark, sf_dir):
    return field(spark, sf_dir, "rc").constants.select("rule", "constant_cost", "hard_contradictions")


def rc_prune_counts(spark, sf_dir):
    f = field(spark, sf_dir, "rc")
    return f.clauses.groupBy("rule").agg(F.count("*").alias("clauses"), F.sum("multiplicity").alias("instances"))


def _orders(name: str):
    return lambda spark, sf_dir: field(spark, sf_dir, name).constants.select("rule", "constant_cost", "hard_contradictions")


def _cost_all(value: bool):
    def query(spark, sf_dir):
        f = field(spark, sf_dir, "rc")
        return views.world_cost(f, views.constant_world(f.clauses, value))

    return query


def cost_by_rule(spark, sf_dir):
    f = field(spark, sf_dir, "rc")
    return views.cost_by_rule(f, views.constant_world(f.clauses, True)).select(F.coalesce("rule", F.lit("all")).alias("rule"), "soft")


def violated_topk(spark, sf_dir):
    f = field(spark, sf_dir, "rc")
    bad = views.violated(f.clauses, views.constant_world(f.clauses, True))
    return _text(bad.select("rule", "lits", "weight").orderBy(F.desc(F.abs("weight")), "rule", "lits").limit(20))


def flip_delta_rc(spark, sf_dir):
    f = field(spark, sf_dir, "rc")
    return views.flip_delta(f.clauses, views.constant_world(f.clauses, True)).select("aid", "make", "mend", "delta")


def degrees_rc(spark, sf_dir):
    return views.degrees(field(spark, sf_dir, "rc").clauses)


def _components(name: str):
    return lambda spark, sf_dir: comps(spark, sf_dir, name).select("aid", "comp")


def histogram_ie(spark, sf_dir):
    return views.component_histogram(comps(spark, sf_dir, "ie"))


def budgets_rc(spark, sf_dir):
    sizes = views.component_sizes(field(spark, sf_dir, "rc").clauses, comps(spark, sf_dir, "rc"))
    return solve.budgets(sizes, 10**7)


def bins_lower_bound(spark, sf_dir):
    sizes = views.component_sizes(field(spark, sf_dir, "ie").clauses, comps(spark, sf_dir, "ie"))
    return sizes.agg(F.ceil(F.sum(F.col("atoms") + F.col("literals")) / 1000).cast("long").alias("bins"))


def pack_ie(spark, sf_dir):
    sizes = views.component_sizes(field(spark, sf_dir, "ie").clauses, comps(spark, sf_dir, "ie"))
    return split.pack_components(sizes.select("comp", (F.col("atoms") + F.col("literals")).alias("size")), 1000)


def _search(name: str, **how):
    """Costs found by search, of every component."""

    def query(spark, sf_dir):
        f, c = field(spark, sf_dir, name), comps(spark, sf_dir, name)
        found = solve.search_components(f.clauses, c, tries=12, budget="fixed", flips=400, prove=True, **how)
        return found.groupBy("comp").agg(F.count("*").alias("atoms"), F.max("hard").alias("hard"), F.max("soft").alias("soft"))

    return query


def _enumerated(name: str, most: int = 20):
    """Least costs by enumeration, of every component; one of more than ``most`` atoms is refused."""

    def query(spark, sf_dir):
        solve._none_larger(comps(spark, sf_dir, name), most)
        return solve.enumerate_components(field(spark, sf_dir, name).clauses, comps(spark, sf_dir, name), most)

    return query


def whole_field_ex1(spark, sf_dir):
    f, c = field(spark, sf_dir, "ex1"), comps(spark, sf_dir, "ex1")
    found = solve.search_whole(f.clauses, c, flips=20_000, tries=1)
    return found.agg(F.max("hard").alias("hard"), F.max("soft").alias("soft"))


def alternate_ex2(spark, sf_dir):
    f, c = field(spark, sf_dir, "ex2"), comps(spark, sf_dir, "ex2")
    pieces = settle(split.split_bounded(f.clauses, c, 24))
    best = min(solve.alternate(f, pieces, sweeps=3, flips=2000, seed=s).costs[-1] for s in range(2))
    return spark.createDataFrame([best], "hard long, soft double")


def condition_ex2(spark, sf_dir):
    f = field(spark, sf_dir, "ex2")
    end = atoms(spark, sf_dir, "ex2").tables["on"].agg(F.min("aid")).first()[0]
    return solve.condition_on(f.clauses, [end])


def split_unbounded_rc(spark, sf_dir):
    return split.split_bounded(field(spark, sf_dir, "rc").clauses, comps(spark, sf_dir, "rc"), None).select("aid", F.col("piece").alias("comp"))


def split_bounded_rc(spark, sf_dir):
    return split.split_bounded(field(spark, sf_dir, "rc").clauses, comps(spark, sf_dir, "rc"), 20.0)


def cut_nation(spark, sf_dir):
    f = field(spark, sf_dir, "bis")
    at = atoms(spark, sf_dir, "bis").tables["on"]
    return views.cut_stats(f.clauses, at.select("aid", (F.col("a1") % 2).alias("piece"))).select("cut_clauses", "cut_weight", "clauses")


def reduction_nation(spark, sf_dir):
    f, at = field(spark, sf_dir, "bis"), atoms(spark, sf_dir, "bis").tables["on"].select("aid", "a1")
    lit = views.literals(f.clauses).join(at, "aid")
    return lit.groupBy("cid").agg(F.max(F.when(~F.col("positive"), F.col("a1"))).alias("x"), F.max(F.when(F.col("positive"), F.col("a1"))).alias("y")).select("x", "y")


def benefit_table(spark, sf_dir):
    """What splitting users' events by type gains and loses, by the type a link begins at: pieces are a user's events of a type."""
    ev = table(spark, sf_dir, "events").select("event_id", "event_type", "user_id")
    _, near = workloads.event_rows(spark, sf_dir)
    ends = near.join(ev.select(F.col("event_id").alias("e1"), F.col("event_type").alias("kind")), "e1").join(ev.select(F.col("event_id").alias("e2"), F.col("event_type").alias("other")), "e2")
    links = ends.groupBy("kind").agg(F.count_if(F.col("kind") != F.col("other")).alias("cut"), F.count("*").alias("edges"))
    pieces = ev.groupBy(F.col("event_type").alias("kind")).agg(F.countDistinct("user_id").alias("n"))
    each = pieces.join(links, "kind", "left").na.fill(0, ["cut", "edges"]).select("*", F.explode(F.array(F.lit(10), F.lit(1000)).cast("array<bigint>")).alias("t"))
    gain, loss = split.benefit_columns(*map(F.col, ("n", "t", "cut", "edges")))
    return each.select("kind", "n", "t", "cut", "edges", F.round(gain, 6).alias("log2_gain"), F.round(loss, 6).alias("loss"))


def profile_ex1(spark, sf_dir):
    return solve.profiles(field(spark, sf_dir, "ex1").clauses, comps(spark, sf_dir, "ex1"))


def gap_ex1(spark, sf_dir):
    rows = [(policy, *split.gap_bound([(r.a, r.b) for r in solve.profiles(field(spark, sf_dir, "ex1").clauses, comps(spark, sf_dir, "ex1"), policy).groupBy("comp", "a", "b").count().select("a", "b").collect()])) for policy in ("listed", "repairing")]
    return spark.createDataFrame([(p, h, round(r, 6), round(x, 6)) for p, h, r, x in rows], "policy string, h long, r double, log2_gap double")


def _marginals(name: str, **how):
    def query(spark, sf_dir):
        got = solve.marginals(field(spark, sf_dir, name).clauses, comps(spark, sf_dir, name), **how)
        return got.select("aid", F.round("p", 5).alias("p"))

    return query


def query_field_rc(spark, sf_dir):
    """The sub-field that a question about all German documents needs."""
    f = field(spark, sf_dir, "rc")
    german = table(spark, sf_dir, "documents").filter("lang = 'de'").select(F.col("doc_id").alias("a1"))
    wanted = atoms(spark, sf_dir, "rc").tables["topic"].join(german, "a1", "left_semi").select("aid")
    return _text(views.query_field(f.clauses, wanted).select("rule", "lits", "weight"))


def _active(rounds: int | None):
    def query(spark, sf_dir):
        rows, _ = g.active_closure(field(spark, sf_dir, "rc").clauses, rounds)
        return _text(rows.select("rule", "lits", "weight"))

    return query


def filled_topic(spark, sf_dir):
    """Rows of the completed relation that evidence alone settles."""
    at = atoms(spark, sf_dir, "rc").tables["topic"]
    return at.filter("truth = 1").select(F.col("a1").alias("doc_id"), F.col("a2").alias("cls"))


def completed_topic(spark, sf_dir):
    return solve.solve_map(*program(spark, sf_dir, "rc"), flips_per_atom=200).filled("topic").select(F.col("a1").alias("doc_id"), F.col("a2").alias("cls"))


def regrown_rc(spark, sf_dir):
    """Documents classified in two steps: links and labels of every seventh document come later and are folded in."""

    def make():
        prog, ev = program(spark, sf_dir, "rc")
        late = {"cites": F.col("d1") % 7 == 0, "topic": (F.col("truth") >= 0) & (F.col("doc_id") % 7 == 0)}
        begun = g.ground(prog, {
            "authored": ev["authored"],
            "cites": ev["cites"].filter(~late["cites"]),
            "topic": ev["topic"].withColumn("truth", F.when(late["topic"], F.lit(-1)).otherwise(F.col("truth")).cast("tinyint")),
        })
        return grow.reground(begun, {n: ev[n].filter(when) for n, when in late.items()})

    return _once(spark, sf_dir, "regrown rc", make)


def reground_clauses_rc(spark, sf_dir):
    return _text(regrown_rc(spark, sf_dir).field.clauses.select("rule", "lits", "weight", "multiplicity"))


def reground_constants_rc(spark, sf_dir):
    return regrown_rc(spark, sf_dir).field.constants.filter("constant_cost > 0 OR hard_contradictions > 0").select("rule", "constant_cost", "hard_contradictions")


def entity_groups_rc(spark, sf_dir):
    groups = entities.entity_groups(*program(spark, sf_dir, "rc"), {"doc"})
    return groups.select(F.col("entity").cast("long").alias("doc_id"), "grp")


def lumped_ex1(spark, sf_dir):
    """Steps of one walk over so many of the customers' two-atom components, and of a walk for each."""
    made = workloads.twin_atoms(spark, sf_dir, "customer")
    fld = g.ground(*made)
    kinds = solve.component_kinds(fld.clauses, settle(views.components(fld.clauses)))
    return experiments.identical_kinds(spark, kinds, [1, 2, 4, 8, 12, 16]).select("policy", "n", F.round("whole_steps", 3).alias("whole_steps"), F.round("component_steps", 3).alias("component_steps"))


def best_curve_ie(spark, sf_dir):
    """The end of the time-cost curve: the field's cost as the sum of its components' best."""
    curve = solve.time_cost_curve(solve.trace_components(field(spark, sf_dir, "ie").clauses, comps(spark, sf_dir, "ie"), tries=12, budget="fixed", flips=400, prove=True))
    return curve.agg(F.max_by("hard", "at").alias("hard"), F.round(F.max_by("soft", "at"), 6).alias("soft"))


def memory_rc(spark, sf_dir):
    return views.memory(field(spark, sf_dir, "rc").clauses, comps(spark, sf_dir, "rc"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    return completed_topic(spark, sf_dir)


def event_rollup(spark, sf_dir):
    ev, _ = workloads.event_rows(spark, sf_dir)
    return ev.rollup("event_type", "band").agg(F.count("*").alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("band", F.lit(-1)).alias("band"), "n")


def event_cube(spark, sf_dir):
    ev, _ = workloads.event_rows(spark, sf_dir)
    return ev.cube("event_type", "band").agg(F.count("*").alias("n")).select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("band", F.lit(-1)).alias("band"), "n")


def event_pivot(spark, sf_dir):
    ev, _ = workloads.event_rows(spark, sf_dir)
    return ev.groupBy("band").pivot("event_type", list(workloads.EVENT_TYPES)).agg(F.count(F.lit(1))).na.fill(0)


def as_of_orders(spark, sf_dir):
    """Each event of type error with the latest purchase of its user at or before it."""
    ev = table(spark, sf_dir, "events")
    seq = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(seq)
    return ev.withColumn("purchase_id", last).filter("event_type = 'error'").select("event_id", "purchase_id")


def json_evidence(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("long")
    return table(spark, sf_dir, "events").groupBy((k >= 90).alias("high")).agg(F.count("*").alias("n"), F.sum(k).alias("k"))


def price_band_join(spark, sf_dir):
    """Parts of a name and type within 10 in price: a range join behind equal keys."""
    return program(spark, sf_dir, "er")[1]["near_price"].select("p", "q")


def running_best(spark, sf_dir):
    """Running least order price by customer and day: the frame of a time-cost curve."""
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, sf_dir, "orders").select("o_orderkey", F.min("o_totalprice").over(w).alias("best"))


def queries() -> dict:
    out = {
        "atoms_rc": _atoms_of("rc", "topic", ["doc_id", "cls"]),
        "atoms_ie": _atoms_of("ie", "infield", ["event_id"]),
        "atoms_lp": _atoms_of("lp", "preferred", ["c", "s"]),
        "atoms_er": atoms_er,
        "ground_fig1": _canonical("fig1"),
        "ground_rc_key": _raw("rc", "r1"),
        "ground_rc_cite": _raw("rc", "r2", "r3"),
        "ground_rc_prior": _raw("rc", "r4"),
        "ground_rc_author": _raw("rc_author", "r5"),
        "ground_ie_pairs": _raw("ie", "r51", "r52"),
        "ground_lp_key": _raw("lp", "r1"),
        "ground_er_transitive": _raw("er", "r6"),
        "ground_exists_orders": _orders("orders_soft"),
        "ground_hard_contradictions": _orders("orders_hard"),
        "canonical_clauses_rc": _canonical("rc"),
        "canonical_clauses_ie": _canonical("ie"),
        "constant_cost_rc": rc_constants,
        "prune_counts_rc": rc_prune_counts,
        "cost_all_false": _cost_all(False),
        "cost_all_true": _cost_all(True),
        "cost_by_rule": cost_by_rule,
        "violated_topk": violated_topk,
        "flip_delta_rc": flip_delta_rc,
        "degrees_rc": degrees_rc,
        "components_rc": _components("rc"),
        "components_ie": _components("ie"),
        "component_histogram": histogram_ie,
        "budgets_rc": budgets_rc,
        "bins_lower_bound": bins_lower_bound,
        "pack_sizes_ie": pack_ie,
        "map_cost_ex1": _search("ex1"),
        "map_cost_ie": _search("ie"),
        "map_cost_rc": _search("rc"),
        "map_cost_ex2": _search("ex2"),
        "optimum_ie": _enumerated("ie"),
        "whole_field_ex1": whole_field_ex1,
        "alternate_cost_ex2": alternate_ex2,
        "condition_cost_ex2": condition_ex2,
        "split_unbounded_rc": split_unbounded_rc,
        "split_bounded_rc": split_bounded_rc,
        "cut_stats_nation": cut_nation,
        "reduction_nation": reduction_nation,
        "benefit_table": benefit_table,
        "profile_ex1": profile_ex1,
        "gap_bound_ex1": gap_ex1,
        "marginals_exact_fig1": _marginals("fig1", exact=True),
        "marginals_exact_ie": _marginals("ie", exact=True, most=20),
        "marginals_mcsat_ie": _marginals("ie", samples=50, burn_in=5),
        "query_field_rc": query_field_rc,
        "active_round0_rc": _active(0),
        "active_closure_rc": _active(None),
        "filled_topic_evidence": filled_topic,
        "completed_topic": completed_topic,
        "sim_tokens_part": similarity.part_tokens,
        "sim_cosine": similarity.vector_pairs,
        "sim_jaccard_docs": similarity.doc_pairs,
        "sim_doc_members": similarity.doc_members,
        "session_components": stream.sessions_batch,
        "windowed_rates": stream.rates_batch,
        "op_rollup": event_rollup,
        "op_cube": event_cube,
        "op_pivot": event_pivot,
        "op_as_of": as_of_orders,
        "op_json": json_evidence,
        "op_band_join": price_band_join,
        "op_running_best": running_best,
        "reground_clauses_rc": reground_clauses_rc,
        "reground_constants_rc": reground_constants_rc,
        "entity_groups_rc": entity_groups_rc,
        "lumped_steps_ex1": lumped_ex1,
        "best_curve_ie": best_curve_ie,
        "memory_rc": memory_rc,
    }
    for lesion in ("order", "nested_loop", "merge", "broadcast", "shuffle_hash", "no_pushdown"):
        out[f"lesion_{lesion}"] = _canonical("rc", lesion)
    from ruleworld.plans import catalog_measures

    return out | catalog_measures.queries()


def oracle_sql() -> dict[str, str]:
    canon = f"SELECT rule, {o.LITS}, weight, multiplicity FROM cl"
    rc, ie = o.RC, o.IE
    known = "SELECT 'r4' AS rule, count(*) FILTER (truth = 1) * 1.0 AS constant_cost, CAST(0 AS BIGINT) AS hard_contradictions FROM topic WHERE cls = 0"
    rows = f"SELECT rule, {o.LITS}, CAST(weight AS DOUBLE) AS weight FROM raw WHERE len(lits) > 0 AND rule IN "
    lost = "SELECT rule, sum(weight) AS constant_cost, CAST(0 AS BIGINT) AS hard_contradictions FROM raw WHERE len(lits) = 0 GROUP BY rule"
    out = {
        "atoms_rc": f"WITH {o.RC_ATOMS} SELECT aid, doc_id, cls, truth FROM topic",
        "atoms_ie": "SELECT row_number() OVER (ORDER BY event_id) AS aid, event_id, -1 AS truth FROM events",
        "atoms_lp": "SELECT row_number() OVER (ORDER BY c, s) AS aid, c, s, -1 AS truth FROM (SELECT o_custkey AS c, l_suppkey AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL HAVING count(DISTINCT o_orderkey) >= 2)",
        "atoms_er": "SELECT row_number() OVER (ORDER BY p, q) AS aid, p, q, -1 AS truth FROM (SELECT a.p_partkey AS p, b.p_partkey AS q FROM part a JOIN part b USING (p_name, p_type) WHERE a.p_partkey <> b.p_partkey)",
        "ground_fig1": "SELECT * FROM (VALUES ('r1', '-5,-6', 10.0, 2), ('r1', '-4', 10.0, 2), ('r1', '-1,-2', 10.0, 2), ('r2', '-2,4', 1.0, 1), ('r2', '1', 1.0, 1), ('r2', '2,-4', 1.0, 1), ('r3', '-2,6', 2.0, 1), ('r3', '-1,5', 2.0, 1), ('r5', '2', -1.0, 1), ('r5', '4', -1.0, 1), ('r5', '6', -1.0, 1)) v(rule, lits, weight, multiplicity)",
        "ground_rc_key": f"WITH {o.RC_ATOMS}, {o.RC_RAW} {rows} ('r1')",
        "ground_rc_cite": f"WITH {o.RC_ATOMS}, {o.RC_RAW} {rows} ('r2', 'r3')",
        "ground_rc_prior": f"WITH {o.RC_ATOMS}, {o.RC_RAW} {rows} ('r4')",
        "ground_rc_author": f"WITH {o.RC_ATOMS}, authored AS (SELECT DISTINCT source, doc_id FROM documents), raw AS ({o.RC_AUTHOR}) {rows} ('r5')",
        "ground_ie_pairs": f"{ie} {rows} ('r51', 'r52')",
        "ground_lp_key": "WITH t AS (SELECT row_number() OVER (ORDER BY c, s) AS aid, c, s FROM (SELECT o_custkey AS c, l_suppkey AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL HAVING count(DISTINCT o_orderkey) >= 2)) SELECT 'r1' AS rule, concat(-least(x.aid, y.aid), ',', -greatest(x.aid, y.aid)) AS lits, 3.0 AS weight FROM t x JOIN t y ON x.c = y.c AND x.s <> y.s",
        "ground_er_transitive": "WITH t AS (SELECT row_number() OVER (ORDER BY p, q) AS aid, p, q FROM (SELECT a.p_partkey AS p, b.p_partkey AS q FROM part a JOIN part b USING (p_name, p_type) WHERE a.p_partkey <> b.p_partkey)) SELECT 'r6' AS rule, array_to_string(list_transform(list_sort([x.aid * 2, y.aid * 2, z.aid * 2 + 1]), lambda v: CASE WHEN v % 2 = 1 THEN v // 2 ELSE -(v // 2) END), ',') AS lits, 3.0 AS weight FROM t x JOIN t y ON x.q = y.p JOIN t z ON z.p = x.p AND z.q = y.q",
        "ground_exists_orders": "SELECT 'r1' AS rule, 2.0 * count(*) AS constant_cost, CAST(0 AS BIGINT) AS hard_contradictions FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
        "ground_hard_contradictions": "SELECT 'r1' AS rule, CAST(0 AS DOUBLE) AS constant_cost, count(*) AS hard_contradictions FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)",
        "canonical_clauses_rc": f"{rc} {canon}",
        "canonical_clauses_ie": f"{ie} {canon}",
        "constant_cost_rc": f"WITH {o.RC_ATOMS}, {o.RC_RAW} SELECT * FROM ({lost} UNION ALL {known}) WHERE constant_cost > 0",
        "prune_counts_rc": f"{rc} SELECT rule, count(*) AS clauses, CAST(sum(multiplicity) AS BIGINT) AS instances FROM cl GROUP BY rule",
        "cost_by_rule": f"{rc}, {o.world_cost('true')} SELECT coalesce(rule, 'all') AS rule, sum(abs(weight)) AS soft FROM bad GROUP BY ROLLUP (rule)",
        "violated_topk": f"{rc}, {o.world_cost('true')} SELECT rule, {o.LITS}, weight FROM (SELECT * FROM bad ORDER BY abs(weight) DESC, rule, lits LIMIT 20)",
        "degrees_rc": f"{rc} SELECT abs(x) AS aid, count(*) AS clauses, CAST(sum(n - 1) AS BIGINT) AS links FROM (SELECT unnest(lits) AS x, len(lits) AS n FROM cl) GROUP BY abs(x)",
        "components_rc": f"{rc}, {o.COMPONENTS} SELECT aid, comp FROM comps",
        "components_ie": f"{ie}, {o.COMPONENTS} SELECT aid, comp FROM comps",
        "component_histogram": f"{ie}, {o.COMPONENTS} SELECT atoms, count(*) AS components FROM (SELECT comp, count(*) AS atoms FROM comps GROUP BY comp) GROUP BY atoms",
        "budgets_rc": f"{rc}, {o.COMPONENTS} SELECT comp, atoms, CAST(ceil(10000000 * atoms / CAST(sum(atoms) OVER () AS DOUBLE)) AS BIGINT) AS flips FROM (SELECT comp, count(*) AS atoms FROM comps GROUP BY comp)",
        "bins_lower_bound": f"{ie} SELECT CAST(ceil(((SELECT count(*) FROM events) + sum(len(lits))) / 1000.0) AS BIGINT) AS bins FROM cl",
        "map_cost_ex1": f"{o.EX1}, {o.enumerated(4)} SELECT comp, atoms, hard, soft FROM ({o.BEST})",
        "map_cost_ie": f"{ie}, {o.enumerated(12)} SELECT comp, atoms, hard, soft FROM ({o.BEST})",
        "map_cost_ex2": f"{o.EX2}, {o.enumerated(10)} SELECT comp, atoms, hard, soft FROM ({o.BEST})",
        "optimum_ie": f"{ie}, {o.enumerated(12)} {o.BEST}",
        "whole_field_ex1": "SELECT CAST(0 AS BIGINT) AS hard, CAST(count(*) AS DOUBLE) AS soft FROM nation",
        "alternate_cost_ex2": f"{o.EX2}, {o.enumerated(10)} SELECT hard, soft FROM ({o.BEST})",
        "condition_cost_ex2": f"{o.EX2}, {o.enumerated(10)} SELECT hard, soft FROM ({o.BEST})",
        "split_unbounded_rc": f"{rc}, {o.COMPONENTS} SELECT aid, comp FROM comps",
        "cut_stats_nation": "WITH f AS (SELECT DISTINCT c_nationkey AS x, s_nationkey AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey) SELECT count(*) FILTER ((x - y) % 2 <> 0) AS cut_clauses, CAST(count(*) FILTER ((x - y) % 2 <> 0) AS DOUBLE) AS cut_weight, count(*) AS clauses FROM f",
        "reduction_nation": "SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS x, CAST(s_nationkey AS BIGINT) AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey",
        "benefit_table": "WITH l AS (SELECT event_type AS kind, user_id, lead(event_type) OVER w AS other, coalesce(lead(ts) OVER w <= ts + INTERVAL 60 MINUTES, false) AS linked FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), "
        "k AS (SELECT kind, count(DISTINCT user_id) AS n, count(*) FILTER (linked AND other <> kind) AS cut, count(*) FILTER (linked) AS edges FROM l GROUP BY kind) "
        "SELECT kind, n, t, cut, edges, round(n / 3.0, 6) AS log2_gain, round(t * cut / CAST(greatest(edges, 1) AS DOUBLE), 6) AS loss FROM k, (SELECT unnest([10, 1000]) AS t)",
        "profile_ex1": "SELECT row_number() OVER (ORDER BY n_nationkey) AS comp, 1.75 AS a, 1.0 AS b, 1.0 AS opt_cost FROM nation",
        "gap_bound_ex1": "SELECT * FROM (VALUES ('listed', 25, round(4 / 7.0, 6), round(25 * 2 / 9.0, 6)), ('repairing', 25, 1.0, round(25 / 3.0, 6))) v(policy, h, r, log2_gap)",
        "marginals_exact_fig1": "SELECT * FROM (VALUES (1, 0.56759), (2, 0.01523), (4, 0.00001), (5, 0.65834), (6, 0.09744)) v(aid, p)",
        "marginals_exact_ie": f"{ie}, {o.enumerated(12)} SELECT aid, round(sum(exp(-cost)) FILTER ((w >> k) & 1 = 1) / sum(exp(-cost)), 5) AS p FROM costs JOIN ranked USING (comp) GROUP BY aid",
        "query_field_rc": f"{rc}, {o.COMPONENTS}, hit AS (SELECT DISTINCT comp FROM comps JOIN topic USING (aid) WHERE doc_id IN (SELECT doc_id FROM documents WHERE lang = 'de')) SELECT rule, {o.LITS}, weight FROM cl WHERE abs(lits[1]) IN (SELECT aid FROM comps WHERE comp IN (SELECT comp FROM hit))",
        "active_round0_rc": f"{rc} SELECT rule, {o.LITS}, weight FROM cl WHERE CASE WHEN weight > 0 THEN len(list_filter(lits, lambda x: x < 0)) = 0 ELSE len(list_filter(lits, lambda x: x < 0)) > 0 END",
        "filled_topic_evidence": f"WITH {o.RC_ATOMS} SELECT doc_id, cls FROM topic WHERE truth = 1",
        "op_rollup": "WITH e AS (SELECT event_type, CAST(least(floor(value / 50), 9) AS INT) AS band FROM events) SELECT coalesce(event_type, 'all') AS event_type, coalesce(band, -1) AS band, count(*) AS n FROM e GROUP BY ROLLUP (event_type, band)",
        "op_cube": "WITH e AS (SELECT event_type, CAST(least(floor(value / 50), 9) AS INT) AS band FROM events) SELECT coalesce(event_type, 'all') AS event_type, coalesce(band, -1) AS band, count(*) AS n FROM e GROUP BY CUBE (event_type, band)",
        "op_pivot": "WITH e AS (SELECT event_type, CAST(least(floor(value / 50), 9) AS INT) AS band FROM events) SELECT band, "
        + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in workloads.EVENT_TYPES)
        + " FROM e GROUP BY band",
        "op_as_of": "SELECT event_id, purchase_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS purchase_id FROM events) WHERE event_type = 'error'",
        "op_json": "SELECT k >= 90 AS high, count(*) AS n, CAST(sum(k) AS BIGINT) AS k FROM (SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events) GROUP BY ALL",
        "op_band_join": "SELECT a.p_partkey AS p, b.p_partkey AS q FROM part a JOIN part b USING (p_name, p_type) WHERE a.p_partkey <> b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 10",
        "op_running_best": "SELECT o_orderkey, min(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS best FROM orders",
    }
    out |= {
        "reground_clauses_rc": out["canonical_clauses_rc"],
        "reground_constants_rc": out["constant_cost_rc"],
        "entity_groups_rc": f"WITH RECURSIVE {o.RC_ATOMS}, link AS (SELECT d1 AS a, d2 AS b FROM cites UNION SELECT d2, d1 FROM cites), reach AS (SELECT DISTINCT doc_id AS a, doc_id AS r FROM documents UNION SELECT b, r FROM reach JOIN link USING (a) WHERE r < b), least AS (SELECT a AS doc_id, min(r) AS c FROM reach GROUP BY a) SELECT doc_id, min('doc:' || doc_id) OVER (PARTITION BY c) AS grp FROM least",
        "lumped_steps_ex1": "SELECT policy, CAST(n AS BIGINT) AS n, CAST(whole_steps AS DOUBLE) AS whole_steps, CAST(round(n * one, 3) AS DOUBLE) AS component_steps FROM (VALUES ('listed', 1, 1.214, 17 / 14.0), ('listed', 2, 4.078, 17 / 14.0), ('listed', 4, 16.166, 17 / 14.0), ('listed', 8, 109.922, 17 / 14.0), ('listed', 12, 684.747, 17 / 14.0), ('listed', 16, 4574.04, 17 / 14.0), ('repairing', 1, 2.5, 2.5), ('repairing', 2, 11.175, 2.5), ('repairing', 4, 83.667, 2.5), ('repairing', 8, 2878.36, 2.5), ('repairing', 12, 105216.543, 2.5), ('repairing', 16, 3995140.869, 2.5)) v(policy, n, whole_steps, one) WHERE n <= (SELECT count(DISTINCT c_custkey) FROM customer)",
        "best_curve_ie": f"{ie}, {o.enumerated(12)} SELECT CAST(sum(hard) AS BIGINT) AS hard, round(sum(soft), 6) AS soft FROM ({o.BEST})",
        "memory_rc": f"{rc}, {o.COMPONENTS}, a AS (SELECT comp, count(*) AS atoms FROM comps GROUP BY comp), c AS (SELECT comp, count(*) AS n, sum(len(lits)) AS l FROM cl JOIN comps ON aid = abs(lits[1]) GROUP BY comp) SELECT CAST(sum(l * 8 + n * 33) AS BIGINT) AS clause_bytes, CAST(sum(atoms * 40 + n * 64 + l * 16) AS BIGINT) AS whole_bytes, CAST(max(atoms * 40 + n * 64 + l * 16) AS BIGINT) AS largest_bytes FROM a JOIN c USING (comp)",
    }
    for value, name in (("false", "cost_all_false"), ("true", "cost_all_true")):
        out[name] = f"{rc}, {o.world_cost(value)}, base AS ({lost} UNION ALL {known}) SELECT CAST(0 AS BIGINT) AS hard, (SELECT sum(abs(weight)) FROM bad) + (SELECT sum(constant_cost) FROM base) AS soft"
    out["flip_delta_rc"] = f"""{rc}, one AS (SELECT cid, weight, len(list_filter(lits, lambda x: x > 0)) AS n_true, unnest(lits) AS x FROM cl),
        turned AS (SELECT abs(x) AS aid, abs(weight) AS c, (n_true > 0) <> (weight > 0) AS was, (n_true + CASE WHEN x > 0 THEN -1 ELSE 1 END > 0) <> (weight > 0) AS now FROM one)
        SELECT aid, sum(CASE WHEN now AND NOT was THEN c ELSE 0 END) AS make, sum(CASE WHEN was AND NOT now THEN c ELSE 0 END) AS mend,
               sum(CASE WHEN now AND NOT was THEN c WHEN was AND NOT now THEN -c ELSE 0 END) AS delta FROM turned GROUP BY aid"""
    out["active_closure_rc"] = f"""{rc}, part AS (SELECT cid, weight, unnest(lits) AS x FROM cl),
        grow AS (SELECT aid FROM (SELECT abs(x) AS aid FROM part WHERE cid IN (SELECT cid FROM cl WHERE (weight > 0 AND len(list_filter(lits, lambda x: x < 0)) = 0) OR (weight < 0 AND len(list_filter(lits, lambda x: x < 0)) > 0)))
                 UNION SELECT abs(p.x) FROM grow JOIN part n ON abs(n.x) = grow.aid JOIN cl c ON c.cid = n.cid JOIN part p ON p.cid = c.cid
                       WHERE (c.weight > 0 AND n.x < 0 AND len(list_filter(c.lits, lambda v: v < 0)) = 1) OR (c.weight < 0 AND n.x > 0))
        SELECT rule, {o.LITS}, weight FROM cl JOIN (
          SELECT cid, bool_or(x < 0 AND aid IS NULL) AS blocked, bool_or(x < 0 OR aid IS NOT NULL) AS moved
          FROM part LEFT JOIN (SELECT DISTINCT aid FROM grow) g ON aid = abs(x) GROUP BY cid) USING (cid)
        WHERE CASE WHEN weight > 0 THEN NOT blocked ELSE moved END"""
    for lesion in ("order", "nested_loop", "merge", "broadcast", "shuffle_hash", "no_pushdown"):
        out[f"lesion_{lesion}"] = out["canonical_clauses_rc"]
    from ruleworld.plans import catalog_measures

    return out | similarity.oracle_sql() | stream.oracle_sql() | catalog_measures.oracle_sql()
