"""Queries of measures, exhaustive grounding, splitting and packing invariants, and relational operators, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ruleworld.operators import field as views
from ruleworld.operators import measures, split
from ruleworld.plans import exhaustive, solve, workloads
from ruleworld.plans import ground as g
from ruleworld.plans import oracles as o
from ruleworld.plans.catalog import _canonical, _raw, _text, atoms, comps, field, program
from ruleworld.sources.scratch import settle, table

# Measures ------------------------------------------------------------------------------------------------------------


def potentials_rc(spark, sf_dir):
    """Potentials of the world where every atom is true, by rule."""
    f = field(spark, sf_dir, "rc")
    rows = measures.potentials(f, views.constant_world(f.clauses, True))
    return rows.groupBy("rule").agg(F.count("*").alias("clauses"), F.round(F.sum("potential"), 6).alias("potential"))


def log_partition_ie(spark, sf_dir):
    return measures.log_partition(field(spark, sf_dir, "ie"), comps(spark, sf_dir, "ie")).select(F.round("log_z", 3).alias("log_z"))


def world_probability_ie(spark, sf_dir):
    """Logarithm of the chance of the worlds where all atoms are false, and true."""
    f, c = field(spark, sf_dir, "ie"), comps(spark, sf_dir, "ie")
    out = None
    for value in (False, True):
        row = measures.world_probability(f, c, views.constant_world(f.clauses, value)).select(F.lit(value).alias("world"), F.round("log_probability", 3).alias("log_probability"))
        out = row if out is None else out.unionByName(row)
    return out


def prune_stats_rc(spark, sf_dir):
    return measures.prune_stats(program(spark, sf_dir, "rc")[0], atoms(spark, sf_dir, "rc"))


def neighbours_rc(spark, sf_dir):
    return measures.neighbours(field(spark, sf_dir, "rc").clauses)


def program_stats(spark, sf_dir):
    """Relations, rules, entities, evidence rows and query atoms of the workloads, and components of two."""
    rows = []
    for name in ("rc", "ie", "ie2", "lp"):
        p, at = program(spark, sf_dir, name)[0], atoms(spark, sf_dir, name)
        rows += [(name, k, v) for k, v in views.program_stats(p, at).items()]
    for name in ("rc", "ie"):
        rows.append((name, "components", comps(spark, sf_dir, name).select("comp").distinct().count()))
    return spark.createDataFrame(rows, "workload string, measure string, n long")


def held_out_accuracy_rc(spark, sf_dir):
    """Classes found for labelled documents whose labels every fifth was hidden."""
    made = workloads.classify_docs(spark, sf_dir, mask=True)
    found = solve.solve_map(*made, flips_per_atom=100, prove=True).filled("topic").select(F.col("a1").alias("doc_id"), F.col("a2").alias("cls"))
    known = table(spark, sf_dir, "labels").filter("doc_id % 5 = 0").groupBy("doc_id").agg(F.max("quality").alias("cls"))
    return measures.accuracy(found, known, "doc_id", "cls")


# Exhaustive grounding ------------------------------------------------------------------------------------------------


def _every(spark, sf_dir, name: str = "fig1") -> DataFrame:
    prog, evidence = program(spark, sf_dir, name)
    return exhaustive.ground_exhaustive(prog, exhaustive.domains_of(prog, evidence))


def exhaustive_equals_pruned(spark, sf_dir):
    """Costs of the two constant worlds by the pruned field, and by every instance of every rule."""
    f, every = field(spark, sf_dir, "fig1"), settle(_every(spark, sf_dir))
    out = None
    for value in (False, True):
        world = views.constant_world(f.clauses, value)
        whole = exhaustive.full_world(f.atoms, f.atoms.open_rows().select("aid", F.lit(value).alias("value")))
        for method, cost in (("pruned", views.world_cost(f, world)), ("exhaustive", exhaustive.exhaustive_cost(every, whole))):
            row = cost.select(F.lit(value).alias("world"), F.lit(method).alias("method"), "hard", "soft")
            out = row if out is None else out.unionByName(row)
    return out


def exhaustive_counts_fig1(spark, sf_dir):
    """Instances of the running example's rules on nations, every substitution of every variable."""
    return _every(spark, sf_dir, "flows").groupBy("rule").agg(F.count("*").alias("instances"))


# Splitting, packing, cuts --------------------------------------------------------------------------------------------


def pack_invariants_ie(spark, sf_dir):
    """Packed loads: nothing lost, no load of several components overfull, and no more loads than first-fit decreasing allows."""
    sizes = settle(views.component_sizes(field(spark, sf_dir, "ie").clauses, comps(spark, sf_dir, "ie")).select("comp", (F.col("atoms") + F.col("literals")).alias("size")))
    packed = settle(split.pack_components(sizes, 1000))
    stats = split.bin_stats(packed, 1000)
    whole = packed.agg(F.count("*").alias("components"), F.sum("size").cast("long").alias("size"))
    return whole.crossJoin(stats).select("components", "size", "overfull", (F.col("loads") <= F.ceil(F.col("lower_bound") * 11 / 9) + 1).alias("within_bound"))


def _split_invariants(name: str, beta: int):
    """Pieces: every atom in one, none above the bound, none across components, named by their least atom.

    ``has_cut`` tells that clauses are cut where the bound asks for it and nowhere else, so it holds on tables whose components all fit too.
    """

    def query(spark, sf_dir):
        clauses, c = field(spark, sf_dir, name).clauses, comps(spark, sf_dir, name)
        pieces = settle(split.split_bounded(clauses, c, float(beta)))
        held = pieces.groupBy("piece").agg(F.count("*").alias("atoms"), F.min("aid").alias("least"), F.countDistinct("comp").alias("comps"))
        told = held.agg(F.sum("atoms").alias("atoms"), F.count_if(F.col("atoms") > beta).alias("oversized"), F.count_if((F.col("least") != F.col("piece")) | (F.col("comps") > 1)).alias("misnamed"))
        cut = split.cuts_as_due(clauses, c, pieces, beta).select(F.col("as_due").alias("has_cut"))
        held = views.literals(clauses).join(pieces, "aid").agg(F.countDistinct("cid").alias("clauses"))
        return told.crossJoin(held).crossJoin(cut).select("atoms", "oversized", "misnamed", "clauses", "has_cut")

    return query


def bisection_nation_regions(spark, sf_dir):
    """Cut of the nations' flows when regions 0 and 1 stand against the others."""
    f, at = field(spark, sf_dir, "bis"), atoms(spark, sf_dir, "bis").tables["on"]
    region = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("a1"), (F.col("n_regionkey") > 1).cast("long").alias("piece"))
    return views.cut_stats(f.clauses, at.join(region, "a1").select("aid", "piece")).select("cut_clauses", "cut_weight", "clauses")


def bisection_exact_nation(spark, sf_dir):
    """The least cut of the flows among the 16 nations of least key into halves of 8, by trying all 12,870."""
    few = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("k"), F.row_number().over(Window.orderBy("n_nationkey")).alias("p")).filter("p <= 16")
    x, y = few.select(F.col("k").alias("x"), F.col("p").alias("i")), few.select(F.col("k").alias("y"), F.col("p").alias("j"))
    edges = workloads.nation_flows(spark, sf_dir).filter("x <> y").join(x, "x").join(y, "y").select("i", "j")
    halves = spark.range(1 << 16).filter(F.bit_count("id") == 8)
    side = lambda c: F.call_function("shiftright", F.col("id"), F.col(c) - 1).bitwiseAND(F.lit(1))
    cuts = halves.crossJoin(F.broadcast(edges)).groupBy("id").agg(F.count_if(side("i") != side("j")).alias("cut"))  # 12,870 halves by at most 240 edges
    return cuts.agg(F.min("cut").alias("cut"))


def active_round1_rc(spark, sf_dir):
    rows, _ = g.active_closure(field(spark, sf_dir, "rc").clauses, 1)
    return _text(rows.select("rule", "lits", "weight"))


def twins_search(spark, sf_dir):
    """Two-atom components, one a customer, each searched on its own: the sum of their costs is their number."""
    made = workloads.twin_atoms(spark, sf_dir, "customer")
    f = g.ground(*made)
    c = settle(views.components(f.clauses))
    found = solve.search_components(f.clauses, c, tries=4, budget="fixed", flips=100, schedule="round_robin", quantum=10)
    each = found.groupBy("comp").agg(F.max("hard").alias("hard"), F.max("soft").alias("soft"))
    return each.agg(F.count("*").alias("components"), F.sum("hard").cast("long").alias("hard"), F.round(F.sum("soft"), 6).alias("soft"))


# Relational operators ------------------------------------------------------------------------------------------------


def op_approx_distinct(spark, sf_dir):
    """Approximate against exact distinct counts: within a tenth."""
    ev = table(spark, sf_dir, "events")
    near = F.abs(F.approx_count_distinct("user_id", 0.02) - F.countDistinct("user_id")) <= 0.1 * F.countDistinct("user_id")
    return ev.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), near.alias("near"))


def op_grouping_sets(spark, sf_dir):
    seen, _ = workloads.event_rows(spark, sf_dir)
    kinds = [F.col("event_type"), F.col("band")]
    rows = seen.groupingSets([[kinds[0]], [kinds[1]], []], *kinds).agg(F.count("*").alias("n"))
    return rows.select(F.coalesce("event_type", F.lit("all")).alias("event_type"), F.coalesce("band", F.lit(-1)).alias("band"), "n")


def op_ranks(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    tie = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, sf_dir, "orders").select("o_orderkey", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.ntile(3).over(tie).alias("third"))


def op_set_ops(spark, sf_dir):
    """Customers and suppliers by nation: common, only the first's, with and without repeats."""
    c = table(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k"))
    s = table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))
    parts = {"intersect": c.intersect(s), "intersect_all": c.intersectAll(s), "except": c.subtract(s), "except_all": c.exceptAll(s)}
    out = None
    for name, rows in parts.items():
        row = rows.agg(F.count("*").alias("n"), F.coalesce(F.sum("k"), F.lit(0)).cast("long").alias("k")).select(F.lit(name).alias("op"), "n", "k")
        out = row if out is None else out.unionByName(row)
    return out


def op_unpivot(spark, sf_dir):
    seen, _ = workloads.event_rows(spark, sf_dir)
    wide = seen.groupBy("band").pivot("event_type", list(workloads.EVENT_TYPES)).agg(F.count(F.lit(1))).na.fill(0)
    return wide.unpivot("band", list(workloads.EVENT_TYPES), "event_type", "n").select("band", "event_type", "n")


def op_recursive(spark, sf_dir):
    """Nations that flows reach from the least one over ascending keys, in SQL."""
    workloads.nation_flows(spark, sf_dir).createOrReplaceTempView("rw_flows")
    return spark.sql(
        "WITH RECURSIVE r(k, steps) AS (SELECT min(x), 0 FROM rw_flows UNION ALL SELECT f.y, r.steps + 1 FROM r JOIN rw_flows f ON f.x = r.k WHERE f.y > r.k AND r.steps < 2) "
        "SELECT k, CAST(min(steps) AS BIGINT) AS steps FROM r GROUP BY k"
    )


def op_subquery(spark, sf_dir):
    """Customers above the mean balance of their nation who have an order, by nation, in SQL."""
    for name in ("customer", "orders"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"rw_{name}")
    return spark.sql(
        "SELECT c_nationkey, count(*) AS n FROM rw_customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM rw_customer d WHERE d.c_nationkey = c.c_nationkey) "
        "AND EXISTS (SELECT 1 FROM rw_orders WHERE o_custkey = c_custkey) GROUP BY c_nationkey"
    )


def op_strings(spark, sf_dir):
    """Pairs of part names that share their first word, by edit distance."""
    names = table(spark, sf_dir, "part").select(F.trim(F.lower("p_name")).alias("n")).distinct().withColumn("first", F.regexp_extract("n", r"^(\w+)", 1))
    a, b = names.alias("a"), names.alias("b")
    pairs = a.join(b, (F.col("a.first") == F.col("b.first")) & (F.col("a.n") < F.col("b.n")))
    return pairs.select(F.col("a.n").alias("n1"), F.col("b.n").alias("n2"), F.levenshtein("a.n", "b.n").cast("long").alias("edits"), F.md5("a.n").alias("hash"))


def op_structs(spark, sf_dir):
    """Counts by band as maps, added key by key over two halves of the types."""
    seen, _ = workloads.event_rows(spark, sf_dir)
    half = F.when(F.col("event_type").isin("click", "error"), "a").otherwise("b")
    counts = seen.groupBy(half.alias("h"), "band").agg(F.count("*").alias("n"))
    maps = counts.groupBy("h").agg(F.map_from_entries(F.collect_list(F.struct("band", "n"))).alias("m"))
    a, b = maps.filter("h = 'a'").select(F.col("m").alias("x")), maps.filter("h = 'b'").select(F.col("m").alias("y"))
    added = a.crossJoin(b).select(F.map_zip_with("x", "y", lambda k, p, q: F.coalesce(p, F.lit(0)) + F.coalesce(q, F.lit(0))).alias("m"))  # a row each
    return added.select(F.explode("m").alias("band", "n"))


def op_json_round(spark, sf_dir):
    """Properties read by schema, written back, and read again."""
    ev = table(spark, sf_dir, "events")
    schema = F.schema_of_json(F.lit('{"k": 1}'))
    twice = F.from_json(F.to_json(F.struct((F.from_json("props", schema)["k"] + 1).alias("k"))), schema)["k"]
    return ev.groupBy("event_type").agg(F.sum(twice).cast("long").alias("k"))


# -------------------------------------------------------------------------------------------------------------------------


def queries() -> dict:
    return {
        "potentials_rc": potentials_rc,
        "log_partition_ie": log_partition_ie,
        "world_probability_ie": world_probability_ie,
        "prune_stats_rc": prune_stats_rc,
        "neighbours_rc": neighbours_rc,
        "program_stats": program_stats,
        "held_out_accuracy_rc": held_out_accuracy_rc,
        "exhaustive_equals_pruned": exhaustive_equals_pruned,
        "exhaustive_counts_fig1": exhaustive_counts_fig1,
        "pack_invariants_ie": pack_invariants_ie,
        "split_invariants_rc": _split_invariants("rc", 20),
        "split_invariants_lp": _split_invariants("lp", 500),
        "bisection_nation_regions": bisection_nation_regions,
        "bisection_exact_nation": bisection_exact_nation,
        "active_round1_rc": active_round1_rc,
        "twins_search": twins_search,
        "ground_lp": _canonical("lp"),
        "ground_er2": _canonical("er2"),
        "ground_er3": _raw("er3", "r1", "r2", "r3"),
        "op_approx_distinct": op_approx_distinct,
        "op_grouping_sets": op_grouping_sets,
        "op_ranks": op_ranks,
        "op_set_ops": op_set_ops,
        "op_unpivot": op_unpivot,
        "op_recursive": op_recursive,
        "op_subquery": op_subquery,
        "op_strings": op_strings,
        "op_structs": op_structs,
        "op_json_round": op_json_round,
    }


_EVENTS = "e AS (SELECT event_type, CAST(least(floor(value / 50), 9) AS INT) AS band FROM events)"
_FLOWS = """f AS (SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS x, CAST(s_nationkey AS BIGINT) AS y
      FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey)"""


def oracle_sql() -> dict[str, str]:
    rc, ie = o.RC, o.IE
    active0 = """CASE WHEN weight > 0 THEN len(list_filter(lits, lambda x: x < 0)) = 0
                      ELSE len(list_filter(lits, lambda x: x < 0)) > 0 END"""
    zero = f"costs0 AS (SELECT comp, ln(sum(exp(-cost))) AS z FROM costs GROUP BY comp)"
    return {
        "potentials_rc": f"""{rc}, {o.world_cost('true')}
            SELECT rule, count(*) AS clauses, round(sum(CASE WHEN bad.cid IS NULL THEN 1.0 ELSE exp(-abs(cl.weight)) END), 6) AS potential
            FROM cl LEFT JOIN (SELECT cid FROM bad) bad USING (cid) GROUP BY rule""",
        "log_partition_ie": f"{ie}, {o.enumerated(12)}, {zero} SELECT round(sum(z), 3) AS log_z FROM costs0",
        "world_probability_ie": f"""{ie}, {o.enumerated(12)}, {zero},
            ends AS (SELECT comp, min(cost) FILTER (w = 0) AS none, min(cost) FILTER (w = (1 << CAST(n AS INT)) - 1) AS every FROM costs JOIN sized USING (comp) GROUP BY comp)
            SELECT false AS world, round(sum(-none - z), 3) AS log_probability FROM ends JOIN costs0 USING (comp)
            UNION ALL SELECT true, round(sum(-every - z), 3) FROM ends JOIN costs0 USING (comp)""",
        "prune_stats_rc": f"""{rc}, part AS (SELECT cid, weight, unnest(lits) AS x FROM cl),
            grow AS (SELECT aid FROM (SELECT abs(x) AS aid FROM part WHERE cid IN (SELECT cid FROM cl WHERE {active0}))
                     UNION SELECT abs(p.x) FROM grow JOIN part n ON abs(n.x) = grow.aid JOIN cl c ON c.cid = n.cid JOIN part p ON p.cid = c.cid
                           WHERE (c.weight > 0 AND n.x < 0 AND len(list_filter(c.lits, lambda v: v < 0)) = 1) OR (c.weight < 0 AND n.x > 0)),
            act AS (SELECT rule, count(*) AS active FROM cl JOIN (
                      SELECT cid, bool_or(x < 0 AND aid IS NULL) AS blocked, bool_or(x < 0 OR aid IS NOT NULL) AS moved
                      FROM part LEFT JOIN (SELECT DISTINCT aid FROM grow) g ON aid = abs(x) GROUP BY cid) USING (cid)
                    WHERE CASE WHEN weight > 0 THEN NOT blocked ELSE moved END GROUP BY rule),
            pre AS (SELECT 'r1' AS rule, count(*) AS n FROM topic x JOIN topic y ON x.doc_id = y.doc_id AND x.cls <> y.cls
                    UNION ALL SELECT 'r2', count(*) FROM cites, classes UNION ALL SELECT 'r3', count(*) FROM cites, classes
                    UNION ALL SELECT 'r4', count(*) FROM topic WHERE cls = 0),
            post AS (SELECT rule, count(*) AS n FROM raw WHERE len(lits) > 0 GROUP BY rule)
            SELECT rule, pre.n + CASE WHEN rule = 'r1' THEN (SELECT count(*) FROM topic) ELSE 0 END AS before, coalesce(post.n, 0) AS after, coalesce(active, 0) AS active
            FROM pre LEFT JOIN post USING (rule) LEFT JOIN act USING (rule)""",
        "neighbours_rc": f"""{rc}, part AS (SELECT cid, abs(unnest(lits)) AS aid FROM cl)
            SELECT a.aid, count(DISTINCT b.aid) AS neighbours FROM part a JOIN part b ON a.cid = b.cid AND a.aid <> b.aid GROUP BY a.aid""",
        "program_stats": f"""{rc}, {o.COMPONENTS},
            pairs AS (SELECT o_custkey AS c, l_suppkey AS s, count(DISTINCT o_orderkey) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL HAVING n >= 2),
            home AS (SELECT count(*) AS n FROM pairs JOIN customer ON c = c_custkey JOIN supplier ON s = s_suppkey WHERE c_nationkey = s_nationkey),
            alike AS (SELECT x, y FROM (SELECT c_custkey AS x, lead(c_custkey) OVER (PARTITION BY c_nationkey, c_mktsegment ORDER BY c_custkey) AS y FROM customer) WHERE y IS NOT NULL),
            gaps AS (SELECT count(*) AS n FROM (SELECT ts, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS ts2 FROM events) WHERE ts2 <= ts + INTERVAL 60 MINUTES),
            turns AS (SELECT DISTINCT conv_id, turn, role, CASE WHEN length(text) > 200 THEN 1 ELSE 0 END AS long FROM conversations),
            follows AS (SELECT DISTINCT conv_id, turn, t2 FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS t2 FROM conversations) WHERE t2 IS NOT NULL),
            told(workload, measure, n) AS (
              VALUES ('rc', 'relations', 3), ('rc', 'rules', 4), ('ie', 'relations', 3), ('ie', 'rules', 52), ('ie2', 'relations', 3), ('ie2', 'rules', 6), ('lp', 'relations', 4), ('lp', 'rules', 5)
              UNION ALL SELECT 'rc', 'evidence', (SELECT count(*) FROM (SELECT DISTINCT source, doc_id FROM documents)) + (SELECT count(*) FROM cites) + (SELECT count(*) FROM topic WHERE truth >= 0)
              UNION ALL SELECT 'rc', 'query_atoms', (SELECT count(*) FROM topic WHERE truth < 0)
              UNION ALL SELECT 'rc', 'entities', (SELECT count(DISTINCT doc_id) + count(DISTINCT source) + 2 FROM documents)
              UNION ALL SELECT 'rc', 'components', (SELECT count(DISTINCT comp) FROM comps)
              UNION ALL SELECT 'ie', 'evidence', (SELECT count(*) FROM events) + (SELECT n FROM gaps)
              UNION ALL SELECT 'ie', 'query_atoms', (SELECT count(*) FROM events)
              UNION ALL SELECT 'ie', 'entities', (SELECT count(*) + count(DISTINCT event_type) + count(DISTINCT CAST(least(floor(value / 50), 9) AS INT)) FROM events)
              UNION ALL SELECT 'ie', 'components', (SELECT count(*) FROM events) - (SELECT n FROM gaps)
              UNION ALL SELECT 'ie2', 'evidence', (SELECT count(*) FROM turns) + (SELECT count(*) FROM follows)
              UNION ALL SELECT 'ie2', 'query_atoms', (SELECT count(*) FROM (SELECT DISTINCT conv_id, turn FROM conversations))
              UNION ALL SELECT 'ie2', 'entities', (SELECT count(DISTINCT conv_id) + count(DISTINCT turn) + count(DISTINCT role) + count(DISTINCT long) FROM turns)
              UNION ALL SELECT 'lp', 'evidence', (SELECT count(*) FROM pairs) + (SELECT n FROM home) + (SELECT count(*) FROM alike)
              UNION ALL SELECT 'lp', 'query_atoms', (SELECT count(*) FROM pairs)
              UNION ALL SELECT 'lp', 'entities', (SELECT count(*) FROM (SELECT c FROM pairs UNION SELECT x FROM alike UNION SELECT y FROM alike)) + (SELECT count(DISTINCT s) + count(DISTINCT least(n, 3)) FROM pairs))
            SELECT workload, measure, CAST(n AS BIGINT) AS n FROM told""",
        "exhaustive_equals_pruned": """SELECT world, method, CAST(hard AS BIGINT) AS hard, CAST(soft AS DOUBLE) AS soft
            FROM (VALUES (false, 0, 1.0), (true, 0, 33.0)) v(world, hard, soft), (VALUES ('pruned'), ('exhaustive')) m(method)""",
        "exhaustive_counts_fig1": """WITH d AS (SELECT (SELECT count(DISTINCT n_name) FROM nation) AS docs, (SELECT count(DISTINCT n_nationkey) FROM nation) AS urls, (SELECT count(DISTINCT r_name) FROM region) AS areas,
                   (SELECT count(DISTINCT c_mktsegment) FROM customer WHERE c_nationkey IN (SELECT n_nationkey FROM nation)) AS whos)
            SELECT unnest(['r1', 'r2', 'r3', 'r4', 'r5']) AS rule, unnest([docs * areas * areas, whos * docs * docs * areas, docs * docs * areas, docs * urls, docs]) AS instances FROM d""",
        "pack_invariants_ie": f"""{ie} SELECT (SELECT count(*) FROM events) - (SELECT count(*) FROM near) AS components,
            CAST((SELECT count(*) FROM events) + (SELECT sum(len(lits)) FROM cl) AS BIGINT) AS size, CAST(0 AS BIGINT) AS overfull, true AS within_bound""",
        "split_invariants_rc": f"""{rc} SELECT count(DISTINCT abs(x)) AS atoms, CAST(0 AS BIGINT) AS oversized, CAST(0 AS BIGINT) AS misnamed, (SELECT count(*) FROM cl) AS clauses, true AS has_cut
            FROM (SELECT unnest(lits) AS x FROM cl)""",
        "split_invariants_lp": f"""{o.LP} SELECT count(DISTINCT abs(x)) AS atoms, CAST(0 AS BIGINT) AS oversized, CAST(0 AS BIGINT) AS misnamed, (SELECT count(*) FROM cl) AS clauses, true AS has_cut
            FROM (SELECT unnest(lits) AS x FROM cl)""",
        "bisection_nation_regions": f"""WITH {_FLOWS}, r AS (SELECT CAST(n_nationkey AS BIGINT) AS k, n_regionkey > 1 AS side FROM nation),
            e AS (SELECT a.side <> b.side AS crosses FROM f JOIN r a ON a.k = x JOIN r b ON b.k = y WHERE x <> y)
            SELECT count(*) FILTER (crosses) AS cut_clauses, CAST(count(*) FILTER (crosses) AS DOUBLE) AS cut_weight, count(*) AS clauses FROM e""",
        "bisection_exact_nation": f"""WITH {_FLOWS}, few AS (SELECT CAST(n_nationkey AS BIGINT) AS k, p FROM (SELECT n_nationkey, row_number() OVER (ORDER BY n_nationkey) AS p FROM nation) WHERE p <= 16),
            e AS (SELECT a.p AS i, b.p AS j FROM f JOIN few a ON a.k = x JOIN few b ON b.k = y WHERE x <> y),
            h AS (SELECT w FROM (SELECT unnest(generate_series(0, 65535)) AS w) WHERE bit_count(w) = 8)
            SELECT min(cut) AS cut FROM (SELECT w, count(*) FILTER ((w >> (i - 1)) & 1 <> (w >> (j - 1)) & 1) AS cut FROM h, e GROUP BY w)""",
        "active_round1_rc": f"""{rc}, part AS (SELECT cid, unnest(lits) AS x FROM cl),
            first AS (SELECT DISTINCT abs(x) AS aid FROM part JOIN (SELECT cid FROM cl WHERE {active0}) USING (cid)),
            told AS (SELECT cid, bool_or(x < 0 AND aid IS NULL) AS blocked, bool_or(x < 0 OR aid IS NOT NULL) AS moved FROM part LEFT JOIN first ON aid = abs(x) GROUP BY cid)
            SELECT rule, {o.LITS}, weight FROM cl JOIN told USING (cid) WHERE CASE WHEN weight > 0 THEN NOT blocked ELSE moved END""",
        "twins_search": "SELECT count(*) AS components, CAST(0 AS BIGINT) AS hard, CAST(count(*) AS DOUBLE) AS soft FROM customer",
        "ground_lp": f"{o.LP} SELECT rule, {o.LITS}, weight, multiplicity FROM cl",
        "ground_er2": f"{o.ER2} SELECT rule, {o.LITS}, weight, multiplicity FROM cl",
        "ground_er3": f"{o.ER3} SELECT rule, {o.LITS}, CAST(weight AS DOUBLE) AS weight FROM raw",
        "op_approx_distinct": "SELECT event_type, count(DISTINCT user_id) AS users, true AS near FROM events GROUP BY event_type",
        "op_grouping_sets": f"WITH {_EVENTS} SELECT coalesce(event_type, 'all') AS event_type, coalesce(band, -1) AS band, count(*) AS n FROM e GROUP BY GROUPING SETS ((event_type), (band), ())",
        "op_ranks": """SELECT o_orderkey, rank() OVER w AS rank, dense_rank() OVER w AS dense, ntile(3) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS third
            FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate)""",
        "op_set_ops": """WITH c AS (SELECT c_nationkey AS k FROM customer), s AS (SELECT s_nationkey AS k FROM supplier),
            u AS (SELECT 'intersect' AS op, k FROM (SELECT k FROM c INTERSECT SELECT k FROM s) UNION ALL SELECT 'intersect_all', k FROM (SELECT k FROM c INTERSECT ALL SELECT k FROM s)
                  UNION ALL SELECT 'except', k FROM (SELECT k FROM c EXCEPT SELECT k FROM s) UNION ALL SELECT 'except_all', k FROM (SELECT k FROM c EXCEPT ALL SELECT k FROM s))
            SELECT op, count(k) AS n, CAST(coalesce(sum(k), 0) AS BIGINT) AS k FROM (VALUES ('intersect'), ('intersect_all'), ('except'), ('except_all')) v(op) LEFT JOIN u USING (op) GROUP BY op""",
        "op_unpivot": f"WITH {_EVENTS}, b AS (SELECT DISTINCT band FROM e), t AS (SELECT DISTINCT event_type FROM e) SELECT b.band, t.event_type, count(e.band) AS n FROM b CROSS JOIN t LEFT JOIN e ON e.band = b.band AND e.event_type = t.event_type GROUP BY ALL",
        "op_recursive": f"""WITH RECURSIVE {_FLOWS}, r(k, steps) AS (SELECT min(x), 0 FROM f UNION ALL SELECT f.y, r.steps + 1 FROM r JOIN f ON f.x = r.k WHERE f.y > r.k AND r.steps < 2)
            SELECT k, CAST(min(steps) AS BIGINT) AS steps FROM r GROUP BY k""",
        "op_subquery": """SELECT c_nationkey, count(*) AS n FROM customer c WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer d WHERE d.c_nationkey = c.c_nationkey)
            AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) GROUP BY c_nationkey""",
        "op_strings": r"""WITH n AS (SELECT DISTINCT trim(lower(p_name)) AS n, regexp_extract(trim(lower(p_name)), '^(\w+)', 1) AS first FROM part)
            SELECT a.n AS n1, b.n AS n2, CAST(levenshtein(a.n, b.n) AS BIGINT) AS edits, md5(a.n) AS hash FROM n a JOIN n b ON a.first = b.first AND a.n < b.n""",
        "op_structs": f"WITH {_EVENTS} SELECT band, count(*) AS n FROM e GROUP BY band",
        "op_json_round": "SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT) + 1) AS BIGINT) AS k FROM events GROUP BY event_type",
    }
