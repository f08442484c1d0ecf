"""The experiments' programs over the given tables. Each returns ``(Program, evidence)``; evidence are plain scans and joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ruleworld.functions import similarity
from ruleworld.operators.rank import running_total
from ruleworld.plans.ground import query_atoms
from ruleworld.plans.program import Program
from ruleworld.sources.scratch import settle, table


def unknown():
    return F.lit(-1).cast("tinyint").alias("truth")


def example_program(area: str) -> Program:
    """The five rules of the running example; ``area`` is the one that its last rule disfavours."""
    return Program.parse(
        f"""
        @closed item(doc string, url string)
        @closed authored(who string, doc string)
        @closed cites(doc string, doc string)
        @open topic(doc string, area string)
        5: topic(p, a) & topic(p, b) => a = b
        1: authored(w, p) & authored(w, q) & topic(p, a) => topic(q, a)
        2: topic(p, a) & cites(p, q) => topic(q, a)
        hard: item(p, u) => exists w: authored(w, p)
        -1: topic(p, '{area}')
        """
    )


def running_example(spark: SparkSession):
    program = example_program("Networking")
    docs = spark.createDataFrame([("P1", "u1"), ("P2", "u2"), ("P3", "u3")], "doc string, url string")
    areas = spark.createDataFrame([("DB",), ("Networking",)], "area string")
    known = spark.createDataFrame([("P2", "DB", 1)], "doc string, area string, truth int")
    return program, {
        "item": docs,
        "authored": spark.createDataFrame([("Joe", "P1"), ("Joe", "P2"), ("Jake", "P3")], "who string, doc string"),
        "cites": spark.createDataFrame([("P1", "P3")], "a string, b string"),
        "topic": query_atoms([docs.select("doc"), areas], known),
    }


def nations_example(spark: SparkSession, sf_dir: str):
    """The running example's rules on nations: customers' segments write them, orders cite the suppliers' nations, areas are regions."""
    nation = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_name").alias("doc"), "n_regionkey")
    region = table(spark, sf_dir, "region").select("r_regionkey", F.col("r_name").alias("area"))
    wrote = table(spark, sf_dir, "customer").join(nation, F.col("c_nationkey") == F.col("k")).select("c_mktsegment", "doc").distinct()
    x, y = nation.select(F.col("k").alias("x"), F.col("doc").alias("a")), nation.select(F.col("k").alias("y"), F.col("doc").alias("b"))
    cites = nation_flows(spark, sf_dir).filter("x <> y").join(x, "x").join(y, "y").select("a", "b")
    known = nation.filter("k % 2 = 0").join(region, F.col("n_regionkey") == F.col("r_regionkey")).select("doc", "area", F.lit(1).alias("truth"))
    return example_program("ASIA"), {
        "item": nation.select("doc", F.col("k").cast("string").alias("url")),
        "authored": wrote,
        "cites": cites,
        "topic": query_atoms([nation.select("doc"), region.select("area")], known),
    }


def doc_links(docs: DataFrame) -> DataFrame:
    """``d1, d2``: consecutive documents of a source and language, and equal texts next to each other by id."""
    seq = Window.partitionBy("source", "lang").orderBy("doc_id")
    same = Window.partitionBy("text").orderBy("doc_id")
    nxt = docs.select("doc_id", F.lead("doc_id").over(seq).alias("d2"))
    eq = docs.select("doc_id", F.lead("doc_id").over(same).alias("d2"))
    return nxt.unionByName(eq).filter("d2 IS NOT NULL").select(F.col("doc_id").alias("d1"), "d2").distinct()


def classify_docs(spark: SparkSession, sf_dir: str, author_rule: bool = False, mask: bool = False, copies: int = 1):
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text")
    labels = table(spark, sf_dir, "labels").select("doc_id", "quality")
    if copies > 1:
        shift = F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")
        docs = docs.select("*", shift).select((F.col("doc_id") + F.col("copy") * 10**9).alias("doc_id"), F.concat_ws("#", "source", "copy").alias("source"), "lang", F.concat_ws("#", "text", "copy").alias("text"))
        labels = labels.select("*", shift).select((F.col("doc_id") + F.col("copy") * 10**9).alias("doc_id"), "quality")
    if mask:
        labels = labels.filter("doc_id % 5 <> 0")
    text = """
        @closed authored(source string, doc bigint)
        @closed cites(doc bigint, doc bigint)
        @open topic(doc bigint, cls int)
        5: topic(d, a) & topic(d, b) => a = b
        1: topic(d, a) & cites(d, e) => topic(e, a)
        1: topic(e, a) & cites(d, e) => topic(d, a)
        -1: topic(d, 0)
        """
    if author_rule:
        text += "1: authored(s, d) & authored(s, e) & topic(d, a) => topic(e, a)"
    classes = spark.createDataFrame([(0,), (1,)], "cls int")
    known = labels.groupBy("doc_id").agg(F.max("quality").alias("q"))
    topic = docs.select("doc_id").distinct().crossJoin(classes).join(known, "doc_id", "left").select("doc_id", "cls", F.coalesce((F.col("cls") == F.col("q")).cast("tinyint"), F.lit(-1).cast("tinyint")).alias("truth"))
    return Program.parse(text), {"authored": docs.select("source", "doc_id").distinct(), "cites": doc_links(docs), "topic": topic}


def event_rows(spark: SparkSession, sf_dir: str, gap_minutes: int = 60) -> tuple[DataFrame, DataFrame]:
    """``event_id, event_type, band`` and neighbours ``e1, e2`` of a user within the gap."""
    ev = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    seq = Window.partitionBy("user_id").orderBy("ts", "event_id")
    near = ev.select("event_id", "ts", F.lead("event_id").over(seq).alias("e2"), F.lead("ts").over(seq).alias("ts2"))
    near = near.filter(F.expr(f"ts2 <= ts + INTERVAL {gap_minutes} MINUTES")).select(F.col("event_id").alias("e1"), "e2")
    band = F.least(F.floor(F.col("value") / 50), F.lit(9)).cast("int").alias("band")
    return ev.select("event_id", "event_type", band), near


def band_weight(kind: int, band: int) -> float:
    """Weight of an event type and value band; never zero, of both signs."""
    w = ((7 * kind + 3 * band) % 11 - 5) * 0.5
    return w if w else 0.25


EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def tag_events(spark: SparkSession, sf_dir: str, gap_minutes: int = 60):
    seen, near = event_rows(spark, sf_dir, gap_minutes)
    rules = []
    for k, kind in enumerate(EVENT_TYPES):
        for band in range(10):
            w = band_weight(k, band)
            rules.append(f"{abs(w)}: seen(e, '{kind}', {band}) => {'' if w > 0 else '!'}infield(e)")
    text = "@closed seen(event bigint, kind string, band int)\n@closed next_to(event bigint, event bigint)\n@open infield(event bigint)\n" + "\n".join(rules)
    text += "\n2: infield(e) & next_to(e, f) => infield(f)\n1.5: infield(f) & next_to(e, f) => infield(e)"
    return Program.parse(text), {"seen": seen, "next_to": near, "infield": seen.select("event_id", unknown())}


def tag_turns(spark: SparkSession, sf_dir: str):
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", F.when(F.length("text") > 200, 1).otherwise(0).alias("long"))
    near = turns.select("conv_id", "turn", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn")).alias("t2")).filter("t2 IS NOT NULL")
    program = Program.parse(
        """
        @closed said(conv bigint, turn bigint, role string, long int)
        @closed follows(conv bigint, turn bigint, turn bigint)
        @open topic(conv bigint, turn bigint)
        1: said(c, t, 'user', 1) => topic(c, t)
        0.5: said(c, t, 'user', 0) => !topic(c, t)
        0.75: said(c, t, 'assistant', 0) => !topic(c, t)
        0.25: said(c, t, 'assistant', 1) => topic(c, t)
        1: topic(c, t) & follows(c, t, u) => topic(c, u)
        1: topic(c, u) & follows(c, t, u) => topic(c, t)
        """
    )
    return program, {"said": turns, "follows": near, "topic": turns.select("conv_id", "turn", unknown()).distinct()}


def link_customers(spark: SparkSession, sf_dir: str, hard_key: bool = False):
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    cust, supp = table(spark, sf_dir, "customer"), table(spark, sf_dir, "supplier")
    pairs = orders.join(lines, orders.o_orderkey == lines.l_orderkey).groupBy(F.col("o_custkey").alias("c"), F.col("l_suppkey").alias("s")).agg(F.countDistinct("o_orderkey").alias("n")).filter("n >= 2")
    home = pairs.join(cust, pairs.c == cust.c_custkey).join(supp, pairs.s == supp.s_suppkey)
    ring = Window.partitionBy("c_nationkey", "c_mktsegment").orderBy("c_custkey")
    alike = cust.select(F.col("c_custkey").alias("x"), F.lead("c_custkey").over(ring).alias("y")).filter("y IS NOT NULL")
    program = Program.parse(
        f"""
        @closed bought(cust bigint, supp bigint, band int)
        @closed same_nation(cust bigint, supp bigint)
        @closed alike(cust bigint, cust bigint)
        @open preferred(cust bigint, supp bigint)
        {'hard' if hard_key else '3'}: preferred(c, s) & preferred(c, t) => s = t
        1: bought(c, s, 3) => preferred(c, s)
        0.5: bought(c, s, 2) => preferred(c, s)
        1: same_nation(c, s) => preferred(c, s)
        0.5: preferred(c, s) & alike(c, d) => preferred(d, s)
        """
    )
    band = F.least("n", F.lit(3)).cast("int")
    return program, {
        "bought": pairs.select("c", "s", band),
        "same_nation": home.filter("c_nationkey = s_nationkey").select("c", "s"),
        "alike": alike,
        "preferred": pairs.select("c", "s", unknown()),
    }


def dedup_parts(spark: SparkSession, sf_dir: str, block: tuple[str, ...] = ("p_name", "p_type"), transitive: bool = True):
    part = table(spark, sf_dir, "part")
    a, b = part.alias("a"), part.alias("b")
    cond = F.col("a.p_partkey") != F.col("b.p_partkey")
    for c in block:
        cond = cond & (F.col(f"a.{c}") == F.col(f"b.{c}"))
    pairs = a.join(b, cond).select(F.col("a.p_partkey").alias("p"), F.col("b.p_partkey").alias("q"), (F.abs(F.col("a.p_retailprice") - F.col("b.p_retailprice")) <= 10).alias("price"), (F.col("a.p_brand") == F.col("b.p_brand")).alias("brand"), (F.abs(F.col("a.p_size") - F.col("b.p_size")) <= 2).alias("near"))
    program = Program.parse(
        """
        @closed near_price(part bigint, part bigint)
        @closed same_brand(part bigint, part bigint)
        @closed near_size(part bigint, part bigint)
        @open same(part bigint, part bigint)
        2: near_price(p, q) => same(p, q)
        1: same_brand(p, q) => same(p, q)
        0.5: near_size(p, q) => same(p, q)
        -1: same(p, q)
        hard: same(p, q) => same(q, p)
        """
        + ("3: same(p, q) & same(q, r) => same(p, r)" if transitive else "")
    )
    return program, {
        "near_price": pairs.filter("price").select("p", "q"),
        "same_brand": pairs.filter("brand").select("p", "q"),
        "near_size": pairs.filter("near").select("p", "q"),
        "same": pairs.select("p", "q", unknown()),
    }


def blocked_pairs(rows: DataFrame, key: str, block: list[str], least: int = 256, most: int = 64) -> DataFrame:
    """``aid, p, q``: all ordered pairs of unlike keys of a block, numbered from 1 in the order of (p, q). Keys must be unique.

    A pair's number follows from how many pairs the keys before ``p`` have and from the place of ``q`` in its block, so pairs are
    neither sorted nor shuffled. A block is made in slices of ``least`` keys or more, ``most`` at most.
    """
    named = rows.select(key, *block).dropna()
    size = named.groupBy(*block).agg(F.count("*").alias("n")).filter("n > 1")
    counted = running_total(named.join(size, block), [key], F.col("n") - 1, "ends")
    groups = counted.groupBy(*block).agg(F.array_sort(F.collect_list(F.struct(F.col(key).alias("p"), F.col("ends")))).alias("m"), F.first("n").alias("n"))
    step = F.greatest(F.lit(least), F.ceil(F.col("n") / most)).cast("int")
    slices = groups.withColumn("step", step).select("m", "n", "step", F.explode(F.sequence(F.lit(1), F.col("n").cast("int"), F.col("step"))).alias("at"))
    tasks = max(8, 4 * rows.sparkSession.sparkContext.defaultParallelism)
    dealt = slices.select("m", "n", "at", F.slice("m", F.col("at"), F.col("step")).alias("some")).repartition(tasks)
    first = dealt.select("m", "n", "at", F.posexplode("some").alias("i", "x")).select("m", "n", (F.col("at") - 1 + F.col("i")).alias("i"), F.col("x.p").alias("p"), F.col("x.ends").alias("ends"))
    both = first.select("n", "i", "p", "ends", F.posexplode("m").alias("j", "y")).filter("i <> j")
    place = F.col("j") + (F.col("j") < F.col("i")).cast("int")
    return both.select((F.col("ends") - F.col("n") + 1 + place).cast("long").alias("aid"), "p", F.col("y.p").alias("q"))


def dedup_docs(spark: SparkSession, sf_dir: str, alike: float = 0.5, near: float = 0.8):
    """Which documents of different text are the same: candidates are texts with a five-word Jaccard similarity from ``alike`` on."""
    docs = table(spark, sf_dir, "documents")
    pairs = settle(similarity.jaccard_pairs(docs.select("doc_id", "text"), alike))
    both = pairs.select("d1", "d2", "sim").unionByName(pairs.select(F.col("d2").alias("d1"), F.col("d1").alias("d2"), "sim"))
    lang = docs.groupBy("doc_id").agg(F.min("lang").alias("lang"))
    spoken = both.join(lang.select(F.col("doc_id").alias("d1"), F.col("lang").alias("l1")), "d1").join(lang.select(F.col("doc_id").alias("d2"), F.col("lang").alias("l2")), "d2")
    program = Program.parse(
        """
        @closed near(doc bigint, doc bigint)
        @closed same_lang(doc bigint, doc bigint)
        @open same(doc bigint, doc bigint)
        2: near(p, q) => same(p, q)
        0.5: same_lang(p, q) => same(p, q)
        -1: same(p, q)
        hard: same(p, q) => same(q, p)
        3: same(p, q) & same(q, r) => same(p, r)
        """
    )
    return program, {"near": both.filter(F.col("sim") >= near).select("d1", "d2"), "same_lang": spoken.filter("l1 = l2").select("d1", "d2"), "same": both.select("d1", "d2", unknown())}


def dedup_vectors(spark: SparkSession, sf_dir: str, alike: float = 0.3, near: float = 0.4):
    """Which vectors are of one thing: candidates are found by a search from the vectors whose id is divisible by 100."""
    label = table(spark, sf_dir, "embeddings").select("vec_id", "label")
    pairs = settle(similarity.vector_pairs(spark, sf_dir, alike))
    both = pairs.unionByName(pairs.select(F.col("v2").alias("v1"), F.col("v1").alias("v2"), "sim")).distinct()
    told = both.join(label.select(F.col("vec_id").alias("v1"), F.col("label").alias("l1")), "v1").join(label.select(F.col("vec_id").alias("v2"), F.col("label").alias("l2")), "v2")
    program = Program.parse(
        """
        @closed near(vec bigint, vec bigint)
        @closed same_label(vec bigint, vec bigint)
        @open same(vec bigint, vec bigint)
        2: near(p, q) => same(p, q)
        1: same_label(p, q) => same(p, q)
        -1: same(p, q)
        hard: same(p, q) => same(q, p)
        """
    )
    return program, {"near": both.filter(F.col("sim") >= near).select("v1", "v2"), "same_label": told.filter("l1 = l2").select("v1", "v2"), "same": both.select("v1", "v2", unknown())}


def twin_atoms(spark: SparkSession, sf_dir: str, keys: str = "nation", n: int | None = None):
    name, key = {"nation": ("nation", "n_nationkey"), "supplier": ("supplier", "s_suppkey"), "customer": ("customer", "c_custkey")}[keys]
    k = table(spark, sf_dir, name).select(F.col(key).cast("long").alias("k"))
    k = k.filter(F.col("k") < n) if n else k
    program = Program.parse("@open left(k bigint)\n@open right(k bigint)\n1: left(k)\n1: right(k)\n-1: left(k) | right(k)")
    return program, {"left": k.select("k", unknown()), "right": k.select("k", unknown())}


def bridged_rings(spark: SparkSession, sf_dir: str):
    nation = table(spark, sf_dir, "nation").filter("n_regionkey IN (0, 1)").select(F.col("n_nationkey").cast("long").alias("k"), F.col("n_regionkey").cast("int").alias("r"))
    seq, whole = Window.partitionBy("r").orderBy("k"), Window.partitionBy("r")
    ring = nation.select("k", F.coalesce(F.lead("k").over(seq), F.min("k").over(whole)).alias("n"))
    ends = nation.groupBy("r").agg(F.min("k").alias("k"))
    bridge = ends.filter("r = 0").select(F.col("k").alias("x")).crossJoin(ends.filter("r = 1").select(F.col("k").alias("y")))
    program = Program.parse(
        """
        @closed ring(n bigint, n bigint)
        @closed bridge(n bigint, n bigint)
        @closed odd(n bigint)
        @closed third(n bigint)
        @open on(n bigint)
        2: on(x) & ring(x, y) => on(y)
        1: on(x) & bridge(x, y) => !on(y)
        0.75: odd(x) => on(x)
        1.25: third(x) => !on(x)
        0.5: on(x) & odd(x) & ring(x, y) => !on(y)
        """
    )
    return program, {"ring": ring, "bridge": bridge, "odd": nation.filter("k % 2 = 1").select("k"), "third": nation.filter("k % 3 = 0").select("k"), "on": nation.select("k", unknown())}


def nation_flows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``x, y``: nations of customers, and of the suppliers they ordered from."""
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    c, s = table(spark, sf_dir, "customer"), table(spark, sf_dir, "supplier")
    joined = o.join(li, o.o_orderkey == li.l_orderkey).join(c, o.o_custkey == c.c_custkey).join(s, li.l_suppkey == s.s_suppkey)
    return joined.select(F.col("c_nationkey").cast("long").alias("x"), F.col("s_nationkey").cast("long").alias("y")).distinct()


def graph_program(edges: DataFrame):
    """One rule whose field is the given graph: a node that is on turns on the nodes it links to."""
    program = Program.parse("@closed link(n bigint, n bigint)\n@open on(n bigint)\n1: on(x) & link(x, y) => on(y)")
    nodes = edges.select(F.col("x").alias("n")).unionByName(edges.select(F.col("y").alias("n"))).distinct()
    return program, {"link": edges.select("x", "y"), "on": nodes.select("n", unknown())}


def order_lines(spark: SparkSession, sf_dir: str, hard: bool = True):
    program = Program.parse(f"@closed placed(o bigint)\n@closed line(o bigint, n int)\n@open done(o bigint)\n{'hard' if hard else '2'}: placed(o) => exists n: line(o, n)\n1: done(o)")
    orders = table(spark, sf_dir, "orders").select("o_orderkey")
    return program, {"placed": orders, "line": table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber"), "done": orders.select("o_orderkey", unknown())}
