"""Similarities that entity rules take as evidence: shared words, shared shingles, cosine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ruleworld.sources.scratch import settle, table


def jaccard(a: Column, b: Column) -> Column:
    """Share of common elements of two sets; null for two empty ones."""
    both = F.size(F.array_intersect(a, b))
    return both / F.nullif(F.size(F.array_union(a, b)), F.lit(0))


def cosine(a: Column, b: Column) -> Column:
    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def part_tokens(spark, sf_dir) -> DataFrame:
    """Word similarity of distinct part names that share a word."""
    names = table(spark, sf_dir, "part").select(F.col("p_name").alias("n")).distinct().select("n", F.array_distinct(F.split(F.lower("n"), " ")).alias("w"))
    word = names.select("n", F.explode("w").alias("t"))
    a, b = word.alias("a"), word.alias("b")
    pairs = a.join(b, (F.col("a.t") == F.col("b.t")) & (F.col("a.n") < F.col("b.n"))).select(F.col("a.n").alias("n1"), F.col("b.n").alias("n2")).distinct()
    w1, w2 = names.select(F.col("n").alias("n1"), F.col("w").alias("w1")), names.select(F.col("n").alias("n2"), F.col("w").alias("w2"))
    return pairs.join(w1, "n1").join(w2, "n2").select("n1", "n2", F.round(jaccard(F.col("w1"), F.col("w2")), 6).alias("sim"))


#: Query vectors that are broadcast at once (64 numbers each: some 5 MB).
QUERY_BLOCK = 20_000


def vector_search(vectors: DataFrame, queries: DataFrame, least: float) -> DataFrame:
    """``v1, v2, sim``: every row whose cosine with a query vector is ``least`` or more. Queries go over all rows in blocks."""
    n = queries.count()
    out = None
    for k in range(max(1, -(-n // QUERY_BLOCK))):
        block = queries if n <= QUERY_BLOCK else queries.filter(F.pmod(F.xxhash64("vec_id"), F.lit(-(-n // QUERY_BLOCK))) == k)
        q, v = F.broadcast(block.alias("q")), vectors.alias("v")
        sim = F.round(cosine(F.col("q.embedding"), F.col("v.embedding")), 4)
        found = v.join(q, F.col("v.vec_id") != F.col("q.vec_id")).select(F.col("q.vec_id").alias("v1"), F.col("v.vec_id").alias("v2"), sim.alias("sim")).filter(F.col("sim") >= least)
        out = found if out is None else out.unionByName(found)
    return out


def vector_pairs(spark, sf_dir, least: float = 0.3) -> DataFrame:
    """Vectors near those whose id is divisible by 100."""
    v = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return vector_search(v, v.filter("vec_id % 100 = 0"), least)


def shingles(text: Column, k: int = 5) -> Column:
    """Distinct hashes of runs of ``k`` words."""

    def runs(words: Column) -> Column:
        places = F.sequence(F.lit(1), F.greatest(F.size(words) - k + 1, F.lit(1)))
        return F.array_distinct(F.transform(places, lambda p: F.array_join(F.slice(words, p, k), " ")))

    # a one-element array around the words makes them a bound variable, split once a text
    return F.element_at(F.transform(F.array(F.filter(F.split(text, r"\s+"), lambda w: w != "")), runs), 1)


def members(docs: DataFrame) -> DataFrame:
    """``doc_id, rep``: the least id of the documents of the same text."""
    text = F.coalesce("text", F.lit(""))
    reps = docs.groupBy(text.alias("t")).agg(F.min("doc_id").alias("rep"))
    return docs.select("doc_id", text.alias("t")).join(reps, "t").select("doc_id", "rep")


def jaccard_pairs(docs: DataFrame, least: float = 0.8, k: int = 5) -> DataFrame:
    """``d1, d2, n, sim``: all pairs of distinct texts (named by their least id) whose sets of runs of ``k`` words have a
    Jaccard similarity of ``least`` or more.

    Under one order of all runs, rarest first, two such sets share a run among the first size - ceil(least * size) + 1 of
    each; those alone meet. Pairs that sizes or places rule out go, the others are verified on the whole sets.
    """
    text = F.coalesce("text", F.lit(""))
    texts = docs.groupBy(text.alias("t")).agg(F.min("doc_id").alias("rep"))
    hashed = texts.select("rep", F.array_distinct(F.transform(shingles(F.col("t"), k), lambda x: F.xxhash64(x))).alias("s"))
    # a run is sent once, and only those that several texts hold go on: the others come first in the order, so their number is enough
    runs = hashed.select("rep", F.size("s").alias("size"), F.explode("s").alias("h"))
    met = runs.withColumn("df", F.count("*").over(Window.partitionBy("h"))).filter("df > 1")
    by = Window.partitionBy("rep")
    alone = F.col("size") - F.count("*").over(by)
    placed = met.withColumn("place", F.row_number().over(by.orderBy("df", "h")) + alone)
    head = settle(placed.filter(F.col("place") <= F.col("size") - F.ceil(F.col("size") * least) + 1).select("h", "rep", "place", "size"))
    a, b = head.alias("a"), head.alias("b")
    both = F.col("a.size") + F.col("b.size")
    most = F.least("a.place", "b.place") + F.least(F.col("a.size") - F.col("a.place"), F.col("b.size") - F.col("b.place"))
    likely = (F.least("a.size", "b.size") >= least * F.greatest("a.size", "b.size")) & (most >= both * least / (1 + least) - 1e-9)
    pairs = settle(a.join(b, (F.col("a.h") == F.col("b.h")) & (F.col("a.rep") < F.col("b.rep")) & likely).select(F.col("a.rep").alias("d1"), F.col("b.rep").alias("d2")).distinct())
    named = pairs.select(F.explode(F.array("d1", "d2")).alias("rep")).distinct()
    wanted = docs.groupBy(text.alias("t")).agg(F.min("doc_id").alias("rep")).join(named, "rep", "left_semi")
    sets = settle(wanted.select("rep", F.array_distinct(F.transform(shingles(F.col("t"), k), lambda x: F.xxhash64(x))).alias("s")))
    x, y = sets.select(F.col("rep").alias("d1"), F.col("s").alias("x")), sets.select(F.col("rep").alias("d2"), F.col("s").alias("y"))
    told = pairs.join(x, "d1").join(y, "d2").withColumn("n", F.size(F.array_intersect("x", "y")).cast("long"))
    sim = F.col("n") / (F.size("x") + F.size("y") - F.col("n"))
    return told.select("d1", "d2", "n", F.round(sim, 6).alias("sim")).filter(F.col("sim") >= least)


def doc_pairs(spark, sf_dir) -> DataFrame:
    return jaccard_pairs(table(spark, sf_dir, "documents"))


def doc_members(spark, sf_dir) -> DataFrame:
    return members(table(spark, sf_dir, "documents"))


#: Pairs ``d1, d2, n, sim`` of distinct texts by brute force over shared runs, in SQL.
JACCARD_SQL = r"""t AS (SELECT coalesce(text, '') AS t, min(doc_id) AS rep FROM documents GROUP BY ALL),
w AS (SELECT rep, list_filter(regexp_split_to_array(t, '\s+'), lambda x: x <> '') AS w FROM t),
s AS (SELECT DISTINCT rep, array_to_string(w[i : i + 4], ' ') AS s FROM (SELECT *, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM w)),
z AS (SELECT rep, count(*) AS n FROM s GROUP BY rep),
jac AS (SELECT d1, d2, n, round(n / CAST(a.n1 + b.n2 - n AS DOUBLE), 6) AS sim
        FROM (SELECT a.rep AS d1, b.rep AS d2, count(*) AS n FROM s a JOIN s b ON a.s = b.s AND a.rep < b.rep GROUP BY ALL)
        JOIN (SELECT rep AS d1, n AS n1 FROM z) a USING (d1) JOIN (SELECT rep AS d2, n AS n2 FROM z) b USING (d2))"""

_DOT = "list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[]))"
_NORM = "list_dot_product(CAST({0}.embedding AS DOUBLE[]), CAST({0}.embedding AS DOUBLE[]))"
#: Vectors near those whose id is divisible by 100, in SQL.
COSINE_SQL = f"""cos AS (SELECT a.vec_id AS v1, b.vec_id AS v2, round({_DOT} / sqrt({_NORM.format("a")} * {_NORM.format("b")}), 4) AS sim
FROM embeddings a JOIN embeddings b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id)"""


def oracle_sql() -> dict[str, str]:
    return {
        "sim_tokens_part": """WITH n AS (SELECT DISTINCT p_name AS n, list_distinct(string_split(lower(p_name), ' ')) AS w FROM part)
            SELECT a.n AS n1, b.n AS n2, round(len(list_intersect(a.w, b.w)) / CAST(len(list_distinct(list_concat(a.w, b.w))) AS DOUBLE), 6) AS sim
            FROM n a JOIN n b ON a.n < b.n WHERE len(list_intersect(a.w, b.w)) > 0""",
        "sim_cosine": f"WITH {COSINE_SQL} SELECT * FROM cos WHERE sim >= 0.3",
        "sim_jaccard_docs": f"WITH {JACCARD_SQL} SELECT * FROM jac WHERE sim >= 0.8",
        "sim_doc_members": "SELECT doc_id, min(doc_id) OVER (PARTITION BY coalesce(text, '')) AS rep FROM documents",
    }
