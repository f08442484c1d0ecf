"""Joins of wide rows with a set of marked keys, in which rows that are surely unmarked stay out of the shuffle.

A bitmap of bounded size holds two bits for every marked key. It is built by aggregation, reaches the scan as a scalar
subquery, and is tested in generated code. Rows that it does not hold pass at the scan; the others, few while marked
keys are few, meet the marked keys in a shuffled join, so the result is exact whatever the bitmap holds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleworld.sources.scratch import settle

#: 64-bit words of a bitmap at most (2 MB).
MOST_WORDS = 1 << 18


def bitmap(keys: DataFrame, key: str, rows: int) -> tuple[Column, int]:
    """The bitmap of a column as a scalar subquery, and its number of words, by the number of its ``rows``."""
    words = min(MOST_WORDS, max(64, 1 << (max(1, rows) // 4).bit_length()))
    places = keys.select(F.explode(F.array(*_places(F.col(key), words))).alias("p"))
    word = places.groupBy(F.floor(F.col("p") / 64).alias("w")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), (F.col("p") % 64).cast("int"))).alias("b"))
    filled = word.agg(F.map_from_entries(F.collect_list(F.struct("w", "b"))).alias("m"))
    full = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(words - 1).cast("long")), lambda w: F.coalesce(F.try_element_at("m", w), F.lit(0).cast("long")))
    return filled.select(full.alias("bits")).scalar(), words


def _places(key: Column, words: int) -> list[Column]:
    return [F.pmod(F.xxhash64(key, F.lit(k)), F.lit(64 * words).cast("long")) for k in (1, 2)]


def maybe_in(bits: Column, words: int, key: Column) -> Column:
    """False only if the key is surely not in the bitmap."""
    out = F.lit(True)
    for p in _places(key, words):
        word = F.element_at(bits, (F.floor(p / 64) + 1).cast("int"))
        out = out & (F.call_function("shiftright", word, (p % 64).cast("int")).bitwiseAND(F.lit(1).cast("long")) == 1)
    return out


def numbered(docs: DataFrame, name: str) -> DataFrame:
    """``docs`` with a number for every row that any second evaluation gives again.

    Over a plain scan of files that is the row's place; anything else is written to the shared folder first, for a
    shuffle may deal rows otherwise when a lost executor's part of it is made again.
    """
    todo, plain = [docs._jdf.queryExecution().optimizedPlan()], True
    while todo:
        node = todo.pop()
        plain = plain and node.nodeName().split("(")[0].strip() in ("Project", "Filter", "LogicalRelation", "Relation", "RelationV2", "DataSourceV2Relation", "DataSourceV2ScanRelation", "LocalRelation", "Union")
        todo += [node.children().apply(k) for k in range(node.children().size())]
    return (docs if plain else settle(docs)).withColumn(name, F.monotonically_increasing_id())


def without(rows: DataFrame, key: str, marked: DataFrame) -> DataFrame:
    """``rows`` whose ``key`` is not in ``marked``, a settled one-column table of the same name."""
    bits, words = bitmap(marked, key, marked.count())
    held = maybe_in(bits, words, F.col(key))
    return rows.filter(~held).unionByName(rows.filter(held).join(marked, key, "left_anti"))
