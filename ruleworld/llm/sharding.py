"""Minimax contiguous partition of ordered atomic groups into shards, with DataFrame functions only.

Groups (equal texts) are ordered by their least id; a group's size is the sum of its rows' sizes. The smallest shard
capacity for which greedy filling needs no more than the given number of shards is found by binary search, and the
groups are cut where greedy filling with that capacity cuts. The running totals of the sizes ("ends") are computed in
Spark and stay there; the driver searches on a bounded list of ends. It first asks for the first and last end of each of
a fixed number of equal bins of the byte axis, bounds the capacity and every cut from below and above, and asks again
for finer bins, only where cuts can lie, until all ends there are known. The answer is exact at any number of groups.

Law ``bytes``: the largest shard is as small as contiguous atomic groups allow.

Edge cases: a null text has no bytes and equals only other null texts, not the empty text; a null id sorts before all
ids; repeated rows each take a slot; no rows give no shards; fewer groups than shards leave the last shards empty.
"""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.operators.rank import running_total
from ruleworld.sources.scratch import settle

BINS = 1 << 15


class Ends:
    """What the driver knows of the sorted ends: some of them, and between which others may lie."""

    def __init__(self, total: int):
        self.known, self.open = [0, total], {0}  # ``open``: known ends after which unknown ones may follow

    def learn(self, lo: int, hi: int, bins: list[tuple[int, int, int]]) -> None:
        """All ends in (lo, hi], as (first, last, count) of bins; lo and hi are known."""
        inside = [e for e in self.known if lo < e < hi]
        self.open -= {lo, *inside}
        found = sorted({x for f, t, _ in bins for x in (f, t)} | {lo, hi})
        self.open |= {f for f, t, n in bins if n > 2 and f < t}
        a, b = bisect_right(self.known, lo), bisect_right(self.known, hi)
        self.known[a - 1 : b] = found

    def cut(self, reach: int) -> tuple[int, int, bool]:
        """Bounds of the last end up to ``reach``, and whether they are sure to be equal."""
        at = bisect_right(self.known, reach) - 1
        e = self.known[at]
        if e == reach or e not in self.open:
            return e, e, True
        return e, reach, False

    def fill(self, capacity: int, shards: int, hopeful: bool) -> list[tuple[int, int, bool]]:
        """Greedy cuts from 0; each from the lower bound of the last, or from the upper if ``hopeful``."""
        p, out = 0, []
        for _ in range(shards):
            lo, hi, sure = self.cut(p + capacity)
            out.append((lo, hi, sure))
            to = hi if hopeful else lo
            if to == p and to < self.known[-1]:
                break
            p = to
        return out

    def least(self, shards: int, lo: int, hopeful: bool) -> int:
        """Smallest capacity from ``lo`` on whose cuts reach the last end."""
        total, hi = self.known[-1], self.known[-1]
        while lo < hi:
            mid = (lo + hi) // 2
            cuts = self.fill(mid, shards, hopeful)
            if cuts[-1][1 if hopeful else 0] >= total:
                hi = mid
            else:
                lo = mid + 1
        return lo


def minimax_cuts(ends: DataFrame, total: int, largest: int, shards: int, bins: int = BINS) -> list[int]:
    """Ends at which the shards end, for a column ``end`` of running totals; the last is ``total``."""
    know = Ends(total)
    spans = [(0, total)]
    while True:
        width = max(1, -(-sum(b - a for a, b in spans) // bins))
        for a, b in _asked(ends, spans, width):
            know.learn(a[0], a[1], b)
        low = know.least(shards, max(largest, -(-total // shards)), True)
        high = know.least(shards, low, False)
        near, far = know.fill(low, shards, False), know.fill(high, shards, True)
        if low == high and all(c[2] for c in near):
            return [c[0] for c in near]
        # between the earliest and the latest place of each cut, every gap that may hold unknown ends
        early, late, need = [c[0] for c in near], [c[1] for c in far], set()
        for k in range(max(len(early), len(late))):
            a = bisect_right(know.known, early[min(k, len(early) - 1)]) - 1
            b = bisect_right(know.known, late[min(k, len(late) - 1)])
            need |= {i for i in range(a, min(b, len(know.known) - 1)) if know.known[i] in know.open}
        spans = []
        for i in sorted(need):
            if spans and spans[-1][1] == know.known[i]:
                spans[-1] = (spans[-1][0], know.known[i + 1])
            else:
                spans.append((know.known[i], know.known[i + 1]))


def _asked(ends: DataFrame, spans: list[tuple[int, int]], width: int):
    """First, last and number of the ends in each bin of ``width`` of the spans; at most about twice BINS rows."""
    spark = ends.sparkSession
    asked = spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(spans)], "k int, a long, b long")
    inside = ends.join(F.broadcast(asked), (F.col("end") > F.col("a")) & (F.col("end") <= F.col("b"))) if len(spans) > 1 else ends.filter((F.col("end") > spans[0][0]) & (F.col("end") <= spans[0][1])).select("end", F.lit(0).alias("k"), F.lit(spans[0][0]).alias("a"))
    bins = inside.groupBy("k", F.floor((F.col("end") - F.col("a") - 1) / width).alias("w")).agg(F.min("end").alias("f"), F.max("end").alias("t"), F.count("*").alias("n"))
    by: dict[int, list] = {k: [] for k in range(len(spans))}
    for r in bins.select("k", "f", "t", "n").collect():
        by[r.k].append((r.f, r.t, r.n))
    return [(spans[k], sorted(v)) for k, v in by.items()]


def shard_rows(docs: DataFrame, shards: int = 40, id_col: str = "doc_id", text_col: str = "text", overhead: int = 16) -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard`` (and ``group_first``) of every row."""
    text = F.col(text_col)
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + overhead).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.coalesce(F.sha2(text, 256), F.lit("")).alias("group"),
    )
    rows = settle(rows)
    groups = rows.groupBy("group").agg(F.min(F.coalesce("doc_id", F.lit(-(2**63)))).alias("first"), F.sum("size").alias("bytes"))
    ends = settle(running_total(groups, ["first", "group"], F.col("bytes"), "end"))
    told = ends.agg(F.max("end").alias("total"), F.max("bytes").alias("largest")).first()
    cuts = minimax_cuts(ends.select("end"), told.total, told.largest, shards) if told.total else []
    shard = sum((F.when(F.col("end") > c, 1).otherwise(0) for c in cuts[:-1]), F.lit(0)).cast("int")
    placed = rows.join(ends.select("group", "first", shard.alias("shard")), "group")
    numbered = running_total(placed, ["shard", "first", "group", "doc_id"], F.lit(1).cast("long"), "slot", within=["shard"])
    return numbered.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("slot") - 1).alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "first")
