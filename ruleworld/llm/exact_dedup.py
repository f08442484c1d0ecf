"""Exact deduplication over a log-structured merge index of text digests.

Tasks fill bounded memtables of SHA-256 digests and flush them as sorted runs; runs meet by digest in an index of
levels of sorted runs, each with a filter. Hot digests shrink to one entry a memtable before anything is shuffled.
Compaction leaves a digest one entry (the row that stays, the number of rows); digests that the filters of all other
runs deny have one row and skip it. Digests with several rows are hits: their texts are compared
byte by byte, by grouping on the text itself, which collapses equal copies within a task before the shuffle. A
bitmap of bounded size of the hit digests keeps the texts of all other rows out of that shuffle. Should a digest ever hold
different texts, its rows are grouped by text instead.

Edge cases: a null text counts as the empty text; a null id is below every other id, and stays only if its group
has no other; of repeated rows that tie on the id exactly one stays; an empty table gives an empty result; further
columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.tokens import forget
from ruleworld.llm.sift import bitmap, maybe_in, numbered, without
from ruleworld.sources.scratch import settle

ENTRY = "digest binary, has_id boolean, id bigint, rid bigint, n bigint"


class DigestFilter:
    """Bloom filter whose positions are words of the digests, which are uniform already."""

    def __init__(self, digests: list[bytes], bits_each: int = 12, hashes: int = 4):
        self.size, self.hashes = max(64, len(digests) * bits_each), hashes
        self.bits = np.zeros(self.size, bool)
        for places in self._places(digests):
            self.bits[places] = True

    def _places(self, digests: list[bytes]) -> Iterator[np.ndarray]:
        if not digests:
            return
        words = np.frombuffer(b"".join(d.ljust(32, b"\0") for d in digests), "<u8").reshape(-1, 4)
        low, step = words[:, 0], words[:, 1] ^ words[:, 3] | np.uint64(1)
        for k in range(self.hashes):
            yield ((low + np.uint64(k) * step) % np.uint64(self.size)).astype(np.int64)

    def holds(self, digests: list[bytes]) -> np.ndarray:
        """False for digests that are surely not in it."""
        out = np.ones(len(digests), bool)
        for places in self._places(digests):
            out &= self.bits[places]
        return out


class SortedRun:
    """Immutable run: digests in order, their entries, and a filter."""

    def __init__(self, items: list[tuple[bytes, tuple]]):
        self.digests = [k for k, _ in items]
        self.entries = [v for _, v in items]
        self.filter = DigestFilter(self.digests)

    def get(self, digest: bytes) -> tuple | None:
        if not self.filter.holds([digest])[0]:
            return None
        at = bisect_left(self.digests, digest)
        return self.entries[at] if at < len(self.digests) and self.digests[at] == digest else None


class DigestIndex:
    """Memtable over levels of sorted runs. An entry is ``((has_id, id, rid), rows)``."""

    def __init__(self, keep: str = "smallest", memtable: int = 200_000, fanout: int = 4):
        if keep not in ("smallest", "largest"):
            raise ValueError(f"keep is 'smallest' or 'largest', not {keep!r}")
        self.keep, self.limit, self.fanout = keep, memtable, fanout
        self.memtable: dict[bytes, tuple] = {}
        self.levels: list[list[SortedRun]] = []

    def merge(self, a: tuple | None, b: tuple | None) -> tuple | None:
        if a is None or b is None:
            return a or b
        (x, n), (y, m) = a, b
        if x[0] != y[0]:  # a row without id never beats one with an id
            return (x if x[0] else y), n + m
        return (min if self.keep == "smallest" else max)(x, y), n + m

    def put(self, digest: bytes, entry: tuple) -> None:
        self.memtable[digest] = self.merge(self.memtable.get(digest), entry)
        if len(self.memtable) >= self.limit:
            self.flush()

    def drain(self) -> list[tuple[bytes, tuple]]:
        """The memtable as a sorted run's items; empties it."""
        items, self.memtable = sorted(self.memtable.items()), {}
        return items

    def flush(self) -> None:
        if self.memtable:
            self._push(0, SortedRun(self.drain()))

    def _push(self, level: int, run: SortedRun) -> None:
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(run)
        if len(self.levels[level]) >= self.fanout:
            runs, self.levels[level] = self.levels[level], []
            self._push(level + 1, SortedRun(list(self._compact(runs))))

    def _compact(self, runs: list[SortedRun]) -> Iterator[tuple[bytes, tuple]]:
        return self._merged([zip(r.digests, r.entries, strict=True) for r in runs])

    def _merged(self, parts: list) -> Iterator[tuple[bytes, tuple]]:
        last, entry = None, None
        for digest, e in heapq.merge(*parts, key=lambda x: x[0]):
            if digest == last:
                entry = self.merge(entry, e)
                continue
            if last is not None:
                yield last, entry
            last, entry = digest, e
        if last is not None:
            yield last, entry

    def get(self, digest: bytes) -> tuple | None:
        found = self.memtable.get(digest)
        for run in (r for level in self.levels for r in level):
            found = self.merge(found, run.get(digest))
        return found

    def scan(self) -> Iterator[tuple[bytes, tuple]]:
        """All entries in digest order, each digest once."""
        self.flush()
        return self._compact([r for level in self.levels for r in level])

    def hits(self) -> Iterator[tuple[bytes, tuple]]:
        """Entries of digests with several rows, in digest order.

        An entry of one row whose digest no other run's filter holds is alone; it is left out before runs are merged.
        """
        self.flush()
        runs = [r for level in self.levels for r in level]
        left = []
        for r in runs:
            stays = np.fromiter((n > 1 for _, n in r.entries), bool, len(r.entries))
            for other in runs:
                if other is not r:
                    at = np.flatnonzero(~stays)
                    stays[at] = other.filter.holds([r.digests[k] for k in at.tolist()])
            at = np.flatnonzero(stays).tolist()
            left.append(zip([r.digests[k] for k in at], [r.entries[k] for k in at], strict=True))
        return ((d, e) for d, e in self._merged(left) if e[1] > 1)


def _batches(items, size: int = 20_000) -> Iterator[pa.RecordBatch]:
    part: list = []
    for item in items:
        part.append(item)
        if len(part) == size:
            yield _batch(part)
            part = []
    if part:
        yield _batch(part)


def _batch(items: list[tuple[bytes, tuple]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [
            pa.array([d for d, _ in items], pa.binary()),
            pa.array([e[0][0] for _, e in items], pa.bool_()),
            pa.array([e[0][1] for _, e in items], pa.int64()),
            pa.array([e[0][2] for _, e in items], pa.int64()),
            pa.array([e[1] for _, e in items], pa.int64()),
        ],
        names=["digest", "has_id", "id", "rid", "n"],
    )


def _rows(batches):
    for b in batches:
        yield from zip(*(b.column(c).to_pylist() for c in ("digest", "has_id", "id", "rid", "n")), strict=True)


def _flushing(keep: str, memtable: int):
    def flush(batches):
        forget()
        index = DigestIndex(keep, memtable)
        for digest, has_id, i, rid, n in _rows(batches):
            index.memtable[digest] = index.merge(index.memtable.get(digest), ((has_id, i, rid), n))
            if len(index.memtable) >= memtable:
                yield from _batches(index.drain())
        yield from _batches(index.drain())

    return flush


def _compacting(keep: str, memtable: int):
    def compact(batches):
        index = DigestIndex(keep, memtable)
        for digest, has_id, i, rid, n in _rows(batches):
            index.put(digest, ((has_id, i, rid), n))
        yield from _batches(index.hits())

    return compact


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "smallest", digest_bytes: int = 32, memtable: int = 200_000, row_col: str | None = None) -> DataFrame:
    """One row per row of ``docs``: ``rid, doc_id, keep_id, keep_rid, group_size, kept, text_sha256``.

    ``rid`` is the row's number: the column ``row_col``, or its place in the files (see ``sift.numbered``).
    ``digest_bytes`` below 32 shortens the index key only, to let tests meet collisions.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    placed = numbered(docs, "__rw_row") if row_col is None else docs.withColumn("__rw_row", F.col(row_col))
    source = placed.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("body"), F.col("__rw_row").alias("rid")).withColumn("text_sha256", F.sha2("body", 256))
    key = F.substring(F.unhex("text_sha256"), 1, digest_bytes)
    rows = settle(source.select("rid", "doc_id", "text_sha256", key.alias("digest")))
    seeds = rows.select("digest", F.col("doc_id").isNotNull().alias("has_id"), F.col("doc_id").alias("id"), "rid", F.lit(1).cast("long").alias("n"))
    runs = seeds.mapInArrow(_flushing(keep, memtable), ENTRY)
    hits = settle(runs.repartition("digest").mapInArrow(_compacting(keep, memtable), ENTRY))
    # verification: equal digests must mean equal bytes
    bits, words = bitmap(hits, "digest", hits.count())
    keyed = source.withColumn("digest", key)
    near = keyed.filter(maybe_in(bits, words, F.col("digest")))
    texts = near.groupBy("digest", "body").agg(F.count("*").alias("c")).groupBy("digest").agg(F.count("*").alias("texts"))
    clashing = settle(texts.filter("texts > 1").join(hits.select("digest"), "digest", "left_semi").select("digest"))
    choice = hits.select("digest", F.col("id").alias("g_id"), F.col("rid").alias("g_rid"), F.col("n").alias("g_n"))
    if not clashing.isEmpty():
        choice = choice.join(clashing, "digest", "left_anti")
        rank = F.struct(F.col("doc_id").isNotNull(), F.coalesce(F.col("doc_id") if keep == "largest" else -F.col("doc_id"), F.lit(0).cast("long")), F.col("rid") if keep == "largest" else -F.col("rid"))
        torn = keyed.join(clashing, "digest", "left_semi")
        best = torn.groupBy("digest", "body").agg(F.max_by(F.struct("doc_id", "rid"), rank).alias("b"), F.count("*").alias("g_n"))
        apart = torn.join(best, ["digest", "body"]).select("rid", "doc_id", "text_sha256", F.col("b.doc_id").alias("g_id"), F.col("b.rid").alias("g_rid"), "g_n")
        rest = rows.join(clashing, "digest", "left_anti")
    else:
        apart, rest = None, rows
    joined = rest.join(choice, "digest", "left").select("rid", "doc_id", "text_sha256", "g_id", "g_rid", "g_n")
    joined = joined.unionByName(apart) if apart is not None else joined
    alone = F.col("g_rid").isNull()
    return joined.select(
        "rid",
        "doc_id",
        F.when(alone, F.col("doc_id")).otherwise(F.col("g_id")).alias("keep_id"),
        F.coalesce("g_rid", "rid").alias("keep_rid"),
        F.coalesce("g_n", F.lit(1).cast("long")).alias("group_size"),
        (alone | (F.col("g_rid") == F.col("rid"))).alias("kept"),
        "text_sha256",
    )


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "largest") -> DataFrame:
    """The rows of ``docs`` that stay, with its columns only."""
    mark = "__rw_rid"
    placed = numbered(docs, mark)
    gone = settle(exact_groups(placed, id_col, text_col, keep, row_col=mark).filter("NOT kept").select(F.col("rid").alias(mark)))
    return without(placed, mark, gone).select(*[F.col(f"`{c}`") for c in docs.columns])
