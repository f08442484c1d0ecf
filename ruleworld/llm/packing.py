"""Packing of token sequences: first-fit decreasing over a tournament tree, in randomised groups.

Documents are tokenized at the scan and cut into pieces of a sequence's length and a rest. Documents go to groups by a
hash of their row's place, and each group is packed on its own: pieces by falling length, each into the first
sequence with room, found in a tree that holds the largest room of every subtree. Groups have a few thousand
documents at any corpus size, whatever ids are null or repeated. Only piece records are written and shuffled, never texts or ids.

Edge cases: a null or empty text is the end id alone; a null id is kept; repeated rows are packed each for itself;
ties in length go by id, start and checksum, so a retry packs alike; the same rows in other files are dealt to other
groups; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.ship import portions, small_batches, trim
from ruleworld.llm.sift import numbered
from ruleworld.llm.tokens import encoder as shared_encoder
from ruleworld.sources.scratch import settle

#: Words that a worker's encoder remembers, in each of two generations: a third of what one that does nothing else may.
MEMO = 100_000
PIECE = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint"
_NAMES = [x.split()[0] for x in PIECE.split(", ")]


class RoomTree:
    """Tournament tree over bins' free room; ``take`` finds the first bin with room and fills it."""

    def __init__(self, bins: int, capacity: int):
        self.leaves = 1 << max(0, bins - 1).bit_length()
        self.capacity, self.room = capacity, [capacity] * (2 * self.leaves)

    def take(self, need: int) -> tuple[int, int]:
        """Bin and the offset in it. Bins are as many as items, so one always has room."""
        room, node = self.room, 1
        while node < self.leaves:
            node *= 2
            if room[node] < need:
                node += 1
        offset = self.capacity - room[node]
        room[node] -= need
        place = node - self.leaves
        while node > 1:
            node >>= 1
            best = room[2 * node] if room[2 * node] >= room[2 * node + 1] else room[2 * node + 1]
            if room[node] == best:
                break
            room[node] = best
        return place, offset


def first_fit_decreasing(lengths, capacity: int) -> list[tuple[int, int]]:
    """``(bin, offset)`` of every item, in the order given; ties keep that order."""
    tree, out = RoomTree(len(lengths), capacity), [(0, 0)] * len(lengths)
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        if lengths[i] > capacity:
            raise ValueError(f"an item of {lengths[i]} does not fit {capacity}")
        out[i] = tree.take(lengths[i])
    return out


def _cutting(vocabulary: str, end_id: int, capacity: int):
    """``doc_id, pack_group, text`` become ``PIECE, pack_group``."""

    def cut(batches):
        trim()
        encoder, end = shared_encoder(vocabulary, MEMO), np.array([end_id], "<u4").tobytes()
        for b in portions(batches, 2000):
            rows = []
            for doc, group, ids in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), encoder.stream(b.column(2).to_pylist()), strict=True):
                ids += end
                total = len(ids) // 4
                for start in range(0, total, capacity):
                    part = memoryview(ids)[4 * start : 4 * (start + capacity)]
                    rows.append((doc, start, len(part) // 4, zlib.crc32(part), total, group))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in range(6)], names=[*_NAMES, "pack_group"])

    return cut


def pieces(docs: DataFrame, vocabulary: str, end_id: int, capacity: int, groups: int = 1, seed: int = 7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of at most ``capacity`` ids, and a random group of their row; every id, the end id included, lies in exactly one."""
    rows = numbered(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body")), "place")
    group = F.pmod(F.xxhash64("place", F.lit(seed)), F.lit(groups).cast("long"))
    return rows.select("doc_id", group.alias("pack_group"), "body").mapInArrow(_cutting(vocabulary, end_id, capacity), PIECE + ", pack_group bigint")


def _packing(capacity: int):
    def pack(t: pa.Table) -> pa.Table:
        t = t.sort_by([(c, "descending" if c == "length" else "ascending") for c in ("length", "doc_id", "start", "ids_crc32")])
        place = first_fit_decreasing(t.column("length").to_pylist(), capacity)
        group = t.column("pack_group")[0].as_py()
        seq = np.array([p for p, _ in place], np.int64) + (group << 32)
        return t.drop_columns("pack_group").append_column("sequence_id", pa.array(seq)).append_column("offset", pa.array([o for _, o in place], pa.int64()))

    return pack


def pack(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", end_id: int = 1, capacity: int = 2048, group_docs: int = 4096, seed: int = 7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a piece: where its ids are in its document, and where in which sequence.

    ``sequence_tokens`` is the sequence's fill and ``padded_to`` the length it is padded to: the capacity, but the fill
    itself where that is a power of two.
    """
    groups = max(1, -(-docs.count() // group_docs))
    with small_batches(docs.sparkSession):  # settled here, so that the whole texts are read under that setting
        dealt = settle(pieces(docs, vocabulary, end_id, capacity, groups, seed, id_col, text_col))
    return dealt.groupBy("pack_group").applyInArrow(_padding(_packing(capacity), capacity), PIECE + ", sequence_id bigint, offset bigint, sequence_tokens bigint, padded_to bigint")


def _padding(inner, capacity: int):
    def run(t: pa.Table) -> pa.Table:
        t = inner(t)
        seq, inverse = np.unique(t.column("sequence_id").to_numpy(), return_inverse=True)
        fill = np.bincount(inverse, weights=t.column("length").to_numpy(), minlength=len(seq)).astype(np.int64)
        padded = np.where(fill & (fill - 1) == 0, fill, capacity)
        return t.append_column("sequence_tokens", pa.array(fill[inverse])).append_column("padded_to", pa.array(padded[inverse]))

    return run
