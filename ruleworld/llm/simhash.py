"""SimHash near-duplicate groups by meet-in-the-middle ball hashing.

Two fingerprints within an even radius r share a variant within r / 2 of both, and two fingerprints that share such
a variant are within r of each other. So every distinct fingerprint emits all variants within r / 2, equal variants
meet, and the pairs found there are the links. The shuffle is by the leading bits of the variants: a fingerprint is
sent once to each cell that holds any of its variants, and the cell's task emits the variants of that cell only, so
that 2081 variants travel as a few dozen rows. In a cell, equal variants are found by sorting, each group of m
fingerprints is chained by m - 1 pairs instead of m (m - 1) / 2 (all of them are linked anyway), pairs are
deduplicated and verified, and only a spanning forest leaves the task. A task sorts its rows by cell and works off a few
cells at a time; cells with more variants than a fixed number are worked off in sub-cells of one more bit each, so memory
is bounded. The forests' components give groups.

Edge cases: null and empty texts, and texts without words, have fingerprint zero and are linked like any other;
texts below the shingle length are one shingle; a null id never names a group unless all ids of the group are
null; repeated rows come back as often as they went in; further columns are ignored.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.tokens import forget
from ruleworld.operators.connect import connect
from ruleworld.llm.sift import numbered, without
from ruleworld.sources.scratch import settle

SEED = 42
#: Variants that a cell should hold, and that a task sorts at once; rows of cells that a task holds at once, whole cells beyond.
CELL_VARIANTS, TASK_VARIANTS, TASK_ROWS = 2_000_000, 3_000_000, 1_000_000


def fingerprint(text: str | None, words: int = 4) -> int:
    """64-bit SimHash of the word shingles, each bit by majority over XXH64 values."""
    if not text:
        return 0
    tokens = text.encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII case and ASCII white space only
    n = len(tokens)
    if not n:
        return 0
    if n <= words:
        return xxhash.xxh64_intdigest(b" ".join(tokens), SEED)
    line = b" ".join(tokens)
    ends = np.cumsum(np.fromiter(map(len, tokens), np.int64, n) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    spans = zip(starts[: n - words + 1].tolist(), ends[words - 1 :].tolist(), strict=True)
    hash_of, count = xxhash.xxh64_intdigest, n - words + 1
    h = np.fromiter((hash_of(line[a:b], SEED) for a, b in spans), np.uint64, count)
    return majority(h)


def majority(h: np.ndarray) -> int:
    """The bits that are set in over half of the hashes."""
    ones = np.concatenate([np.bincount(h8, minlength=256) @ _BITS for h8 in h.view(np.uint8).reshape(-1, 8).T])
    return int.from_bytes(np.packbits(2 * ones > len(h), bitorder="little").tobytes(), "little")


_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little").astype(np.int64)


def _fingerprints(words: int):
    """The last column, a text, becomes its fingerprint."""

    def run(batches):
        forget()
        for b in batches:
            last = b.num_columns - 1
            values = np.fromiter((fingerprint(t, words) for t in b.column(last).to_pylist()), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([*b.columns[:last], pa.array(values.view(np.int64))], names=[*b.schema.names[:last], "fp"])

    return run


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 4) -> DataFrame:
    """``(doc_id, fp)``, the fingerprint as a signed long with the same bits."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), text_col).mapInArrow(_fingerprints(words), "doc_id bigint, fp bigint")


def flips(low: int, high: int, most: int) -> np.ndarray:
    """Masks that flip at most ``most`` of the bits low..high-1, fewest first."""
    return np.array([sum(1 << x for x in c) for k in range(most + 1) for c in combinations(range(low, high), k)], np.uint64)


class Forest:
    """Least-label union of numbered nodes, fed with arrays of pairs."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def find(self, x: np.ndarray) -> np.ndarray:
        r = self.root[x]
        while (up := self.root[r]).shape and (up != r).any():
            r = up
        return r

    def union(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.find(a), self.find(b)
            apart = a != b
            a, b = np.minimum(a[apart], b[apart]), np.maximum(a[apart], b[apart])
            np.minimum.at(self.root, b, a)

    def pairs(self) -> tuple[np.ndarray, np.ndarray]:
        x = np.arange(len(self.root))
        r = self.find(x)
        return r[r != x], x[r != x]


def cell_links(fps: np.ndarray, cell: int, bits: int, half: int, forest: Forest, at: np.ndarray, most: int = TASK_VARIANTS) -> None:
    """Unite the fingerprints ``fps`` (nodes ``at``) that share a variant within ``half`` whose leading ``bits`` are ``cell``."""
    lead = np.uint64(64 - bits)
    away = np.bitwise_count((fps >> lead) ^ np.uint64(cell)) if bits else np.zeros(len(fps), np.uint8)
    masks = [flips(0, 64 - bits, half - d) for d in range(half + 1)]
    by = [np.flatnonzero(away == d) for d in range(half + 1)]
    if sum(map(len, by)) < 2:
        return
    if sum(len(i) * len(m) for i, m in zip(by, masks, strict=True)) > most and bits < 64:
        for bit in (0, 1):
            near = np.concatenate(by)
            cell_links(fps[near], cell << 1 | bit, bits + 1, half, forest, at[near], most)
        return
    variants, owner = [], []
    for d, i in enumerate(by):
        if len(i):
            base = fps[i] if not bits else (np.uint64(cell) << lead if bits < 64 else np.uint64(cell)) | (fps[i] & np.uint64((1 << (64 - bits)) - 1))
            variants.append((base[:, None] ^ masks[d]).ravel())
            owner.append(np.repeat(i.astype(np.int32), len(masks[d])))
    v, o = np.concatenate(variants), np.concatenate(owner)
    order = np.argsort(v)
    v, o = v[order], o[order].astype(np.int64)
    same = np.flatnonzero(v[1:] == v[:-1])
    if not len(same):
        return
    pair = np.unique(np.minimum(o[same], o[same + 1]) * len(fps) + np.maximum(o[same], o[same + 1]))
    a, b = pair // len(fps), pair % len(fps)
    if (np.bitwise_count(fps[a] ^ fps[b]) > 2 * half).any():
        raise AssertionError("a shared variant joined fingerprints beyond the radius")
    forest.union(at[a], at[b])


def _cells(batches, rows: int):
    """Cells and fingerprints of sorted batches, in runs of whole cells that hold about so many ``rows``."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    size = 0
    for b in batches:
        cells, fps = b.column(0).to_numpy(), b.column(1).to_numpy().view(np.uint64)
        if size >= rows and len(cells):
            cut = int(np.searchsorted(cells, held[-1][0][-1], side="right"))  # what follows the last cell held
            held.append((cells[:cut], fps[:cut]))
            if cut < len(cells):
                yield tuple(np.concatenate(x) for x in zip(*held, strict=True))
                held, size = [], 0
            cells, fps = cells[cut:], fps[cut:]
        if len(cells):
            held.append((cells, fps))
            size += len(cells)
    if held:
        yield tuple(np.concatenate(x) for x in zip(*held, strict=True))


def _linking(bits: int, half: int, rows: int):
    def run(batches):
        for cells, fps in _cells(batches, rows):
            nodes, at = np.unique(fps, return_inverse=True)
            forest = Forest(len(nodes))
            edges = np.flatnonzero(np.concatenate(([True], cells[1:] != cells[:-1], [True])))
            for i, j in zip(edges[:-1], edges[1:], strict=True):
                cell_links(fps[i:j], int(cells[i]), bits, half, forest, at[i:j])
            a, b = forest.pairs()
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(nodes[a].view(np.int64)), pa.array(nodes[b].view(np.int64))], names=["u", "v"])

    return run


def ball_links(nodes: DataFrame, radius: int = 4, rows: int | None = None) -> DataFrame:
    """Links ``(u, v)`` between distinct fingerprints (column ``fp``) that span each group within ``radius`` steps."""
    if radius % 2 or radius < 2:
        raise ValueError("the radius must be even")
    half, n = radius // 2, nodes.count() if rows is None else rows
    each = len(flips(0, 64, half))
    bits = min(40, max(3, int(np.ceil(np.log2(max(1, n * each / CELL_VARIANTS))))))
    masks = F.array(*[F.lit(int(m)) for m in flips(0, bits, half)])
    lead = F.shiftrightunsigned("fp", 64 - bits)
    cells = nodes.select(F.explode(F.transform(masks, lambda m: lead.bitwiseXOR(m.cast("long")))).alias("cell"), "fp")
    return cells.repartition("cell").sortWithinPartitions("cell").mapInArrow(_linking(bits, half, TASK_ROWS), "u bigint, v bigint")


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 4, radius: int = 4) -> DataFrame:
    """``doc_id, fp, component_id``: the least id of all documents reachable over links, for every row."""
    prints = settle(fingerprints(docs, id_col, text_col, words))
    nodes = settle(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id")))
    roots = connect(ball_links(nodes, radius))
    placed = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    least = placed.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = placed.join(least, "root").select("fp", "component_id")
    return prints.join(named, "fp", "left").select("doc_id", "fp", "component_id")


def drop_near(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 4, radius: int = 4) -> DataFrame:
    """One row of each group stays: the one with the least id (the first row where ids repeat), all columns unchanged.

    Rows with a null id stay only where no row of their group has an id.
    """
    mark = "__rw_rid"
    placed = numbered(docs, mark)
    marked = placed.select(F.col(mark).alias("rid"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col))
    prints = settle(marked.mapInArrow(_fingerprints(words), "rid bigint, doc_id bigint, fp bigint"))
    order = F.struct(F.col("doc_id").isNull().alias("a"), F.col("doc_id").alias("b"), F.col("rid").alias("c"))
    nodes = settle(prints.groupBy("fp").agg(F.min(order).alias("best")))
    roots = connect(ball_links(nodes.select("fp"), radius))
    grouped = nodes.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    stay = grouped.groupBy("root").agg(F.min("best").alias("first"))
    place = grouped.join(stay, "root").select("fp", F.col("first.c").alias("stays"))
    gone = settle(prints.join(place, "fp").filter("rid <> stays").select(F.col("rid").alias(mark)))
    return without(placed, mark, gone).select(*[F.col(f"`{c}`") for c in docs.columns])
