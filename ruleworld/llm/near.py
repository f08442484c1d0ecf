"""Near-duplicate texts: SimHash balls propose, a prefix join completes, exact Jaccard similarity of word runs decides.

A text is the set of its runs of ``words`` words (64-bit hashes). Under one order of all runs, two sets of similarity
``least`` or more share a run among the first n - ceil(least n) + 1 of each, so only those prefixes travel, to the task
of each run. The order puts runs that are frequent in a bounded sample last; any order gives the same result. Pairs that
meet are dropped only if they cannot be similar, by their sizes, by the places of the shared run, or by parity bitmaps
of two to four bits a run (as many unlike bits as the sets have unlike runs at most, where unlike sets of any size
show more); the others are verified on the whole sets.

Groups are found in three rounds: first the links of fingerprints by meet-in-the-middle ball hashing (``simhash.py``) and,
for the few prefix runs of least hash of each text, the text with the least row number that has the run; then, over runs that many groups
hold, pairs next to each other by size; last all pairs that are not in one group by then, over runs that texts of several groups
hold. So the first two rounds take a number of pairs in proportion to the texts and their runs, however large their groups, and
no link between groups is lost. A pair is told of once for each stretch of runs it shares, not for each run. A ball of 4 of 64 bits alone
would miss most pairs of a similarity near 0.8.

Edge cases: texts without words are equal; texts of fewer words are one run; ASCII case and white space do not count.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.ship import landed, portions, ship
from ruleworld.llm.sift import bitmap, maybe_in, numbered, without
from ruleworld.llm.simhash import ball_links, majority
from ruleworld.llm.tokens import forget
from ruleworld.operators.connect import connect
from ruleworld.sources.scratch import settle

SEED = 42
#: 64-bit words of a parity bitmap at least; documents of the sample that tells frequent runs; times a frequent run is seen
#: there; prefix runs of a text that meet in the first round.
PARITY, SAMPLE, OFTEN, FEW = 8, 4000, 3, 8
#: 64-bit words at most of the bitmaps that travel to each run.
SHORT = 32
#: Prefix runs before a run by which it is told that a pair met before; groups of a run whose neighbours by size are compared
#: before all pairs are, and how many neighbours.
BEFORE, WIDE, NEXT = 4, 8, 2
MIX = np.uint64(0x9E3779B97F4A7C15)


def word_runs(text: str | None, words: int = 5) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``words`` words."""
    tokens = (text or "").encode("utf-8", "surrogatepass").lower().split()
    n = len(tokens) - words + 1
    if n <= 1:
        return np.array([xxhash.xxh64_intdigest(b" ".join(tokens), SEED)], np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, tokens), np.uint64, len(tokens))
    out = np.zeros(n, np.uint64)
    for k in range(words):
        out = (out ^ h[k : k + n]) * MIX
        out ^= out >> np.uint64(29)
    return np.unique(out)


def parity(runs: np.ndarray) -> np.ndarray:
    """A bitmap of 2 to 4 bits a run, 64 ``PARITY`` at least, in which each run turns one bit."""
    size = max(64 * PARITY, 2 << (len(runs) - 1).bit_length())
    odd = np.bincount((runs >> np.uint64(7)).astype(np.int64) & (size - 1), minlength=size) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)


class Bitmaps:
    """Bitmaps of several sizes, and the number of unlike bits of pairs: of different sizes, the larger is folded to the smaller.

    Sets that are similar enough are of like sizes, so that a bitmap is folded once at most; other pairs are not asked for.
    """

    def __init__(self, packed: list[bytes]):
        self.words = np.fromiter(map(len, packed), np.int64, len(packed)) // 8
        self.place: dict[int, np.ndarray] = {}
        self.bits: dict[int, np.ndarray] = {}
        for w in np.unique(self.words).tolist():
            own, above = np.flatnonzero(self.words == w), np.flatnonzero(self.words == 2 * w)
            parts = [np.frombuffer(b"".join(packed[k] for k in own), np.uint64).reshape(-1, w)]
            if len(above):
                whole = np.frombuffer(b"".join(packed[k] for k in above), np.uint64).reshape(-1, 2 * w)
                parts.append(whole[:, :w] ^ whole[:, w:])
            self.place[w] = np.full(len(packed), -1)
            self.place[w][np.concatenate([own, above])] = np.arange(len(own) + len(above))
            self.bits[w] = np.concatenate(parts)

    def unlike(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        out = np.zeros(len(i), np.int64)
        least = np.minimum(self.words[i], self.words[j])
        for w in np.unique(least).tolist():
            at, step = np.flatnonzero(least == w), max(1, (1 << 20) // w)
            for k in range(0, len(at), step):
                some = at[k : k + step]
                x, y = self.place[w][i[some]], self.place[w][j[some]]
                out[some] = np.bitwise_count(self.bits[w][x] ^ self.bits[w][y]).sum(axis=1, dtype=np.int64)
        return out


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, arrays)]).astype(np.int32)
    flat = np.concatenate(arrays) if arrays else np.zeros(0, np.uint64)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat.view(np.int64)))


def _telling(words: int):
    """``rid, text`` become ``rid, runs``."""

    def run(batches):
        forget()
        for b in portions(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), _lists([word_runs(t, words) for t in b.column(1).to_pylist()])], names=["rid", "runs"])

    return run


def _prefixes(shared, words: int, num: int, den: int):
    """``rid, doc_id, text`` become ``rid, doc_id, n, fp, parity, short, prefix, few``;
    ``short`` is ``parity`` folded to ``SHORT`` words, where it is longer."""

    def run(batches):
        forget()
        often, level = landed(shared)
        for b in portions(batches):
            n, bits, short, fps, heads, few = [], [], [], [], [], []
            for t in b.column(2).to_pylist():
                runs = word_runs(t, words)
                n.append(len(runs))
                bits.append((own := parity(runs)).tobytes())
                short.append(np.bitwise_xor.reduce(own.reshape(-1, SHORT), axis=0).tobytes() if len(own) > SHORT else bits[-1])
                fps.append(majority(runs))
                if len(often):
                    at = np.minimum(np.searchsorted(often, runs), len(often) - 1)
                    runs = runs[np.lexsort((runs, np.where(often[at] == runs, level[at], 0)))]
                heads.append(runs[: len(runs) + 1 + (-len(runs) * num) // den])
                few.append(np.sort(heads[-1])[:FEW])
            told = [pa.array(n, pa.int64()), pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(bits, pa.binary()), pa.array(short, pa.binary()), _lists(heads), _lists(few)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *told], names=["rid", "doc_id", "n", "fp", "parity", "short", "prefix", "few"])

    return run


def _meeting(batches):
    """Rows ``s, rid, pos, root`` of runs that texts of more than one group hold, and whether ``WIDE`` groups or more do."""
    got = [[b.column(k).to_numpy() for k in range(4)] for b in batches]
    if got:
        s, rid, pos, root = (np.concatenate(x) for x in zip(*got, strict=True))
        order = np.lexsort((root, s))
        s, rid, pos, root = (x[order] for x in (s, rid, pos, root))
        first = np.flatnonzero(np.concatenate(([True], s[1:] != s[:-1]))) if len(s) else np.zeros(0, int)
        if len(first):
            new = np.concatenate(([True], (s[1:] != s[:-1]) | (root[1:] != root[:-1])))
            groups = np.repeat(np.add.reduceat(new.astype(np.int64), first), np.diff(np.append(first, len(s))))
            keep = groups > 1
            if keep.any():
                yield pa.RecordBatch.from_arrays([pa.array(x[keep]) for x in (s, rid, pos, root, groups >= WIDE)], names=["s", "rid", "pos", "root", "wide"])


def possible(n, pos, bits: Bitmaps, i: np.ndarray, j: np.ndarray, num: int, den: int) -> np.ndarray:
    """False for pairs ``i, j`` that cannot be similar."""
    n1, n2, p1, p2 = n[i], n[j], pos[i], pos[j]
    both = n1 + n2
    ok = (np.minimum(n1, n2) * den >= num * np.maximum(n1, n2)) & ((1 + np.minimum(p1, p2) + np.minimum(n1 - p1, n2 - p2) - 1) * (num + den) >= num * both)
    at = np.flatnonzero(ok)
    ok[at] = bits.unlike(i[at], j[at]) * (num + den) <= both[at] * (den - num)
    return ok


def _whole_keys(batches, rows: int = 50_000):
    """Sorted batches in portions of about so many rows, all rows of a key (first column) in one."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in batches:
        if size >= rows and b.num_rows:
            cut = int(np.searchsorted(b.column(0).to_numpy(), held[-1].column(0)[-1].as_py(), side="right"))
            held.append(b.slice(0, cut))
            b = b.slice(cut)
            if b.num_rows:
                yield pa.Table.from_batches(held)
                held, size = [], 0
        if b.num_rows:
            held.append(b)
            size += b.num_rows
    if held:
        yield pa.Table.from_batches(held)


def _earlier(lists: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The last ``BEFORE`` runs before each row's as a matrix, and which of its places hold one."""
    lists = lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists
    ends = lists.offsets.to_numpy()
    number = np.diff(ends)
    held = np.arange(BEFORE) < number[:, None]
    runs = np.zeros((len(number), BEFORE), np.int64)
    runs[held] = lists.flatten().to_numpy()
    return runs, held


def _met_before(runs: np.ndarray, held: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Whether pairs share one of the runs just before: then they have met there."""
    out = np.zeros(len(i), bool)
    for a in range(BEFORE):
        for b in range(BEFORE):
            out |= (runs[i, a] == runs[j, b]) & held[i, a] & held[j, b]
    return out


def _pairing(num: int, den: int, most: int | None = None):
    """Pairs of texts of different groups that share a run and may be similar, a few runs at a time; ``most``: only of so many
    next to each other by size."""

    def portion(t: pa.Table) -> np.ndarray:
        s, rid, pos, n, root = (t.column(k).to_numpy() for k in range(5))
        order = np.lexsort((rid, n, s))
        s, rid, pos, n, root = (x[order] for x in (s, rid, pos, n, root))
        packed, found = t.column(5).to_pylist(), []
        runs, held = (x[order] for x in _earlier(t.column(6)))
        bits = Bitmaps([packed[k] for k in order.tolist()])
        i, k = np.arange(len(s)), 1
        while (most is None or k <= most) and len(i := i[i + k < len(s)]) and len(i := i[(s[i] == s[i + k]) & (n[i] * den >= num * n[i + k])]):
            x = i[root[i] != root[i + k]]  # sizes ascend, so a row that has met one too large meets no further
            if most is None:
                x = x[~_met_before(runs, held, x, x + k)]
            ok = possible(n, pos, bits, x, x + k, num, den)
            a, b = rid[x[ok]], rid[x[ok] + k]
            found.append(np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1), axis=0))
            k += 1
        return np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 2), np.int64)

    def run(batches):
        for t in _whole_keys(batches):
            pairs = portion(t)
            if len(pairs):
                yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["u", "v"])

    return run


def _likely(num: int, den: int):
    """Pairs ``u, v`` with sizes and bitmaps that do not rule similarity out."""

    def run(batches):
        for b in batches:
            n1, n2 = b.column(2).to_numpy(), b.column(3).to_numpy()
            at = np.flatnonzero(np.minimum(n1, n2) * den >= num * np.maximum(n1, n2))
            if len(at):
                near = b.take(pa.array(at))
                bits = Bitmaps(near.column(4).to_pylist() + near.column(5).to_pylist())
                x = np.arange(len(at))
                ok = bits.unlike(x, x + len(at)) * (num + den) <= (n1[at] + n2[at]) * (den - num)
                yield near.select(["u", "v"]).filter(pa.array(ok))

    return run


def _verified(num: int, den: int):
    def run(batches):
        for b in portions(batches):
            sides = [(c.offsets.to_numpy(), c.values.to_numpy()) for c in (b.column(2), b.column(3))]
            same = np.zeros(b.num_rows, np.int64)
            whole = np.zeros(b.num_rows, np.int64)
            for k in range(b.num_rows):
                x, y = (values[ends[k] : ends[k + 1]] for ends, values in sides)
                same[k] = len(np.intersect1d(x, y, assume_unique=True))
                whole[k] = len(x) + len(y) - same[k]
            ok = pa.array(same * den >= num * whole)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(same / whole)], names=["u", "v", "sim"]).filter(ok)

    return run


def _verify(docs: DataFrame, pairs: DataFrame, words: int, num: int, den: int) -> DataFrame:
    """``u, v, sim`` of the pairs that are similar; only the texts that they name leave the scan of ``rid, text``."""
    ids = settle(pairs.select(F.explode(F.array("u", "v")).alias("rid")).distinct())
    bits, size = bitmap(ids, "rid", ids.count())
    sets = settle(docs.filter(maybe_in(bits, size, F.col("rid"))).mapInArrow(_telling(words), "rid bigint, runs array<bigint>").join(ids, "rid", "left_semi"))
    one, two = sets.select(F.col("rid").alias("u"), F.col("runs").alias("x")), sets.select(F.col("rid").alias("v"), F.col("runs").alias("y"))
    return pairs.join(one, "u").join(two, "v").select("u", "v", "x", "y").mapInArrow(_verified(num, den), "u bigint, v bigint, sim double")


def _balls(told: DataFrame, radius: int = 4) -> DataFrame:
    """``u, v``: pairs of rows that span each group of fingerprints linked within the radius."""
    nodes = settle(told.groupBy("fp").agg(F.min("rid").alias("first")))
    links = ball_links(nodes.select("fp"), radius)
    ends = [nodes.select(F.col("fp").alias(a), F.col("first").alias(f"{a}_first")) for a in ("u", "v")]
    between = links.join(ends[0], "u").join(ends[1], "v").select(F.col("u_first").alias("u"), F.col("v_first").alias("v"))
    equal = told.join(nodes, "fp").filter("rid <> first").select(F.col("first").alias("u"), F.col("rid").alias("v"))
    return between.unionByName(equal).select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))


def _told(docs: DataFrame, words: int, num: int, den: int) -> DataFrame:
    """What is known of each text of ``rid, doc_id, text``."""
    spark, n = docs.sparkSession, docs.count()
    sample = docs.filter(F.pmod(F.xxhash64("rid"), F.lit(max(1, n // SAMPLE))) == 0).select("rid", "text")
    seen = sample.mapInArrow(_telling(words), "rid bigint, runs array<bigint>").select(F.explode("runs").alias("s")).groupBy("s").count().filter(F.col("count") >= OFTEN).collect()
    seen = sorted((r[0] % 2**64, r[1]) for r in seen)
    shared = ship(spark, (np.array([r[0] for r in seen], np.uint64), np.array([r[1] for r in seen], np.int64)))
    schema = "rid bigint, doc_id bigint, n bigint, fp bigint, parity binary, short binary, prefix array<bigint>, few array<bigint>"
    return settle(docs.select("rid", "doc_id", "text").mapInArrow(_prefixes(shared, words, num, den), schema))


def _met(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """Rows ``s, rid, pos`` of runs that several groups (``rid, root``) hold, with the group and whether many do."""
    grouped = rows.join(roots, "rid", "left").select("s", "rid", "pos", F.coalesce("root", "rid").alias("root"))
    return settle(grouped.repartition("s").mapInArrow(_meeting, "s bigint, rid bigint, pos bigint, root bigint, wide boolean"))


def _prefix_met(told: DataFrame, roots: DataFrame) -> DataFrame:
    grouped = told.select("rid", "prefix").join(roots, "rid", "left").select("rid", F.coalesce("root", "rid").alias("root"), "prefix")
    rows = grouped.select("rid", "root", F.posexplode("prefix").alias("pos", "s")).select("s", "rid", F.col("pos").cast("long").alias("pos"), "root")
    return settle(rows.repartition("s").mapInArrow(_meeting, "s bigint, rid bigint, pos bigint, root bigint, wide boolean"))


def _candidates(told: DataFrame, met: DataFrame, num: int, den: int, most: int | None = None) -> DataFrame:
    """``u, v``: pairs that share a run of ``met``, are in different groups, and may be similar."""
    at = F.col("pos").cast("int")
    before = F.slice("prefix", F.greatest(at - (BEFORE - 1), F.lit(1)), F.least(at, F.lit(BEFORE))).alias("before")
    known = met.join(told.select("rid", "n", "short", "prefix"), "rid").select("s", "rid", "pos", "n", "root", "short", before).repartition("s").sortWithinPartitions("s")
    return _filtered(told, settle(known.mapInArrow(_pairing(num, den, most), "u bigint, v bigint").distinct()), num, den)


def _filtered(told: DataFrame, pairs: DataFrame, num: int, den: int) -> DataFrame:
    """``u, v``: the pairs that sizes and whole bitmaps do not rule out."""
    one, two = (told.select(F.col("rid").alias(a), F.col("n").alias(f"n{a}"), F.col("parity").alias(f"p{a}")) for a in ("u", "v"))
    both = pairs.join(one, "u").join(two, "v").select("u", "v", "nu", "nv", "pu", "pv")
    return settle(both.mapInArrow(_likely(num, den), "u bigint, v bigint"))


def _first(told: DataFrame, num: int, den: int) -> DataFrame:
    """``u, v``: pairs of the first round that may be similar: a few for each text."""
    few = settle(told.select("rid", F.explode("few").alias("s")))
    least = few.groupBy("s").agg(F.min("rid").alias("u"), F.count("*").alias("c")).filter("c > 1").select("s", "u")
    stars = few.join(least, "s").filter("rid <> u").select("u", F.col("rid").alias("v"))
    return _filtered(told, _balls(told).unionByName(stars).distinct(), num, den)


def similar_pairs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, least: float = 0.8) -> DataFrame:
    """``u, v, sim``: all pairs of ids, ``u < v``, whose texts have a Jaccard similarity of ``least`` or more. Ids are distinct."""
    num, den = Fraction(str(least)).as_integer_ratio()
    rows = docs.select(F.col(id_col).cast("long").alias("rid"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    none = docs.sparkSession.createDataFrame([], "rid bigint, root bigint")
    told = _told(rows, words, num, den)
    return _verify(rows.select("rid", "text"), _candidates(told, _prefix_met(told, none), num, den), words, num, den)


def drop_near(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, least: float = 0.8) -> DataFrame:
    """One row of each group that links of ``least`` or more make stays: the one with the least id, all columns unchanged.

    Rows with a null id stay only where no row of their group has an id.
    """
    num, den = Fraction(str(least)).as_integer_ratio()
    mark = "__rw_rid"
    placed = numbered(docs, mark)
    rows = placed.select(F.col(mark).alias("rid"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    told, texts = _told(rows, words, num, den), rows.select("rid", "text")
    links = settle(_verify(texts, _first(told, num, den), words, num, den).select("u", "v"))
    roots = settle(connect(links).select(F.col("node").alias("rid"), "root"))
    met = _prefix_met(told, roots)
    links = links.unionByName(settle(_verify(texts, _candidates(told, met.filter("wide"), num, den, NEXT), words, num, den).select("u", "v")))
    roots = settle(connect(links).select(F.col("node").alias("rid"), "root"))
    met = _met(met.select("s", "rid", "pos"), roots)
    more = _verify(texts, _candidates(told, met, num, den), words, num, den).select("u", "v")
    roots = connect(links.unionByName(more)).select(F.col("node").alias("rid"), "root")
    order = F.struct(F.col("doc_id").isNull().alias("a"), F.col("doc_id").alias("b"), F.col("rid").alias("c"))
    known = settle(told.select("rid", "doc_id").join(roots, "rid"))
    stay = known.groupBy("root").agg(F.min(order).alias("best"))
    gone = settle(known.join(stay, "root").filter("rid <> best.c").select(F.col("rid").alias(mark)))
    return without(placed, mark, gone).select(*[F.col(f"`{c}`") for c in docs.columns])
