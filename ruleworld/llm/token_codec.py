"""Token ids in files of independently reset, checksummed blocks, compressed by an adaptive context-mixing range coder.

A block's ids are laid out as lanes: lane k holds a run of consecutive ids. Step s codes the s-th id of every lane
at once, each lane with a range coder of its own (64-bit low with carries, 32-bit words), all lanes with one shared
model that learns from the ids of a step before the next. The model predicts by order 2 (hash of the two ids before)
and order 1 (the id before), each with a candidate and a confidence, and by order 0 (adaptive frequencies). The three
are mixed: a table indexed by both confidences learns how often each candidate is right, and that share of the range
goes to the candidates, the rest to order 0. Every operation runs over all lanes, so the cost an id is small.

File: blocks one after another. Block: header (see ``HEADER``), lane lengths, lane words, document runs
(compressed); both checksums are verified on reading.

Documents are range-sorted by id, and by the start of the text and the row's place among equal ids, so that one id on
many rows makes several files; a task starts the next file when the written size passes a limit.

Edge cases: null and empty texts are the end id alone; a null id sorts first; ties of ids go by the text's first
characters; an empty table gives no files and an empty result; a document may span blocks, never files; a vocabulary
that leaves the frequencies no room is refused.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.ship import portions
from ruleworld.llm.sift import numbered
from ruleworld.llm.store import Store
from ruleworld.llm.tokens import encoder as shared_encoder
from ruleworld.sources.scratch import shared_dir

#: magic, ids, lanes, vocabulary size, bytes of lane words, bytes of document runs, crc32 of the ids, crc32 of the rest.
HEADER = "<4sIIIIIII"
MAGIC = b"RWB1"
BLOCK_IDS, LANES, LANE_IDS = 1 << 21, 4096, 128
#: Chunks in a generation of the encoder's memo: more than its default, for nothing else shares these workers.
MEMO = 500_000
TOTAL_BITS = 24
FLOOR = 16
_T = np.uint64(TOTAL_BITS)
_32 = np.uint64(32)
_WORD = np.uint64(0xFFFFFFFF)
_FULL, _ZERO, _ONE = np.uint64(1 << TOTAL_BITS), np.uint64(0), np.uint64(1)


class Mixer:
    """The shared adaptive model of a block. A slot holds ``candidate * 16 + confidence``; -16 is an empty one."""

    def __init__(self, vocabulary: int):
        if 2 * FLOOR * vocabulary > 1 << TOTAL_BITS:
            raise ValueError(f"a vocabulary of {vocabulary} ids is too large for {TOTAL_BITS} bits")
        self.size = vocabulary
        self.count = np.ones(vocabulary, np.int64)
        self.slots = [np.full(1 << 16, -16, np.int32), np.full(1 << 20, -16, np.int32)]
        self.right = [np.full(256, 0.2), np.full(256, 0.4)]
        self.seen = np.ones(256)
        self.step, self.fresh = 0, []
        self._refresh()

    def _refresh(self) -> None:
        """Take what the steps since the last call have shown into the frequencies and mixing shares."""
        if self.fresh:
            x, state, hit1, hit2 = (np.concatenate(c) for c in zip(*self.fresh, strict=True))
            self.count += np.bincount(x, minlength=self.size) * 24
            self.seen += np.bincount(state, minlength=256)
            self.right[1] += np.bincount(state[hit2], minlength=256)
            self.right[0] += np.bincount(state[hit1 & ~hit2], minlength=256)
            self.fresh = []
        room = (1 << TOTAL_BITS) - FLOOR * self.size
        freq = FLOOR + (self.count * (room / int(self.count.sum()))).astype(np.int64)
        self.cum = np.zeros(self.size + 1, np.uint64)
        np.cumsum(freq, out=self.cum[1:])
        self.cum[-1] = 1 << TOTAL_BITS
        m1, m2 = self.right[0] / self.seen, self.right[1] / self.seen
        scale = np.minimum(1.0, 0.9 / (m1 + m2)) * float(1 << TOTAL_BITS)
        self.mass = [(m1 * scale).astype(np.uint64), (m2 * scale).astype(np.uint64)]

    def look(self, p1: np.ndarray, p2: np.ndarray) -> None:
        """Candidates and their masses for contexts ``p1`` (last id) and ``p2`` (the one before)."""
        self.a = p1 & 0xFFFF
        self.b = (p1 * 0x9E3779B1 + p2 * 0x85EBCA6B >> 7) & 0xFFFFF
        self.v1, self.v2 = self.slots[0][self.a], self.slots[1][self.b]
        self.c1, self.c2 = self.v1 >> 4, self.v2 >> 4
        self.state = (self.v2 & 15) << 4 | self.v1 & 15
        self.m2 = self.mass[1][self.state] * (self.v2 >= 0)
        self.m1 = self.mass[0][self.state] * ((self.v1 >= 0) & (self.c1 != self.c2))
        self.base = self.m1 + self.m2
        self.rest = _FULL - self.base

    def span(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Start and width of ids ``x`` in the mixed range."""
        lo = self.base + (self.cum[x] * self.rest >> _T)
        wide = self.base + (self.cum[x + 1] * self.rest >> _T) - lo
        self.hit1, self.hit2 = x == self.c1, x == self.c2
        np.copyto(lo, self.m2, where=self.hit1)
        np.copyto(wide, self.m1, where=self.hit1)
        np.copyto(lo, _ZERO, where=self.hit2)
        np.copyto(wide, self.m2, where=self.hit2)
        return lo, wide

    def find(self, v: np.ndarray) -> np.ndarray:
        """Ids whose span holds ``v``."""
        x = np.where(v < self.m2, self.c2, self.c1).astype(np.int64)
        far = np.flatnonzero(v >= self.base)
        u = v[far] - self.base[far]
        u = ((u + _ONE << _T) - _ONE) // self.rest[far]
        order = np.argsort(u)  # in order, neighbouring searches read the same part of the table
        x[far[order]] = np.searchsorted(self.cum, u[order], side="right") - 1
        return x

    def learn(self, x: np.ndarray) -> None:
        """Confirmed candidates gain confidence, others lose half of it or, at none, give way."""
        self.fresh.append((x, self.state, self.hit1, self.hit2))
        new = (x << 4 | 1).astype(np.int32)
        for slots, at, v, hit in ((self.slots[0], self.a, self.v1, self.hit1), (self.slots[1], self.b, self.v2, self.hit2)):
            sure = v & 15
            slots[at] = np.where(hit, v + (sure < 15), np.where(sure == 0, new, v - (sure + 1 >> 1)))
        self.step += 1
        if self.step & (self.step - 1) == 0 or self.step % 16 == 0:
            self._refresh()


def encode_ids(ids: np.ndarray, vocabulary: int) -> tuple[int, bytes]:
    """Lanes, and the lanes' lengths and words."""
    n = len(ids)
    if not n:
        return 0, b""
    lanes = min(LANES, max(1, n // LANE_IDS))
    steps = -(-n // lanes)
    grid = np.zeros(lanes * steps, np.int64)
    grid[:n] = ids
    grid = np.ascontiguousarray(grid.reshape(lanes, steps).T)
    model, row = Mixer(vocabulary), np.arange(lanes)
    low, rng = np.zeros(lanes, np.uint64), np.full(lanes, 2**64 - 1, np.uint64)
    words, fill = np.zeros((lanes, steps + 2), np.uint64), np.zeros(lanes, np.int64)
    p1 = p2 = np.zeros(lanes, np.int64)
    for x in grid:
        model.look(p1, p2)
        start, wide = model.span(x)
        r = rng >> _T
        moved = low + r * start
        over = np.flatnonzero(moved < low)
        if len(over):
            words[over, fill[over] - 1] += np.uint64(1)
        low, rng = moved, r * wide
        out = np.flatnonzero(rng <= _WORD)
        words[out, fill[out]] = low[out] >> _32
        fill[out] += 1
        low[out] <<= _32
        rng[out] <<= _32
        model.learn(x)
        p2, p1 = p1, x
    words[row, fill] = low >> _32
    words[row, fill + 1] = low & _WORD
    fill += 2
    for k in range(words.shape[1] - 1, 0, -1):  # carries
        words[:, k - 1] += words[:, k] >> _32
    kept = words.astype("<u4")[np.arange(words.shape[1]) < fill[:, None]]
    return lanes, fill.astype("<u4").tobytes() + kept.tobytes()


def decode_ids(n: int, lanes: int, vocabulary: int, body: bytes) -> np.ndarray:
    if not n:
        return np.zeros(0, np.uint32)
    steps = -(-n // lanes)
    fill = np.frombuffer(body, "<u4", lanes).astype(np.int64)
    words = np.concatenate([np.frombuffer(body, "<u4", offset=4 * lanes).astype(np.uint64), np.zeros(1, np.uint64)])
    at = np.cumsum(fill) - fill
    model, rng = Mixer(vocabulary), np.full(lanes, 2**64 - 1, np.uint64)
    code = words[at] << _32 | words[at + 1]
    at += 2
    grid = np.zeros((steps, lanes), np.int64)
    p1 = p2 = np.zeros(lanes, np.int64)
    top = _FULL - _ONE
    for s in range(steps):
        model.look(p1, p2)
        r = rng >> _T
        x = model.find(np.minimum(code // r, top))
        start, wide = model.span(x)
        code -= r * start
        rng = r * wide
        more = np.flatnonzero(rng <= _WORD)
        code[more] = code[more] << _32 | words[at[more]]
        at[more] += 1
        rng[more] <<= _32
        model.learn(x)
        p2, p1 = p1, x
        grid[s] = x
    return grid.T.reshape(-1)[:n].astype(np.uint32)


def write_block(ids: np.ndarray, runs: list[tuple[int | None, int, bool]], vocabulary: int) -> bytes:
    """``runs``: document id, its number of ids here, and whether it ends here."""
    lanes, body = encode_ids(ids, vocabulary)
    doc = zlib.compress(b"".join(struct.pack("<?qI?", i is not None, i or 0, n, ends) for i, n, ends in runs), 6)
    rest = body + doc
    return struct.pack(HEADER, MAGIC, len(ids), lanes, vocabulary, len(body), len(doc), zlib.crc32(ids.astype("<u4").tobytes()), zlib.crc32(rest)) + rest


def read_block(f):
    """``(ids, runs)`` of the next block of a file, or None at its end."""
    head = f.read(struct.calcsize(HEADER))
    if not head:
        return None
    magic, n, lanes, vocabulary, size, more, crc, rest_crc = struct.unpack(HEADER, head)
    rest = f.read(size + more)
    if magic != MAGIC or zlib.crc32(rest) != rest_crc:
        raise ValueError("a block is damaged")
    ids = decode_ids(n, lanes, vocabulary, rest[:size])
    if zlib.crc32(ids.astype("<u4").tobytes()) != crc:
        raise ValueError("a block's ids do not match their checksum")
    runs = [(i if has else None, k, ends) for has, i, k, ends in struct.iter_unpack("<?qI?", zlib.decompress(rest[size:]))]
    return ids, runs


def _writing(where: str, vocabulary: str, end_id: int, block_ids: int, roll: int):
    def write(batches):
        from pyspark import TaskContext

        part, turn, docs, total, size = TaskContext.get().partitionId(), 0, 0, 0, 0
        encoder, end = shared_encoder(vocabulary, MEMO), np.array([end_id], "<u4").tobytes()
        store, out, held, filled, runs = Store(where), None, [], 0, []

        def put():
            nonlocal held, filled, runs, size
            block = write_block(np.frombuffer(b"".join(held), "<u4"), runs, encoder.size)
            out.write(block)
            size += len(block)
            held, filled, runs = [], 0, []

        def told():
            return pa.RecordBatch.from_pydict({"part": [part], "turn": [turn], "file": [name], "docs": [docs], "ids": [total], "bytes": [size]})

        for b in portions(batches, 2000):
            for doc, ids in zip(b.column(0).to_pylist(), encoder.stream(b.column(1).to_pylist()), strict=True):
                if out is not None and size >= roll:
                    if runs:
                        put()
                    store.commit(out)
                    yield told()
                    out, turn, docs, total, size = None, turn + 1, 0, 0, 0
                if out is None:
                    name = f"part-{part:06d}-{turn:05d}.rwb"
                    out = store.create(name)
                ids += end
                n, at = len(ids) // 4, 0
                docs, total = docs + 1, total + n
                while at < n:
                    k = min(n - at, block_ids - filled)
                    held.append(ids[4 * at : 4 * (at + k)])
                    at, filled = at + k, filled + k
                    runs.append((doc, k, at == n))
                    if filled == block_ids:
                        put()
        if out is None:
            return
        if runs:
            put()
        store.commit(out)
        yield told()

    return write


def write_ids(docs: DataFrame, vocabulary: str, end_id: int, id_col: str = "doc_id", text_col: str = "text", block_ids: int = BLOCK_IDS, roll: int = 256 << 20) -> tuple[str, list]:
    """Write all documents in id order; the folder, and a record a file (part, turn, file, docs, ids, bytes) in that order."""
    where = shared_dir(docs.sparkSession)
    rows = numbered(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("body")), "place")
    order = ["doc_id", F.substring("body", 1, 64), "place"]
    ordered = rows.repartitionByRange(*order).sortWithinPartitions(*order).select("doc_id", "body")
    made = ordered.mapInArrow(_writing(where, vocabulary, end_id, block_ids, roll), "part bigint, turn bigint, file string, docs bigint, ids bigint, bytes bigint")
    return where, sorted(made.collect())  # a few numbers a file


def _reading(where: str):
    def read(batches):
        store = Store(where)
        for b in batches:
            for name, base in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                rows, crc, n, at = [], 0, 0, base
                with store.open(name) as f:
                    while block := read_block(f):
                        ids, k = block[0].astype("<u4"), 0
                        for doc, m, ends in block[1]:
                            crc, n, k = zlib.crc32(ids[k : k + m], crc), n + m, k + m
                            if ends:
                                rows.append((doc, at, n, crc))
                                crc, n, at = 0, 0, at + n
                        if rows:
                            yield _told(rows)
                            rows = []

    return read


def _told(rows: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=["doc_id", "start", "n_tokens", "ids_crc32"])


def read_ids(spark, where: str, files: list) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, from the files."""
    base, rows = 0, []
    for f in files:
        rows.append((f.file, base))
        base += f.ids
    listed = spark.createDataFrame(rows, "file string, base bigint").repartition(max(1, len(rows)))
    return listed.mapInArrow(_reading(where), "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def round_trip(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", end_id: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    where, files = write_ids(docs, vocabulary, end_id, id_col, text_col)
    return read_ids(docs.sparkSession, where, files)
