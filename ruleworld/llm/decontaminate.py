"""Benchmark decontamination with a generalised suffix automaton over the words of test items.

The items' words build one automaton (a state for each class of equal end positions). A document's words are streamed
through it; the longest match that ends at each word is tracked, and where it reaches the window length the window is
hit, with all items that hold it. Items shorter than the window match only as a whole; the states that stand for them
are reached over suffix links. The automaton covers a block of items of bounded total length (an item longer than that
makes a block of its own). More items make more blocks, each one more pass over the documents, whose hits are settled
before the next; so a task holds one automaton at a time, whatever the size of the benchmark.

Edge cases: null and empty texts have no words and no hits; items without words are ignored; equal items each count;
an empty benchmark leaves every document clean; repeated rows are each matched; extra columns are ignored.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.ship import landed, portions, ship
from ruleworld.llm.sift import numbered, without
from ruleworld.llm.tokens import forget
from ruleworld.sources.scratch import settle

#: ASCII capitals to small letters; every other ASCII character that is no letter or digit to a space.
_FOLD = bytes((c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32) for c in range(256))
WINDOW = 10
#: Words of items in one automaton: with at most two states and three transitions a word, under 400 MB.
BLOCK_WORDS = 500_000


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased words: runs of ASCII letters, digits and all characters beyond ASCII."""
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []


class ItemAutomaton:
    """Generalised suffix automaton; ``items`` are ``(item_id, words)``."""

    def __init__(self, items, window: int = WINDOW):
        self.window = window
        self.next: list[dict[bytes, int]] = [{}]
        self.link, self.length = [-1], [0]
        kept = [(i, w) for i, w in items if w]
        for _, words in kept:
            last = 0
            for word in words:
                last = self._extend(last, word)
        #: per state: the one on the way to the root that stands for its last ``window`` words
        self.top = [0] * len(self.link)
        for s in sorted(range(1, len(self.link)), key=self.length.__getitem__):
            self.top[s] = s if self.length[self.link[s]] < window else self.top[self.link[s]]
        self.found: dict[int, list] = {}  # state of a window, or of a whole short item: ids of its items
        short: dict[int, int] = {}
        for i, words in kept:
            need, state, n = min(window, len(words)), 0, 0
            for word in words:
                state, n = self.next[state][word], n + 1
                if n < need:
                    continue
                if need == window:
                    state = self.top[state]
                while self.length[self.link[state]] >= need:
                    state = self.link[state]
                n = min(n, self.length[state])
                ids = self.found.setdefault((state, need), [])
                if not ids or ids[-1] != i:
                    ids.append(i)
                if need < window:
                    short.setdefault(state, set()).add(need)
        #: per state: the nearest state on the way to the root that stands for short items, itself included, or -1.
        self.short = {s: sorted(v) for s, v in short.items()}
        self.up = [-1] * len(self.link)
        for s in sorted(range(len(self.link)), key=self.length.__getitem__):
            self.up[s] = s if s in self.short else (self.up[self.link[s]] if s else -1)

    def _extend(self, last: int, word: bytes) -> int:
        old = self.next[last].get(word)
        if old is not None:
            return old if self.length[old] == self.length[last] + 1 else self._split(last, old, word)
        new = len(self.link)
        self.next.append({})
        self.length.append(self.length[last] + 1)
        self.link.append(0)
        p = last
        while p >= 0 and word not in self.next[p]:
            self.next[p][word] = new
            p = self.link[p]
        if p >= 0:
            q = self.next[p][word]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, q, word)
        return new

    def _split(self, p: int, q: int, word: bytes) -> int:
        """The part of state ``q`` that is reached from ``p``, as a state of its own."""
        twin = len(self.link)
        self.next.append(dict(self.next[q]))
        self.length.append(self.length[p] + 1)
        self.link.append(self.link[q])
        self.link[q] = twin
        while p >= 0 and self.next[p].get(word) == q:
            self.next[p][word] = twin
            p = self.link[p]
        return twin

    def match(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set]:
        """Merged spans ``[a, b)`` of hit words, and the ids of the items whose windows occur."""
        nxt, link, length, up, top, window = self.next, self.link, self.length, self.up, self.top, self.window
        spans: list[list[int]] = []
        items: set = set()
        hit: set[tuple[int, int]] = set()
        root, state, n = nxt[0], 0, 0
        for at, word in enumerate(words, 1):
            to = nxt[state].get(word)
            if to is None:
                if state:
                    while state and to is None:
                        state = link[state]
                        to = nxt[state].get(word)
                    n = length[state]
                if to is None:
                    continue
            state, n = to, n + 1
            reach = 0
            if n >= window:
                hit.add((top[state], window))
                reach = window
            low = up[state]
            while low >= 0:
                for need in self.short[low]:
                    if need <= n and need > length[link[low]]:
                        hit.add((low, need))
                        reach = max(reach, need)
                low = up[link[low]] if low else -1
            if reach:
                while spans and spans[-1][0] >= at - reach:
                    spans.pop()
                if spans and spans[-1][1] >= at - reach:
                    spans[-1][1] = at
                else:
                    spans.append([at - reach, at])
        for key in hit:
            items.update(self.found.get(key, ()))
        return [(a, b) for a, b in spans], items


def _automata(benchmark: DataFrame, window: int, block_words: int, item_col: str = "item_id", item_text: str = "text") -> list:
    """Broadcast automata over blocks of at most ``block_words`` words, or one longer item; the driver holds one block at a time."""
    spark, blocks, held, size = benchmark.sparkSession, [], [], 0
    for item, text in benchmark.select(item_col, item_text).filter(F.col(item_text).isNotNull()).toLocalIterator():
        words = words_of(text)
        if held and size + len(words) > block_words:
            blocks.append(ship(spark, ItemAutomaton(held, window)))
            held, size = [], 0
        held.append((item, words))
        size += len(words)
    return [*blocks, ship(spark, ItemAutomaton(held, window))]


FOUND = "n_words bigint, spans array<struct<a:bigint,b:bigint>>, item_ids array<string>"
_FOUND = [("n_words", pa.int64()), ("spans", pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))), ("item_ids", pa.list_(pa.string()))]


def _spans(spans: list[tuple[int, int]]) -> list[dict]:
    return [{"a": a, "b": b} for a, b in spans]


def _matching(shared, hits_only: bool):
    """``rid, key, body`` become ``rid, key`` and ``FOUND``; with ``hits_only``, of rows with hits."""

    def run(batches):
        forget()
        machine = landed(shared)
        for b in batches:
            rows, kept = [], []
            for k, text in enumerate(b.column(2).to_pylist()):
                words = words_of(text)
                spans, items = machine.match(words)
                if items or not hits_only:
                    kept.append(k)
                    rows.append((len(words), _spans(spans), sorted(map(str, items))))
            cols = [pa.array([r[k] for r in rows], t) for k, (_, t) in enumerate(_FOUND)]
            b = b.take(pa.array(kept, pa.int64()))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *cols], names=["rid", "key"] + [n for n, _ in _FOUND])

    return run


def _united(spans: Column) -> Column:
    """Spans of several automata as disjoint spans in order."""
    none = F.array().cast("array<struct<a:bigint,b:bigint>>")

    def step(out: Column, x: Column) -> Column:
        last = F.element_at(out, -1)
        grown = F.concat(F.slice(out, 1, F.size(out) - 1), F.array(F.struct(last["a"].alias("a"), F.greatest(last["b"], x["b"]).alias("b"))))
        return F.when((F.size(out) > 0) & (x["a"] <= F.try_element_at(out, F.lit(-1))["b"]), grown).otherwise(F.concat(out, F.array(x)))

    return F.aggregate(F.array_sort(F.flatten(spans)), none, step)


def _hits(rows: DataFrame, blocks: list) -> DataFrame:
    """``rid, key`` and ``FOUND`` of ``rid, key, body``, by one pass over the rows for each block."""
    schema = "rid bigint, key bigint, " + FOUND
    base = rows.mapInArrow(_matching(blocks[0], False), schema)
    if len(blocks) == 1:
        return base
    base = settle(base)
    more = [settle(rows.mapInArrow(_matching(b, True), schema)) for b in blocks[1:]]
    found = base.filter(F.size("item_ids") > 0)
    for m in more:
        found = found.unionByName(m)
    found = found.groupBy("rid").agg(_united(F.collect_list("spans")).alias("s"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("item_ids")))).alias("i"))
    joined = base.join(found, "rid", "left")
    return joined.select("rid", "key", "n_words", F.coalesce("s", "spans").alias("spans"), F.coalesce("i", "item_ids").alias("item_ids"))


def find_items(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", block_words: int = BLOCK_WORDS) -> DataFrame:
    """``key`` (the id), ``n_words``, hit ``spans`` of word places, and the sorted ``item_ids`` (as strings) found in each row."""
    blocks = _automata(benchmark, window, block_words, item_col, item_text)
    rows = docs.select(F.col(id_col).cast("long").alias("key"), F.col(text_col).alias("body"))
    rows = numbered(rows, "rid") if len(blocks) > 1 else rows.withColumn("rid", F.lit(0).cast("long"))
    return _hits(rows.select("rid", "key", "body"), blocks).drop("rid")


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    hits = _hit_words()
    return find_items(docs, benchmark, window, id_col, text_col).select(
        F.col("key").alias("doc_id"),
        "n_words",
        hits.alias("n_hit"),
        F.size("item_ids").cast("long").alias("n_items"),
        F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"),
        (hits > 0).alias("contaminated"),
    )


def clean_text(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words of the spans and what stands between them."""
    raw = text.encode("utf-8", "surrogatepass")
    folded = raw.translate(_FOLD)
    places, at = [], 0
    for w in folded.split():
        at = folded.index(w, at)
        places.append((at, at + len(w)))
        at += len(w)
    out, last = [], 0
    for a, b in spans:
        out.append(raw[last : places[a][0]])
        last = places[b - 1][1]
    return b"".join([*out, raw[last:]]).decode("utf-8", "surrogatepass")


def _cleaning(shared, at: int, chars: int | None, limit: float):
    """Rows through the automaton; hit spans go, rows covered beyond ``limit`` go. ``at`` and ``chars``: places of text and length."""

    def run(batches):
        forget()
        machine = landed(shared)
        for b in portions(batches):
            keep, texts, lengths = [], [], b.column(chars).to_pylist() if chars is not None else None
            for k, text in enumerate(b.column(at).to_pylist()):
                words = words_of(text)
                spans = machine.match(words)[0] if words else []
                if sum(e - a for a, e in spans) > limit * len(words):
                    continue
                if spans and lengths and lengths[k] is not None:
                    lengths[k] = -1
                while spans:  # what a removal brings together may match anew
                    text = clean_text(text, spans)
                    spans = machine.match(words_of(text))[0]
                if lengths and lengths[k] == -1:
                    lengths[k] = len(text)
                keep.append(k)
                texts.append(text)
            kept = pa.array(keep, pa.int64())
            out = b.take(kept).set_column(at, b.schema.field(at), pa.array(texts, b.schema.field(at).type))
            if lengths is not None:
                out = out.set_column(chars, b.schema.field(chars), pa.array([lengths[k] for k in keep], b.schema.field(chars).type))
            yield out

    return run


def _cutting(at: int, chars: int | None):
    """Rows whose last column holds hit spans: the text without them."""

    def run(batches):
        for b in batches:
            last = b.num_columns - 1
            texts = [clean_text(t, [(x["a"], x["b"]) for x in s]) if s else t for t, s in zip(b.column(at).to_pylist(), b.column(last).to_pylist(), strict=True)]
            out = b.select(range(last)).set_column(at, b.schema.field(at), pa.array(texts, b.schema.field(at).type))
            if chars is not None:
                n = [c if c is None or not s else len(t) for c, s, t in zip(b.column(chars).to_pylist(), b.column(last).to_pylist(), texts, strict=True)]
                out = out.set_column(chars, b.schema.field(chars), pa.array(n, b.schema.field(chars).type))
            yield out

    return run


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, most_covered: float = 0.5, text_col: str = "text", block_words: int = BLOCK_WORDS) -> DataFrame:
    """``docs`` without hit spans; a row whose hit words are more than ``most_covered`` of its words goes whole.

    What a removal brings together is matched anew until nothing is hit. Rows without a hit are unchanged, byte for
    byte. Columns are those of ``docs``; an integer column ``n_chars`` that is not null is set anew where the text changed.
    """
    at, blocks = docs.columns.index(text_col), _automata(benchmark, window, block_words)
    integer = "n_chars" in docs.columns and docs.schema["n_chars"].dataType.typeName() in ("byte", "short", "integer", "long")
    chars = docs.columns.index("n_chars") if integer else None
    if len(blocks) == 1:
        return docs.mapInArrow(_cleaning(blocks[0], at, chars, most_covered), docs.schema)
    names, mark = docs.columns, "__rw_rid"
    done, now, limit = None, docs, most_covered
    while True:
        placed = numbered(now, mark)
        told = _hits(placed.select(F.col(mark).alias("rid"), F.lit(0).cast("long").alias("key"), F.col(f"`{text_col}`").alias("body")), blocks)
        told = settle(told.filter(F.size("item_ids") > 0).withColumn("n_hit", _hit_words()).select(F.col("rid").alias(mark), F.col("spans").alias("__rw_spans"), (F.col("n_hit") > limit * F.col("n_words")).alias("__rw_gone")))
        clean = without(placed, mark, told.select(mark)).select(*[F.col(f"`{c}`") for c in names])
        done = clean if done is None else settle(done.unionByName(clean))
        if told.isEmpty():
            return done
        hit = placed.join(told, mark).filter("NOT __rw_gone").select(*[F.col(f"`{c}`") for c in names], "__rw_spans")
        now, limit = settle(hit.mapInArrow(_cutting(at, chars), docs.schema)), 1.0  # the limit holds for the text as it came


def _hit_words() -> Column:
    return F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["b"] - s["a"])
