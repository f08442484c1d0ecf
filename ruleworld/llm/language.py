"""Language identification by nearest centroid.

A text is lower-cased, everything but letters becomes single spaces, and its character 1- to 3-grams are hashed into a
fixed number of buckets. Vectors are damped counts times inverse document frequency, of unit length. Each language
has several centroids (spherical k-means over its training vectors); a text gets the language of the centroid with the
largest cosine. A text is rejected if its cosine is below a share of what nearly all training texts of the language
reach, whole or cut short, that fill about as many buckets: texts with few distinct n-grams score low in any language.

The classifier is fitted on a bounded sample (``per_language`` documents of each language, at most ``languages``
languages, ``fit_chars`` characters each); predictions read whole texts, in one scan without a shuffle.

Edge cases: null texts and texts without a letter are ``und``, score 0, rejected; ties go to the language that
sorts first; with no labelled row every text is ``und``; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.tokens import forget
from ruleworld.llm.ship import landed, portions, ship

BUCKETS = 1 << 12
UNKNOWN = "und"


def letter_table() -> np.ndarray:
    """1 for every code point that is a letter."""
    return np.fromiter((chr(c).isalpha() for c in range(0x110000)), np.bool_, 0x110000)


def gram_rows(texts: list[str | None], letters: np.ndarray, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray]:
    """Bucket counts of every text's 1- to 3-grams, and whether it has a letter."""
    joined = "\0".join((t or "").lower() for t in texts)
    raw = joined.encode("utf-32-le", "surrogatepass")
    cp = np.concatenate([np.zeros(1, np.uint32), np.frombuffer(raw, "<u4"), np.zeros(1, np.uint32)])
    is_letter, mark = letters[cp], cp == 0
    if mark.sum() != len(texts) + 1:  # a text holds the separator itself
        parts = [gram_rows([(t or "").replace("\0", " ")], letters, buckets) for t in texts]
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    cp = np.where(is_letter, cp, np.uint32(32))
    keep = is_letter | mark
    keep[1:] |= is_letter[:-1]
    cp, mark, is_letter = cp[keep].astype(np.int64), mark[keep], is_letter[keep]
    doc = np.cumsum(mark) - 1
    n = len(texts)
    has = np.bincount(doc[is_letter], minlength=n)[:n] > 0
    one = cp * 0x9E3779B1
    two = one[:-1] + cp[1:] * 0x85EBCA77
    three = two[:-1] + cp[2:] * 0xC2B2AE3D
    counts = np.zeros(n * buckets, np.int64)
    for k, h in ((0, one), (1, two), (2, three)):
        d = doc[: len(h)]
        inside = is_letter[: len(h)].copy()
        for j in range(1, k + 1):
            inside |= is_letter[j : len(h) + j]
        inside &= doc[k : k + len(h)] == d
        h = ((h ^ (h >> 15)) * 0x2C1B3C6D + k * 0x27D4EB2F >> 9) & (buckets - 1)
        counts += np.bincount((d * buckets + h)[inside], minlength=n * buckets)[: n * buckets]
    return counts.reshape(n, buckets), has


def fills(counts: np.ndarray) -> np.ndarray:
    """The whole binary logarithm of how many buckets each text fills."""
    return np.log2(np.maximum(1, (counts > 0).sum(axis=1))).astype(int)


#: Letters to which training texts are cut to learn how short ones score, and texts of a language that are cut.
CUTS, CUT_TEXTS = (4, 8, 16, 32, 64, 128, 256, 512), 150


@dataclass
class CentroidModel:
    names: list[str]
    idf: np.ndarray
    centroids: np.ndarray
    owner: np.ndarray
    nearest: np.ndarray  # smallest cosine a language accepts, by the power of two of the buckets that a text fills

    def vectors(self, counts: np.ndarray) -> np.ndarray:
        out = np.empty(counts.shape, np.float32)
        for k in range(0, len(counts), 256):
            v = np.log1p(counts[k : k + 256]).astype(np.float32) * self.idf
            out[k : k + 256] = v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)
        return out

    def predict(self, texts: list[str | None], letters: np.ndarray):
        counts, has = gram_rows(texts, letters, len(self.idf))
        if not len(self.centroids):
            return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
        cos = np.round(self.vectors(counts) @ self.centroids.T, 6)
        best = cos.argmax(axis=1)
        score = np.clip(cos[np.arange(len(texts)), best], 0.0, 1.0) * has
        rejected = ~has | (score < self.nearest[self.owner[best], fills(counts)])
        return [self.names[self.owner[b]] if ok else UNKNOWN for b, ok in zip(best, has, strict=True)], score, rejected


def _small_rows(texts: list[str], letters: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """``gram_rows`` of many texts, a few at a time, in half the width."""
    parts = [(np.zeros((0, buckets), np.int32), np.zeros(0, bool))]
    for k in range(0, len(texts), 64):
        counts, has = gram_rows(texts[k : k + 64], letters, buckets)
        parts.append((counts.astype(np.int32), has))
    return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])


def fit_centroids(rows: list[tuple[str, str]], each: int = 3, buckets: int = BUCKETS, margin: float = 0.5, low: float = 0.01, rounds: int = 12, seed: int = 11) -> CentroidModel:
    letters = letter_table()
    rows = sorted(rows)
    names = sorted({lang for lang, _ in rows})
    if not names:
        return CentroidModel([], np.ones(buckets, np.float32), np.zeros((0, buckets), np.float32), np.zeros(0, int), np.zeros((0, 0)))
    counts = _small_rows([t for _, t in rows], letters, buckets)[0]
    idf = (np.log((1 + len(rows)) / (1 + (counts > 0).sum(axis=0))) + 1).astype(np.float32)
    model = CentroidModel(names, idf, np.zeros((0, buckets), np.float32), np.zeros(0, int), np.zeros((len(names), buckets.bit_length())))
    v, label = model.vectors(counts), np.array([names.index(lang) for lang, _ in rows])
    chance, parts, owner = np.random.default_rng(seed), [], []
    for k in range(len(names)):
        own = v[label == k]
        centre = own[chance.choice(len(own), min(each, len(own)), replace=False)]
        for _ in range(rounds):
            nearest = (own @ centre.T).argmax(axis=1)
            centre = np.stack([own[nearest == c].sum(axis=0) if (nearest == c).any() else centre[c] for c in range(len(centre))])
            centre /= np.maximum(np.linalg.norm(centre, axis=1, keepdims=True), 1e-9)
        parts.append(centre)
        owner += [k] * len(centre)
        texts = [t for lang, t in rows if lang == names[k]]
        short = [t.strip()[:n] for t in texts[:: -(-len(texts) // CUT_TEXTS)] for n in CUTS]
        some, lettered = _small_rows(short, letters, buckets)
        seen = np.concatenate([counts[label == k], some[lettered]])
        cos, size = (model.vectors(seen) @ centre.T).max(axis=1), fills(seen)
        for j in range(buckets.bit_length()):
            at = cos[size == j]
            model.nearest[k, j] = margin * np.quantile(at, low) if len(at) else model.nearest[k, j - 1] if j else 0.0
    model.centroids, model.owner = np.concatenate(parts).astype(np.float32), np.array(owner)
    return model


def held_out(id_col: str = "doc_id") -> Column:
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(3)) == 1


def training_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = 400, languages: int = 200, fit_chars: int = 20_000) -> list[tuple[str, str]]:
    """The bounded sample: of each language, the documents with the least hash of the id."""
    open_rows = docs.filter(F.coalesce(~held_out(id_col), F.lit(False)) & F.col(lang_col).isNotNull() & F.col(text_col).rlike(r"\p{L}"))
    ids = open_rows.select(F.col(lang_col).alias("lang"), F.xxhash64(F.col(id_col)).alias("h"))
    sizes = ids.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(languages).collect()
    if not sizes:
        return []
    wide = {r["lang"]: int(-(2**63) + min(1.0, 2.0 * per_language / r["count"]) * (2**64 - 2**11)) for r in sizes}
    reach = F.create_map(*[F.lit(x) for kv in wide.items() for x in kv])
    from pyspark.sql import Window

    near = open_rows.select(F.col(lang_col).alias("lang"), F.substring(text_col, 1, fit_chars).alias("body"), F.xxhash64(F.col(id_col)).alias("h"))
    near = near.filter(F.col("h") <= F.try_element_at(reach, "lang"))
    order = Window.partitionBy("lang").orderBy("h", "body")  # over about twice the bound a language
    picked = near.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= per_language)
    return [(r["lang"], r["body"]) for r in picked.select("lang", "body").collect()]


def _predicting(shared, at: int):
    def run(batches):
        forget()
        model, letters = landed(shared), letter_table()
        for b in portions(batches):
            texts, k = b.column(at).to_pylist(), 0
            langs, scores, gone = [], [], []
            while k < len(texts):
                n, size = k, 0
                while n < len(texts) and n - k < 64 and size < 2_000_000:
                    size += len(texts[n] or "")
                    n += 1
                a, s, r = model.predict(texts[k:n], letters)
                langs += a
                scores.append(s)
                gone.append(r)
                k = n
            yield b, pa.array(langs, pa.string()), pa.array(np.concatenate(scores) if scores else [], pa.float64()), pa.array(np.concatenate(gone) if gone else [], pa.bool_())

    return run


def _told(shared):
    inner = _predicting(shared, 2)

    def run(batches):
        for b, lang, score, gone in inner(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), lang, score, gone], names=["doc_id", "held_out", "lang_pred", "score", "rejected"])

    return run


def _kept(shared, at: int):
    inner = _predicting(shared, at)

    def run(batches):
        for b, _, _, gone in inner(batches):
            yield b.filter(pa.compute.invert(gone))

    return run


def identify(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", **fit) -> DataFrame:
    """``doc_id, held_out, lang_pred, score`` (cosine) and ``rejected`` for every row."""
    shared = ship(docs.sparkSession, fit_centroids(training_rows(docs, id_col, text_col, lang_col, **fit)))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(held_out(id_col), F.lit(False)).alias("held_out"), F.col(text_col).alias("body"))
    return rows.mapInArrow(_told(shared), "doc_id bigint, held_out boolean, lang_pred string, score double, rejected boolean")


def drop_rejected(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", lang_col: str = "lang", **fit) -> DataFrame:
    """``docs`` without the rows that the classifier rejects; columns and other rows unchanged."""
    shared = ship(docs.sparkSession, fit_centroids(training_rows(docs, id_col, text_col, lang_col, **fit)))
    return docs.mapInArrow(_kept(shared, docs.columns.index(text_col)), docs.schema)
