"""Quality by hierarchical empirical Bayes over documents, paths and hosts.

A document classifier (logistic regression on words that tell the classes apart and on a few shapes of the text) gives
each document a chance of being good and one of being toxic. The chances are summed by path and host (for documents:
language and source), and each level's mean is shrunk toward the level above: a path toward its host, a host toward
the whole. How strongly is estimated from the data: the variance between sites beyond what chance gives sets the
weight of the prior in documents. A document's posterior odds are its own odds times the odds of its path's posterior
over the odds of the whole. Sums are partial aggregates, so a host with a third of all rows is one row a task, and
sites' posteriors come back to the documents by broadcast, or beyond a number of sites over salted keys.

The classifier is fitted on a bounded sample of labelled rows (``fit_rows``, ``fit_chars`` characters each). Everything
else reads whole texts of all rows.

Edge cases: null and empty texts have no words and no shape, and get their site's odds; a null host or path is a site
of its own; labels that are null, or of ids without a document, are left out; with one class only, or no labels, all
documents are good with chance one half and toxic with chance zero; repeated rows count each.
"""

from __future__ import annotations

import math
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.ship import landed, ship
from ruleworld.sources.scratch import settle

_WORD = bytes(c if 48 <= c <= 57 or 65 <= c <= 90 or 97 <= c <= 122 or c >= 128 or c <= 32 else 32 for c in range(256))
_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_UPPER = bytes(range(65, 91))
_LETTER = bytes(range(65, 91)) + bytes(range(97, 123)) + bytes(range(128, 256))
_DIGIT = bytes(range(48, 58))
_PLAIN = b" \t\n\r" + _LETTER + _DIGIT + b".,'"
SHAPES = 8


def shape(raw: bytes, words: list[bytes]) -> list[float]:
    """Shares of capitals, digits and signs, repetition of words and lines, length of words and of the text."""
    if not words:
        return [0.0] * SHAPES
    n = len(raw)
    letters = n - len(raw.translate(None, _LETTER))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return [
        (n - len(raw.translate(None, _UPPER))) / max(1, letters),
        (n - len(raw.translate(None, _DIGIT))) / n,
        len(raw.translate(None, _PLAIN)) / n,
        1 - len(set(words)) / len(words) if len(words) > 20 else 0.0,
        1 - len(set(lines)) / len(lines) if len(lines) > 3 else 0.0,
        min(20.0, letters / len(words)) / 20,
        raw.count(b"|") / len(words),
        min(1.0, math.log1p(len(words)) / 10),
    ]


def tokens(text: str | None) -> tuple[bytes, list[bytes]]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw, raw.translate(_WORD).translate(_LOWER).split()


def marks(words: list[bytes]) -> set[bytes]:
    """What a text is told by: its words, and the stems (``^``) and endings (``$``) of the longer ones."""
    own = set(words)
    long = [w for w in own if len(w) > 5]
    own.update(b"^" + w[:5] for w in long)
    own.update(b"$" + w[-5:] for w in long)
    return own


@dataclass
class TextModel:
    """Words, stems and endings, and for each target: weights of words (by share of documents), of shapes, and the constant."""

    words: dict[bytes, int] = field(default_factory=dict)
    weights: dict[str, np.ndarray] = field(default_factory=dict)
    centre: np.ndarray | None = None
    scale: np.ndarray | None = None

    def features(self, text: str | None) -> np.ndarray:
        raw, words = tokens(text)
        x = np.zeros(len(self.words) + SHAPES + 1)
        get = self.words.get
        for w in self.words.keys() & marks(words):
            x[get(w)] = 1.0
        x[len(self.words) : -1] = shape(raw, words)
        x[-1] = 1.0
        return x

    def chances(self, texts: list[str | None]) -> dict[str, np.ndarray]:
        if not self.weights:
            return {}
        x = np.stack([self.features(t) for t in texts])
        x[:, len(self.words) : -1] = (x[:, len(self.words) : -1] - self.centre) / self.scale
        empty = np.array([not (t or "").strip() for t in texts], bool)
        return {k: np.where(empty, np.nan, np.round(1 / (1 + np.exp(-np.clip(x @ w, -30, 30))), 9)) for k, w in self.weights.items()}


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.3, rounds: int = 30) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the constant is not shrunk."""
    w, shrink = np.zeros(x.shape[1]), np.full(x.shape[1], ridge)
    shrink[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(shrink), x.T @ (y - p) - shrink * w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    return w


def fit_text(rows: list[tuple[str | None, dict[str, int | None]]], targets: tuple[str, ...], most_words: int = 600, z_least: float = 5.0) -> TextModel:
    """``rows``: text and labels. Words enter by the size of their z score between the classes of any target."""
    often = Counter()
    for text, _ in rows:
        often.update(marks(tokens(text)[1]))
    often = {w for w, n in often.items() if n >= 5}
    sets = [marks(tokens(text)[1]) & often for text, _ in rows]
    best: dict[bytes, float] = {}
    usable = []
    for target in targets:
        y = [r[1].get(target) for r in rows]
        pos, neg = sum(v == 1 for v in y), sum(v == 0 for v in y)
        if not pos or not neg:
            continue
        usable.append(target)
        seen = Counter(), Counter()
        for words, v in zip(sets, y, strict=True):
            if v is not None:
                seen[v == 1].update(words)
        for w in often:
            b, a = seen[0][w], seen[1][w]
            p = (a + b) / (pos + neg)
            z = abs(a / pos - b / neg) / math.sqrt(max(p * (1 - p), 1e-9) * (1 / pos + 1 / neg))
            if z >= z_least:
                best[w] = max(best.get(w, 0.0), z)
    model = TextModel({w: k for k, (w, _) in enumerate(sorted(best.items(), key=lambda kv: (-kv[1], kv[0]))[:most_words])})
    if not usable:
        return TextModel()
    x = np.stack([model.features(t) for t, _ in rows])
    inner = x[:, len(model.words) : -1]
    model.centre, model.scale = inner.mean(axis=0), np.maximum(inner.std(axis=0), 1e-3)
    x[:, len(model.words) : -1] = (inner - model.centre) / model.scale
    for target in usable:
        has = np.array([r[1].get(target) is not None for r in rows])
        model.weights[target] = _logistic(x[has], np.array([float(r[1][target]) for r, h in zip(rows, has, strict=True) if h]))
    return model


def labelled_sample(docs: DataFrame, labels: DataFrame, targets: tuple[str, ...], id_col: str, text_col: str, fit_rows: int, fit_chars: int):
    """At most about ``fit_rows`` labelled documents, those with the least hash of the id."""
    told = labels.select(F.col(id_col).alias("key"), *[F.when(F.col(t).isin(0, 1), F.col(t)).cast("int").alias(f"y_{t}") for t in targets]).filter(F.col("key").isNotNull())
    share = min(1.0, 1.1 * fit_rows / max(1, told.count()))
    told = told.filter(F.xxhash64("key") <= int(-(2**63) + share * (2**64 - 2**11))).orderBy(F.xxhash64("key"), *told.columns).limit(fit_rows)
    body = docs.select(F.col(id_col).alias("key"), F.substring(text_col, 1, fit_chars).alias("body"))
    rows = body.join(F.broadcast(told), "key")  # the sample's size is a parameter
    rows = rows.groupBy("key", *[f"y_{t}" for t in targets]).agg(F.min("body").alias("body")).orderBy("key").collect()
    return [(r["body"], {t: r[f"y_{t}"] for t in targets}) for r in rows]


def _scoring(shared, at: int, targets: tuple[str, ...]):
    def run(batches):
        model = landed(shared)
        for b in batches:
            texts, out = b.column(at).to_pylist(), {t: [] for t in targets}
            for k in range(0, len(texts), 256):
                told = model.chances(texts[k : k + 256])
                for t in targets:
                    out[t].append(told.get(t, np.full(len(texts[k : k + 256]), np.nan)))
            cols = [pa.array(np.concatenate(out[t]) if out[t] else np.zeros(0), pa.float64(), from_pandas=True) for t in targets]
            keep = [k for k in range(b.num_columns) if k != at]
            yield pa.RecordBatch.from_arrays([b.column(k) for k in keep] + cols, names=[b.schema.names[k] for k in keep] + [f"p_{t}" for t in targets])

    return run


def _logit(p: Column) -> Column:
    q = F.greatest(F.least(p, F.lit(1 - 1e-6)), F.lit(1e-6))
    return F.log(q / (1 - q))


def _strength(sites: DataFrame, n: str, total: str, squares: str) -> float:
    """Prior weight in documents, by moments: pooled variance within sites over the variance between them."""
    r = sites.filter(F.col(n) > 0).agg(F.sum(n).alias("n"), F.count("*").alias("k"), F.sum(total).alias("s"), F.sum(squares).alias("q"), F.sum(F.col(total) ** 2 / F.col(n)).alias("b"), F.sum(F.col(n) ** 2).alias("n2")).first()
    if not r.n or r.k < 2 or r.n <= r.k:
        return 1e6
    within = max(1e-9, (r.q - r.b) / (r.n - r.k))
    spread = (r.b - r.s**2 / r.n - (r.k - 1) * within) / max(1e-9, r.n - r.n2 / r.n)
    return round(float(min(1e6, within / spread)) if spread > 1e-9 else 1e6, 6)


def site_posteriors(scored: DataFrame, target: str, host: str = "host", path: str = "path") -> tuple[DataFrame, float]:
    """``host, path, host_mean, path_mean`` shrunk means, and the mean of the whole."""
    p = F.col(f"p_{target}")
    paths = settle(scored.groupBy(host, path).agg(F.count(p).cast("double").alias("n"), F.coalesce(F.sum(p), F.lit(0.0)).alias("s"), F.coalesce(F.sum(p * p), F.lit(0.0)).alias("q")))
    hosts = settle(paths.groupBy(host).agg(F.sum("n").alias("hn"), F.sum("s").alias("hs"), F.sum("q").alias("hq")))
    whole = hosts.agg(F.sum("hs").alias("s"), F.sum("hn").alias("n")).first()
    mean = float(whole.s / whole.n) if whole.n else 0.5
    k_host, k_path = _strength(hosts, "hn", "hs", "hq"), _strength(paths, "n", "s", "q")
    hosts = hosts.select(F.col(host).alias("h"), ((F.col("hs") + k_host * mean) / (F.col("hn") + k_host)).alias("host_mean"))
    joined = paths.join(hosts, paths[host].eqNullSafe(hosts["h"]))
    return joined.select(host, path, "host_mean", ((F.col("s") + k_path * F.col("host_mean")) / (F.col("n") + k_path)).alias("path_mean")), mean


#: Sites up to which their posteriors are broadcast (some 10 MB); tasks that a site's documents are dealt to beyond.
BROADCAST_SITES, SALTS = 100_000, 32


def _beside(docs: DataFrame, sites: DataFrame, most: int | None = None) -> DataFrame:
    """Documents with their sites' columns. Many sites are copied once for each salt, so no site's documents meet in one task."""
    met = docs["host"].eqNullSafe(sites["h"]) & docs["path"].eqNullSafe(sites["p"])
    if sites.count() <= (BROADCAST_SITES if most is None else most):
        return docs.join(F.broadcast(sites), met).drop("h", "p")
    salted = docs.withColumn("__rw_salt", F.pmod(F.xxhash64("doc_id", "p_quality", "p_toxic"), F.lit(SALTS).cast("long")))
    copies = sites.withColumn("s", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    met = salted["host"].eqNullSafe(copies["h"]) & salted["path"].eqNullSafe(copies["p"]) & (salted["__rw_salt"] == copies["s"])
    return salted.join(copies, met).drop("h", "p", "s", "__rw_salt")


def url_site(url: Column) -> tuple[Column, Column]:
    """Host and first path step of a URL."""
    host = F.lower(F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#:]*)", 1))
    return host, F.regexp_extract(url, r"^[a-zA-Z][a-zA-Z0-9+.-]*://[^/?#]*(/[^/?#]*)", 1)


def judge(docs: DataFrame, labels: DataFrame, host: Column | None = None, path: Column | None = None, id_col: str = "doc_id", text_col: str = "text", fit_rows: int = 4000, fit_chars: int = 6_000, least_quality: float = 0.5, most_toxic: float = 0.4, pull: float = 0.5) -> DataFrame:
    """``doc_id``, the document's own chances, its site's posteriors, posterior ``quality`` and ``toxicity``, and ``kept``.

    ``pull`` is the weight of the site's odds beside the document's: at 0.5 a site can tip close cases only.
    """
    targets = ("quality", "toxic")
    model = fit_text(labelled_sample(docs, labels, targets, id_col, text_col, fit_rows, fit_chars), targets)
    host, path = F.col("source") if host is None else host, F.col("lang") if path is None else path
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), host.cast("string").alias("host"), path.cast("string").alias("path"), F.col(text_col).alias("body"))
    scored = settle(rows.mapInArrow(_scoring(ship(docs.sparkSession, model), 3, targets), "doc_id bigint, host string, path string, p_quality double, p_toxic double"))
    out = scored
    for target, name in (("quality", "quality"), ("toxic", "toxicity")):
        sites, mean = site_posteriors(scored, target)
        sites = sites.select(F.col("host").alias("h"), F.col("path").alias("p"), F.col("host_mean").alias(f"host_{name}"), F.col("path_mean").alias(f"path_{name}"))
        out = _beside(out, settle(sites))
        known = target in model.weights
        own = _logit(F.coalesce(F.col(f"p_{target}"), F.lit(mean)))
        site = _logit(F.col(f"path_{name}")) - _logit(F.lit(mean))
        sure = F.round(1 / (1 + F.exp(-(own + pull * site))), 6)
        out = out.withColumn(name, sure if known else F.lit(0.5 if name == "quality" else 0.0))
    kept = (F.col("quality") >= least_quality) & (F.col("toxicity") < most_toxic)
    return out.select("doc_id", "host", "path", *[F.round(c, 6).alias(c) for c in ("p_quality", "p_toxic", "host_quality", "path_quality", "host_toxicity", "path_toxicity")], "quality", "toxicity", kept.alias("kept"))
