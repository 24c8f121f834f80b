"""Quality classifier: a generalised additive model with pairwise interactions.

Every feature is a number of the whole text (no label, language, source or id).  Boosting runs over the features in a
cycle: each step fits a shallow tree to the gradient on one feature's bins and adds it to that feature's lookup table.
Then the pairs with the largest gain on what is left get two-way tables, boosted in a cycle as well.  A score is the
logistic of a sum of table entries, so scoring is a bin search and an addition a feature, over whole vectors.

The model is fitted on the driver on at most `max_rows` labels, chosen by hash of the id before any text is read: this
bound is a parameter and the only sample.  The chosen documents' features make the model; then one pass over all texts
computes features and scores together, so no text is shuffled and no feature table is written.

Defined results: a null text is an empty one and is scored; rows that share an id are scored each, and the smallest of
their texts is learned from; a document with several labels counts once a label; labels of no document count nothing;
with no label, or labels of one kind, the score is the labels' smoothed mean (0.5 without labels).
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm.common import crc_mod, cut, documents, raw, thrifty

FEATURES = ("words", "word_bytes", "distinct", "top_word", "upper", "digits", "symbols", "symbol_ends", "bars", "bangs", "stops", "non_ascii", "lines", "line_words", "repeated_lines", "short_words", "repeated_pairs")
THRESHOLD = 0.3
_KIND = np.zeros(256, np.int64)
for _c in range(256):
    _s = chr(_c)
    _KIND[_c] = 1 if "A" <= _s <= "Z" else 2 if "a" <= _s <= "z" else 3 if _s.isdigit() and _c < 128 else 4 if _s == "|" else 5 if _s == "!" else 6 if _s in ".,;:?'\"-()" else 7 if _c >= 128 else 0 if _c <= 32 else 8


def features(text: bytes | None) -> list[float]:
    text = text or b""
    words = text.split()
    n = len(words)
    if not n:
        return [0.0] * len(FEATURES)
    kinds = np.bincount(_KIND[np.frombuffer(text, np.uint8)], minlength=9)
    seen = Counter(words)
    lines = [x for x in (y.strip() for y in text.split(b"\n")) if x]
    pairs = len(set(zip(words, words[1:])))
    size = max(1, len(text))
    return [
        math.log1p(n),
        sum(map(len, words)) / n,
        len(seen) / n,
        max(seen.values()) / n,
        kinds[1] / max(1, kinds[1] + kinds[2] + kinds[7] / 2),
        kinds[3] / size,
        kinds[8] / size,
        sum(1 for w in words if w[-1] in b"#*$%&@~^=+_<>/\\") / n,
        kinds[4] / n,
        kinds[5] / n,
        kinds[6] / n,
        kinds[7] / size,
        math.log1p(len(lines)),
        math.log1p(n / max(1, len(lines))),
        1 - len(set(lines)) / max(1, len(lines)),
        sum(1 for w in words if len(w) <= 3) / n,
        1 - pairs / max(1, n - 1),
    ]


def feature_table(docs: DataFrame) -> DataFrame:
    """doc_id and x: the features."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            flat = np.array([features(t) for t in raw(batch.column("text"))], np.float64).ravel()
            x = pa.FixedSizeListArray.from_arrays(pa.array(flat), len(FEATURES)).cast(pa.list_(pa.float64()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), x], names=["doc_id", "x"])

    return documents(docs).mapInArrow(stream, "doc_id long, x array<double>")


@dataclass
class AdditiveModel:
    """Bin edges, one table a feature, and two-way tables over coarser bins."""

    base: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    coarse: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int, np.ndarray]] = field(default_factory=list)

    def margin(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        for j, (e, t) in enumerate(zip(self.edges, self.tables)):
            out += t[np.searchsorted(e, x[:, j], side="right")]
        at = {j: np.searchsorted(self.coarse[j], x[:, j], side="right") for j in {i for p in self.pairs for i in p[:2]}}
        for a, b, t in self.pairs:
            out += t[at[a], at[b]]
        return out

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -30, 30)))


def _edges(v: np.ndarray, bins: int) -> np.ndarray:
    return np.unique(np.quantile(v, np.linspace(0, 1, bins + 1)[1:-1])) if len(v) else np.array([])


def _leaf(g, h, reg):
    return -g / (h + reg)


def shallow_tree(g: np.ndarray, h: np.ndarray, depth: int, reg: float, least: float) -> np.ndarray:
    """Values of the bins under a tree of the given depth that is fitted to summed gradients."""
    out = np.full(len(g), _leaf(g.sum(), h.sum(), reg))
    if depth and len(g) > 1:
        gl, hl = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
        gr, hr = g.sum() - gl, h.sum() - hl
        gain = np.where((hl >= least) & (hr >= least), gl**2 / (hl + reg) + gr**2 / (hr + reg), -1)
        k = int(gain.argmax())
        if gain[k] > g.sum() ** 2 / (h.sum() + reg) + 1e-9:
            out[: k + 1] = shallow_tree(g[: k + 1], h[: k + 1], depth - 1, reg, least)
            out[k + 1 :] = shallow_tree(g[k + 1 :], h[k + 1 :], depth - 1, reg, least)
    return out


def pair_tree(g: np.ndarray, h: np.ndarray, reg: float, least: float) -> tuple[np.ndarray, float]:
    """Best cut along one axis, then along the other on each side; with the gain."""
    best, gain = np.zeros_like(g), 0.0
    for turned in (False, True):
        gg, hh = (g.T, h.T) if turned else (g, h)
        for k in range(1, gg.shape[0]):
            out = np.empty_like(gg)
            for side in (slice(0, k), slice(k, None)):
                out[side] = shallow_tree(gg[side].sum(axis=0), hh[side].sum(axis=0), 1, reg, least)
            now = -float((gg * out + hh * out**2 / 2).sum())
            if now > gain:
                best, gain = (out.T if turned else out).copy(), now
    return best, gain


def fit(x: np.ndarray, y: np.ndarray, rounds: int = 250, rate: float = 0.08, bins: int = 64, coarse: int = 6, n_pairs: int = 6, pair_rounds: int = 40, reg: float = 2.0, least: float = 1.5) -> AdditiveModel:
    mean = (y.sum() + 0.5) / (len(y) + 1)
    model = AdditiveModel(base=math.log(mean / (1 - mean)))
    if len(y) == 0 or y.min() == y.max():
        return model
    d = x.shape[1]
    model.edges, model.coarse = [_edges(x[:, j], bins) for j in range(d)], [_edges(x[:, j], coarse) for j in range(d)]
    at = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(model.edges)]
    model.tables = [np.zeros(len(e) + 1) for e in model.edges]
    margin = np.full(len(y), model.base)

    def slope():
        p = 1 / (1 + np.exp(-margin))
        return p - y, np.maximum(p * (1 - p), 1e-6)

    for _ in range(rounds):
        for j in range(d):
            if not len(model.edges[j]):
                continue
            g, h = slope()
            n = len(model.tables[j])
            step = rate * shallow_tree(np.bincount(at[j], g, n), np.bincount(at[j], h, n), 2, reg, least)
            model.tables[j] += step
            margin += step[at[j]]
    low = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(model.coarse)]
    size = [len(e) + 1 for e in model.coarse]

    def cells(a, b, v):
        return np.bincount(low[a] * size[b] + low[b], v, size[a] * size[b]).reshape(size[a], size[b])

    g, h = slope()
    ranked = sorted(((pair_tree(cells(a, b, g), cells(a, b, h), reg, least)[1], a, b) for a, b in combinations(range(d), 2)), reverse=True)
    model.pairs = [(a, b, np.zeros((size[a], size[b]))) for gain, a, b in ranked[:n_pairs] if gain > 0]
    for _ in range(pair_rounds):
        for a, b, table in model.pairs:
            g, h = slope()
            step = rate * pair_tree(cells(a, b, g), cells(a, b, h), reg, least)[0]
            table += step
            margin += step[low[a], low[b]]
    return model


def sampled(docs: DataFrame, labels: DataFrame, train, max_rows: int) -> DataFrame:
    """doc_id, y: at most max_rows labels, by hash of the id, of documents where the Column train holds.  Ids only, no texts."""
    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("y")).where("y in (0, 1)").where(train)
    present = docs.select("doc_id").join(marks.select("doc_id"), "doc_id", "left_semi").distinct()  # few labels are broadcast to the ids
    marks = marks.join(present, "doc_id", "left_semi")
    n = marks.count()
    if n > max_rows:  # a share by hash first, so that tasks hand on about max_rows rows together
        marks = marks.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) < F.lit(int((1 << 30) * 1.1 * max_rows / n)))
    return marks.orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(max_rows)


def learn(spark: SparkSession, docs: DataFrame, labels: DataFrame, train, max_rows: int = 20_000) -> AdditiveModel:
    """Fit on at most max_rows labels of documents where the Column train holds; only their texts get features here."""
    docs = documents(docs)
    chosen = cut(spark, sampled(docs, labels, train, max_rows), "labelled")
    texts = docs.join(F.broadcast(chosen.select("doc_id").distinct()), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"))
    rows = feature_table(texts).join(F.broadcast(chosen), "doc_id").select(F.xxhash64("doc_id").alias("at"), "doc_id", "x", "y").toPandas()
    rows = rows.sort_values(["at", "doc_id", "y"])
    x = np.array(rows["x"].tolist(), float).reshape(len(rows), len(FEATURES))
    return fit(x, rows["y"].to_numpy(float))


def scores_of(model: AdditiveModel, batch: pa.RecordBatch) -> np.ndarray:
    """The scores of a batch's texts."""
    x = np.array([features(t) for t in raw(batch.column("text"))], float).reshape(batch.num_rows, len(FEATURES))
    return model.score(x)


def trained_on(doc_id: str = "doc_id"):
    """Ids that may be learned from: crc32 of the id mod 5 is not 0."""
    return ~F.coalesce(crc_mod(doc_id, 5) == 0, F.lit(False))


def score(spark: SparkSession, docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted; rows whose crc32(doc_id) mod 5 is 0 are held out."""
    docs = documents(docs)
    model = learn(spark, docs, labels, trained_on(), max_rows)

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            s = scores_of(model, batch)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return docs.select("doc_id", (~trained_on()).alias("held_out"), "text").mapInArrow(stream, "doc_id long, held_out boolean, score double, predicted int")


def keep_good(spark: SparkSession, docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs, all columns, that the classifier doesn't reject; fitted on the labelled rows that aren't held out.

    Texts are scored where they are read, so none is shuffled and each has its features computed once.
    """
    model = learn(spark, docs, labels, trained_on(), max_rows)

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            yield batch.filter(pa.array(scores_of(model, batch) >= threshold))

    return docs.mapInArrow(stream, docs.schema)
