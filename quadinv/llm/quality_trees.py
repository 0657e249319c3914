"""Quality classifier: histogram gradient-boosted trees over statistics of a document.

Statistics of whole texts are cut into at most 64 histogram bins each; trees of fixed depth are grown level by level on the
gradient histograms of the logistic loss, and flattened into arrays, so that a batch of documents walks down all trees by a
few numpy look-ups a level.

The trees learn from at most `sample_rows` labelled documents. Null and empty texts have statistics of zero and get a score
like any text. Without labels, or with one label only, the score is the (smoothed) share of label 1. Rows that repeat a
doc_id in the labels each count; repeated documents score alike.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_sample, extended, fold, table, with_columns
from .quality_rules import SPACES, SYMBOLS, _upper, repeated_words

#: Bound of the training sample, in rows of labels.
SAMPLE_ROWS = 12_000
BINS = 64
DEPTH = 4
TREES = 80
RATE = 0.15
KEPT_FROM = 0.7
NUMBER = re.compile(r"[0-9]")
STATISTICS = ("words", "word length", "symbols", "repeated lines", "repeated windows", "stutter", "capitals", "shouting", "separators", "distinct words", "digits", "lines", "line length", "stops", "commas", "longest word", "commonest word", "long words", "short words", "longest line")


def statistics(text: str | None) -> list[float]:
    """STATISTICS of a text."""
    text = text or ""
    words = text.encode("utf-8", "replace").split()
    n = len(words)
    if not n:
        return [0.0] * len(STATISTICS)
    known: dict[bytes, int] = {}
    ids = np.fromiter([known.setdefault(w, len(known)) for w in words], np.int64, n)
    size = np.fromiter(map(len, words), np.int64, n)
    chars = len(text) - sum(map(text.count, SPACES))
    lines = [line for line in text.split("\n") if line.strip(SPACES)]
    length = [len(line) for line in lines]
    return [
        np.log1p(n),
        chars / n,
        sum(map(text.count, SYMBOLS)) / n,
        (len(lines) - len(set(lines))) / len(lines),
        repeated_words(ids) / n,
        float((ids[1:] == ids[:-1]).sum()) / n,
        _upper(text) / chars,
        text.count("!") / n,
        text.count("|") / n,
        len(known) / n,
        len(NUMBER.findall(text)) / chars,
        np.log1p(len(lines)),
        np.log1p(sum(length) / len(lines)),
        text.count(".") / n,
        text.count(",") / n,
        np.log1p(float(size.max())),
        float(np.bincount(ids).max()) / n,
        float((size > 12).mean()),
        float((size <= 3).mean()),
        np.log1p(max(length)),
    ]


class Trees:
    """Trees of one depth as arrays: node k of a level has children 2k and 2k + 1 on the next."""

    def __init__(self, base: float, feature: np.ndarray, cut: np.ndarray, leaf: np.ndarray):
        self.base, self.feature, self.cut, self.leaf = base, feature, cut, leaf

    def scores(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.base)
        row = np.arange(len(x))
        for feature, cut, leaf in zip(self.feature, self.cut, self.leaf):
            node, first = np.zeros(len(x), np.int64), 0
            depth = len(leaf).bit_length() - 1
            for level in range(depth):
                at = first + node
                node = 2 * node + (x[row, feature[at]] > cut[at])
                first += 1 << level
            total += leaf[node]
        return 1 / (1 + np.exp(-np.clip(total, -40, 40)))


def grow(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, rate: float = RATE, least: float = 20.0, ridge: float = 1.0) -> Trees:
    """Boosted trees for labels y (0 or 1) of the rows of x. least: rows that a split leaves on either side at least."""
    n, width = x.shape
    share = (y.sum() + 0.5) / (n + 1.0)
    base = float(np.log(share / (1 - share)))
    inner = (1 << depth) - 1
    if n == 0 or y.min() == y.max():
        return Trees(base, np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)))
    edges = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, BINS + 1)[1:-1])) for f in range(width)]
    binned = np.stack([np.searchsorted(e, x[:, f]) for f, e in enumerate(edges)])  # bin k: above edge k - 1, at most edge k
    total, features, cuts, leaves = np.full(n, base), [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-total))
        g, h = y - p, p * (1 - p)
        node = np.zeros(n, np.int64)
        feature, cut = np.zeros(inner, np.int64), np.full(inner, np.inf)
        first = 0
        for level in range(depth):
            wide = 1 << level
            best = np.full(wide, 1e-6)
            place = np.full(wide, -1)
            for f in range(width):
                key = node * BINS + binned[f]
                sums = [np.bincount(key, v, wide * BINS).reshape(wide, BINS).cumsum(axis=1) for v in (g, h, None)]
                (gl, hl, nl), (gt, ht, nt) = sums, (s[:, -1:] for s in sums)
                gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
                gain = np.where((nl >= least) & (nt - nl >= least), gain, 0)[:, : len(edges[f])]
                if not gain.shape[1]:
                    continue
                at = gain.argmax(axis=1)
                top = gain[np.arange(wide), at]
                better = top > best
                best[better] = top[better]
                place[better] = f * BINS + at[better]
            for k in np.flatnonzero(place >= 0):
                feature[first + k] = place[k] // BINS
                cut[first + k] = edges[place[k] // BINS][place[k] % BINS]
            at = first + node
            node = 2 * node + (x[np.arange(n), feature[at]] > cut[at])
            first += wide
        leaf = rate * np.bincount(node, g, inner + 1) / (np.bincount(node, h, inner + 1) + ridge)
        total += leaf[node]
        features.append(feature)
        cuts.append(cut)
        leaves.append(leaf)
    return Trees(base, np.stack(features), np.stack(cuts), np.stack(leaves))


def _stats_column(values: list[str | None]) -> np.ndarray:
    return np.array([statistics(v) for v in values], np.float64).reshape(-1, len(STATISTICS))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, text: str = "text", doc_id: str = "doc_id", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """(y, x): label and statistics of at most sample_rows labelled documents. The sample is small enough to broadcast."""
    known = labels.filter(F.col(label).isin(0, 1) & F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("label_id"), F.col(label).cast("int").alias("y"))
    some = bounded_sample(known, "label_id", sample_rows)
    both = docs.select(F.col(doc_id).alias("label_id"), F.col(text).alias("text")).join(F.broadcast(some), "label_id").select("y", "text")

    def run(batches):
        for batch in batches:
            found = _stats_column(batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(found), pa.list_(pa.float64()))], names=["y", "x"])

    return both.mapInArrow(run, "y int, x array<double>")


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", sample_rows: int = SAMPLE_ROWS) -> Trees:
    rows = sorted((r.y, tuple(r.x)) for r in training_rows(docs, labels, label, sample_rows=sample_rows).collect())
    return grow(np.array([r[1] for r in rows], np.float64).reshape(-1, len(STATISTICS)), np.array([r[0] for r in rows], np.float64))


def scored(docs: DataFrame, model: Trees, text: str = "text", keep: list[str] | None = None, kept_from: float = KEPT_FROM) -> DataFrame:
    """docs (or its columns in keep) with score and predicted; the texts alone are looked at."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("score", "predicted")]

    def run(batches):
        for batch in batches:
            score = shipped.value.scores(_stats_column(batch.column(text).to_pylist()))
            yield with_columns(batch, {"score": pa.array(score, pa.float64()), "predicted": pa.array((score >= kept_from).astype(np.int32))}, kept)

    return docs.select(*dict.fromkeys([*kept, text])).mapInArrow(run, extended(docs, "score double, predicted int", kept))


def op3_quality_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held_out = fold("doc_id", 4, 2)
    model = fit(docs, labels.filter(~held_out))
    return scored(docs.select("doc_id", "text"), model, keep=["doc_id"]).select("doc_id", held_out.alias("held_out"), "score", "predicted")
