"""Toxicity by a factorization machine over hashed terms.

A text's terms are its distinct words (runs of letters, lower-cased) and the first four, five and six letters of longer ones,
hashed into 2**18 slots. Each slot has a weight and a vector of factors; the score is the logistic of the bias, the weights of
the terms present and the inner products of all pairs of their vectors, so that two terms can mean together what neither
means alone. The pairs are summed in linear time as half the square of the sum less the sum of squares.

The machine learns from at most `sample_rows` labelled documents of each label. Only slots whose documents bear the label
significantly more or less often than others, by themselves or together with another slot than with either alone, get a weight
and factors; all others stay zero, so that the many words of a long text that have nothing to do with the label say nothing,
met before or not. Null and empty texts have no terms and the score of the bias alone.
Without labels, or with one only, the score is the smoothed share of label 1. Repeated documents score alike.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_sample, cut, extended, fold, table, with_columns

BITS = 18
FACTORS = 6
PREFIXES = (4, 5, 6)
#: Bound of the training sample, in rows of labels for either label.
SAMPLE_ROWS = 4_000
TOXIC_FROM = 0.5
LEAST_DOCS, LEAST_Z = 3, 4.0
#: Chance, over all pairs of slots, of taking one for significant that isn't.
PAIR_CHANCE = 0.01
PAIR_BLOCK = 1024
WORD = re.compile(r"[^\W\d_]+")


class Terms(dict):
    """Word to its slots, remembered up to a bounded number of words."""

    LIMIT = 300_000

    def __missing__(self, word: str) -> tuple[int, ...]:
        if len(self) >= self.LIMIT:
            self.clear()
        parts = [word, *(f"{word[:k]}*" for k in PREFIXES if len(word) >= k)]
        slots = self[word] = tuple({xxhash.xxh3_64_intdigest(p.encode()) >> (64 - BITS) for p in parts})
        return slots

    def of(self, text: str | None) -> np.ndarray:
        found: set[int] = set()
        for word in set(WORD.findall((text or "").lower())):
            found.update(self[word])
        return np.fromiter(found, np.int64, len(found))


class Machine:
    def __init__(self, bias: float, weights: np.ndarray, factors: np.ndarray):
        self.bias, self.weights, self.factors = bias, weights, factors

    def scores(self, terms: list[np.ndarray]) -> np.ndarray:
        size = np.fromiter(map(len, terms), np.int64, len(terms))
        flat = np.concatenate(terms) if len(terms) else np.empty(0, np.int64)
        return 1 / (1 + np.exp(-np.clip(self._raw(flat, size)[0], -40, 40)))

    def _raw(self, flat: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        row = np.repeat(np.arange(len(size)), size)
        v = self.factors[flat]
        linear = np.bincount(row, self.weights[flat], len(size))
        total = np.zeros((len(size), self.factors.shape[1]))
        np.add.at(total, row, v)
        squares = np.bincount(row, (v * v).sum(axis=1), len(size))
        return self.bias + linear + 0.5 * ((total * total).sum(axis=1) - squares), total


def counted(terms: list[np.ndarray], y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each slot, in how many documents it is, and in how many of label 1."""
    size = np.fromiter(map(len, terms), np.int64, len(terms))
    flat = np.concatenate(terms)
    return np.bincount(flat, minlength=1 << BITS), np.bincount(flat, np.repeat(y, size), minlength=1 << BITS)


def significant(met: np.ndarray, bad: np.ndarray, share: float) -> np.ndarray:
    """Slots in at least LEAST_DOCS documents whose share of label 1 is LEAST_Z standard errors off that of all."""
    z = np.abs(bad - met * share) / np.sqrt(np.maximum(met * share * (1 - share), 1e-9))
    return (met >= LEAST_DOCS) & (z >= LEAST_Z)


def _surprise(bad: np.ndarray, met: np.ndarray, share: np.ndarray) -> np.ndarray:
    """Signed -log of the bound (Chernoff's) on the chance of so many or few of label 1 among met documents at the given share."""
    own = bad / np.maximum(met, 1)
    with np.errstate(divide="ignore", invalid="ignore"):
        apart = np.where(own > 0, own * np.log(own / share), 0) + np.where(own < 1, (1 - own) * np.log((1 - own) / (1 - share)), 0)
    return np.sign(own - share) * met * apart


def pairable(met: np.ndarray, bad: np.ndarray, overall: float) -> tuple[np.ndarray, np.ndarray, float]:
    """Slots that aren't too rare for a pair of theirs to be significant, each slot's share of label 1, and the bound that decides.

    A pair is in no more documents than its slots.
    """
    share = np.clip((bad + overall) / (met + 1), 1e-12, 1 - 1e-12)
    most = np.maximum(-bad * np.log(share), -(met - bad) * np.log(1 - share))  # where all documents of one label are common, and no others
    least, used = np.log(2 / PAIR_CHANCE), np.empty(0, np.int64)
    for _ in range(8):  # fewer slots make fewer pairs, and more pairs ask for more documents
        bound = least + np.log(max(len(used) or (met > 1).sum(), 2.0)) * 2 - np.log(2)
        used, before = np.flatnonzero(most >= bound), used
        if len(used) == len(before):
            break
    return used, share, bound


def paired(terms: list[np.ndarray], y: np.ndarray, used: np.ndarray, share: np.ndarray, bound: float) -> np.ndarray:
    """Slots of pairs whose common documents bear label 1 significantly more, or less, often than the documents of either slot.

    used, share, bound: from pairable. These slots are compared all with all, block by block.
    """
    slots = 1 << BITS
    chosen = np.zeros(slots, bool)
    size = np.fromiter(map(len, terms), np.int64, len(terms))
    flat, row = np.concatenate(terms), np.repeat(np.arange(len(terms)), size)
    at = np.full(slots, -1)
    at[used] = np.arange(len(used))
    known = at[flat] >= 0
    place, row = at[flat[known]], row[known]
    order = np.argsort(place, kind="stable")
    place, row = place[order], row[order]

    def block(i: int) -> np.ndarray:
        begin, end = np.searchsorted(place, (i, i + PAIR_BLOCK))
        out = np.zeros((len(y), min(PAIR_BLOCK, len(used) - i)), np.float32)
        out[row[begin:end], place[begin:end] - i] = 1
        return out

    for i in range(0, len(used), PAIR_BLOCK):
        one = block(i)
        toxic = one * y[:, None].astype(np.float32)
        for j in range(i, len(used), PAIR_BLOCK):
            two = one if j == i else block(j)
            met_by, bad_by = one.T @ two, toxic.T @ two
            a, b = used[i : i + one.shape[1]], used[j : j + two.shape[1]]
            near = np.ones(met_by.shape, bool)
            for s in (share[a][:, None].astype(np.float32), share[b].astype(np.float32)):
                off = bad_by - met_by * s  # the chi-square is never below the bound that decides, and takes no logarithms
                near &= off * off >= np.float32(0.99 * bound) * met_by * (s * (1 - s))
            p, q = np.nonzero(near & (met_by > 0))
            n, bad = met_by[p, q].astype(float), bad_by[p, q].astype(float)
            for sign in (1, -1):
                sure = (sign * _surprise(bad, n, share[a[p]]) >= bound) & (sign * _surprise(bad, n, share[b[q]]) >= bound)
                chosen[a[p[sure]]] = True
                chosen[b[q[sure]]] = True
    return chosen


def learn(terms: list[np.ndarray], y: np.ndarray, counts: tuple[np.ndarray, np.ndarray] | None = None, epochs: int = 15, batch: int = 64, rate: float = 0.02, ridge: float = 1e-4, seed: int = 11) -> Machine:
    """Adam on the logistic loss, with both labels weighed to equal shares. counts: of all terms, where some of them have been left out."""
    slots = 1 << BITS
    share = float((y.sum() + 0.5) / (len(y) + 1.0))
    machine = Machine(float(np.log(share / (1 - share))), np.zeros(slots), np.zeros((slots, FACTORS)))
    if not len(y) or y.min() == y.max():
        return machine
    draw = np.random.default_rng(seed)
    met, bad = counts or counted(terms, y)
    chosen = significant(met, bad, y.mean()) | paired(terms, y, *pairable(met, bad, y.mean()))
    used = np.flatnonzero(chosen)
    terms = [t[chosen[t]] for t in terms]
    machine.bias = 0.0
    machine.factors[used] = draw.normal(0, 0.01, (len(used), FACTORS))
    weigh = np.where(y == 1, 0.5 / max(share, 1e-9), 0.5 / max(1 - share, 1e-9))
    mw, sw = np.zeros(slots), np.zeros(slots)
    mv, sv = np.zeros((slots, FACTORS)), np.zeros((slots, FACTORS))
    mb = sb = 0.0
    step = 0
    for _ in range(epochs):
        order = draw.permutation(len(y))
        for i in range(0, len(order), batch):
            step += 1
            some = order[i : i + batch]
            size = np.fromiter((len(terms[k]) for k in some), np.int64, len(some))
            flat = np.concatenate([terms[k] for k in some])
            raw, total = machine._raw(flat, size)
            away = weigh[some] * (1 / (1 + np.exp(-np.clip(raw, -40, 40))) - y[some]) / len(some)
            row = np.repeat(np.arange(len(some)), size)
            slot, which = np.unique(flat, return_inverse=True)
            gw = np.bincount(which, away[row], len(slot)) + ridge * machine.weights[slot]
            gv = np.zeros((len(slot), FACTORS))
            np.add.at(gv, which, away[row][:, None] * (total[row] - machine.factors[flat]))
            gv += ridge * machine.factors[slot]
            up, down = 1 - 0.9**step, 1 - 0.999**step
            for g, value, m, s in ((gw, machine.weights, mw, sw), (gv, machine.factors, mv, sv)):
                m[slot] = 0.9 * m[slot] + 0.1 * g
                s[slot] = 0.999 * s[slot] + 0.001 * g * g
                value[slot] -= rate * (m[slot] / up) / (np.sqrt(s[slot] / down) + 1e-6)
            g = float(away.sum())
            mb, sb = 0.9 * mb + 0.1 * g, 0.999 * sb + 0.001 * g * g
            machine.bias -= rate * (mb / up) / (sb / down) ** 0.5 if sb else 0.0
    return machine


def training_rows(docs: DataFrame, labels: DataFrame, label: str, text: str = "text", doc_id: str = "doc_id", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """(y, terms) of at most sample_rows documents of either label. The sample is small enough to broadcast."""
    known = labels.filter(F.col(label).isin(0, 1) & F.col(doc_id).isNotNull()).select(F.col(doc_id).alias("label_id"), F.col(label).cast("int").alias("y"))
    some = bounded_sample(known.filter("y = 1"), "label_id", sample_rows).unionByName(bounded_sample(known.filter("y = 0"), "label_id", sample_rows))
    both = docs.select(F.col(doc_id).alias("label_id"), F.col(text).alias("text")).join(F.broadcast(some), "label_id").select("y", "text")

    def run(batches):
        terms = Terms()
        for batch in batches:
            found = [np.sort(terms.of(v)).astype(np.int32) for v in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.list_(pa.int32()))], names=["y", "terms"])

    return both.mapInArrow(run, "y int, terms array<int>")


def fit(docs: DataFrame, labels: DataFrame, label: str = "toxic", sample_rows: int = SAMPLE_ROWS) -> Machine:
    """The driver gets two numbers a slot first, and then only those slots of the sample that may matter."""
    sample = cut(training_rows(docs, labels, label, sample_rows=sample_rows))
    met, bad = np.zeros(1 << BITS, np.int64), np.zeros(1 << BITS)
    counts = sample.select("y", F.explode("terms").alias("slot")).groupBy("slot").agg(F.count("*").alias("met"), F.sum("y").alias("bad")).toArrow()
    at = counts.column("slot").to_numpy()
    met[at], bad[at] = counts.column("met").to_numpy(), counts.column("bad").to_numpy()
    rows, toxic = sample.agg(F.count("*"), F.coalesce(F.sum("y"), F.lit(0))).first()
    wanted = np.zeros(1 << BITS, bool)
    if 0 < toxic < rows:
        wanted |= significant(met, bad, toxic / rows)
        wanted[pairable(met, bad, toxic / rows)[0]] = True
    packed = np.packbits(wanted)

    def run(batches):
        mask = np.unpackbits(packed).astype(bool)
        for batch in batches:
            found = [t[mask[t]] for t in (np.asarray(v.values.to_numpy()) for v in batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.list_(pa.int32()))], names=["y", "terms"])

    got = sample.mapInArrow(run, "y int, terms array<int>").toArrow()
    y = got.column("y").to_numpy().astype(np.float64)
    terms = [np.asarray(t.values.to_numpy(), np.int64) for t in got.column("terms")]
    order = sorted(range(len(terms)), key=lambda k: (y[k], len(terms[k]), terms[k].tobytes()))
    return learn([terms[k] for k in order], y[order], (met, bad))


def scored(docs: DataFrame, model: Machine, text: str = "text", keep: list[str] | None = None, toxic_from: float = TOXIC_FROM) -> DataFrame:
    """docs (or its columns in keep) with score and predicted; the texts alone are looked at."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("score", "predicted")]

    def run(batches):
        machine, terms = shipped.value, Terms()
        for batch in batches:
            score = np.empty(batch.num_rows)
            values = batch.column(text)
            for i in range(0, batch.num_rows, 256):
                score[i : i + 256] = machine.scores([terms.of(v) for v in values.slice(i, 256).to_pylist()])
            yield with_columns(batch, {"score": pa.array(score, pa.float64()), "predicted": pa.array((score >= toxic_from).astype(np.int32))}, kept)

    return docs.select(*dict.fromkeys([*kept, text])).mapInArrow(run, extended(docs, "score double, predicted int", kept))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    held_out = fold("doc_id", 5, 0)
    model = fit(docs, labels.filter(~held_out))
    return scored(docs.select("doc_id", "text"), model, keep=["doc_id"]).select("doc_id", held_out.alias("held_out"), "score", "predicted")
