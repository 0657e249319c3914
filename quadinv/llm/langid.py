"""Language identification by a byte convolutional network, trained in numpy on labelled text.

Bytes are embedded; filters of several widths run over a window of fixed length, the greatest response of each filter in the
window is kept, and a softmax over these gives the window's language. A text is cut into such windows from begin to end and
gets the mean of their distributions, the last window by the share of it that the text fills. For prediction, embedding and
filters are folded into tables over byte pairs, so that a convolution is a few look-ups.

The network learns from some windows of about `sample_docs` texts of each language, whatever the number of languages; the driver
holds one count a language and these windows. A null text, and one without a letter (Unicode category L, in training and in
prediction; numerals like \u00bd or \u2167 are none), is `und` with score 0. Without any learnable text everything is `und`. Repeated
rows are predicted alike.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import chunks, extended, fold, table, utf8, with_columns

LENGTH = 192
WIDTHS = (2, 3, 4)
FILTERS = 16
EMBEDDED = 8
#: Bound of the training sample, in texts of each language (expected number), and windows of each text.
SAMPLE_DOCS = 300
SAMPLE_WINDOWS = 5
UNKNOWN = "und"


class Network:
    def __init__(self, languages: list[str], seed: int = 7):
        draw = np.random.default_rng(seed)
        self.languages = languages
        self.p = {"e": draw.normal(0, 0.5, (256, EMBEDDED)), "c": np.zeros(len(languages)), "v": draw.normal(0, 0.2, (len(WIDTHS) * FILTERS, len(languages)))}
        for w in WIDTHS:
            self.p[f"w{w}"] = draw.normal(0, (2 / (w * EMBEDDED)) ** 0.5, (w, EMBEDDED, FILTERS))
            self.p[f"b{w}"] = np.zeros(FILTERS)
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    def _gradients(self, data: np.ndarray, target: np.ndarray) -> dict[str, np.ndarray]:
        p, n = self.p, len(data)
        x = p["e"][data]
        pooled, peaks = [], []
        for w in WIDTHS:
            span = data.shape[1] - w + 1
            response = sum(x[:, j : j + span] @ p[f"w{w}"][j] for j in range(w))
            at = response.argmax(axis=1)
            peaks.append(at)
            pooled.append(np.take_along_axis(response, at[:, None], axis=1)[:, 0] + p[f"b{w}"])
        raw = np.concatenate(pooled, axis=1)
        active = np.maximum(raw, 0)
        away = _softmax(active @ p["v"] + p["c"])
        away[np.arange(n), target] -= 1
        away /= n
        out = {"v": active.T @ away, "c": away.sum(axis=0), "e": np.zeros_like(p["e"])}
        back = (away @ p["v"].T) * (raw > 0)
        row = np.arange(n)[:, None]
        for k, w in enumerate(WIDTHS):
            mine = back[:, k * FILTERS : (k + 1) * FILTERS]
            out[f"b{w}"] = mine.sum(axis=0)
            out[f"w{w}"] = np.zeros_like(p[f"w{w}"])
            for j in range(w):
                symbol = data[row, peaks[k] + j]
                out[f"w{w}"][j] = np.einsum("nf,nfd->df", mine, p["e"][symbol])
                np.add.at(out["e"], symbol.ravel(), (mine[:, :, None] * p[f"w{w}"][j].T[None]).reshape(-1, EMBEDDED))
        return out

    def train(self, data: np.ndarray, target: np.ndarray, epochs: int = 6, batch: int = 64, rate: float = 0.004, seed: int = 7) -> Network:
        draw = np.random.default_rng(seed)
        first = {k: np.zeros_like(v) for k, v in self.p.items()}
        second = {k: np.zeros_like(v) for k, v in self.p.items()}
        step = 0
        for _ in range(epochs):
            order = draw.permutation(len(data))
            for i in range(0, len(order), batch):
                step += 1
                some = order[i : i + batch]
                for k, g in self._gradients(data[some], target[some]).items():
                    first[k] = 0.9 * first[k] + 0.1 * g
                    second[k] = 0.999 * second[k] + 0.001 * g * g
                    self.p[k] -= (rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        return self

    def folded(self) -> Folded:
        return Folded(self)


class Folded:
    """The trained network as tables: for each width, responses to its byte pairs and, if the width is odd, to its last byte."""

    def __init__(self, network: Network):
        p, self.languages = network.p, network.languages
        self.tables = []
        for w in WIDTHS:
            single = [p["e"] @ p[f"w{w}"][j] for j in range(w)]
            pairs = [(single[j][:, None] + single[j + 1][None]).reshape(65536, FILTERS) for j in range(0, w - 1, 2)]
            self.tables.append((w, pairs, single[-1] if w % 2 else None, p[f"b{w}"]))
        self.v, self.c = p["v"], p["c"]

    def windows(self, data: np.ndarray) -> np.ndarray:
        """Distribution over the languages for each row of bytes."""
        out = np.empty((len(data), len(self.languages)), np.float32)
        for i in range(0, len(data), 256):
            part = data[i : i + 256]
            pair = part[:, :-1].astype(np.int32) * 256 + part[:, 1:]
            pooled = []
            for w, pairs, last, bias in self.tables:
                span = part.shape[1] - w + 1
                response = np.take(pairs[0], pair[:, :span], axis=0)
                for k in range(1, len(pairs)):
                    response += np.take(pairs[k], pair[:, 2 * k : 2 * k + span], axis=0)
                if last is not None:
                    response += np.take(last, part[:, w - 1 : w - 1 + span], axis=0)
                pooled.append(response.max(axis=1) + bias)
            out[i : i + 256] = _softmax(np.maximum(np.concatenate(pooled, axis=1), 0) @ self.v + self.c)
        return out

    def texts(self, texts: list[bytes]) -> tuple[list[str], list[float]]:
        size = np.fromiter(map(len, texts), np.int64, len(texts))
        count = -(-size // LENGTH)
        data = np.frombuffer(b"".join(t.ljust(int(n) * LENGTH) for t, n in zip(texts, count)), np.uint8).reshape(-1, LENGTH)
        each = self.windows(data)
        weight = np.full(len(data), 1.0, np.float32)
        ends = np.cumsum(count)
        some = count > 0
        weight[ends[some] - 1] = ((size[some] - 1) % LENGTH + 1) / LENGTH
        total = np.zeros((len(texts), len(self.languages)))
        np.add.at(total, np.repeat(np.arange(len(texts)), count), each * weight[:, None])
        share = total / np.maximum(total.sum(axis=1, keepdims=True), 1e-12)
        best = share.argmax(axis=1)
        known = [any(map(str.isalpha, t.decode("utf-8", "replace"))) for t in texts]  # exactly the categories L
        return [self.languages[b] if k else UNKNOWN for b, k in zip(best, known)], [float(min(1.0, share[i, b])) if k else 0.0 for i, (b, k) in enumerate(zip(best, known))]


def _softmax(x: np.ndarray) -> np.ndarray:
    x = np.exp(x - x.max(axis=1, keepdims=True))
    return x / x.sum(axis=1, keepdims=True)


def training_windows(docs: DataFrame, text: str, lang: str, doc_id: str, sample_docs: int, per_text: int = SAMPLE_WINDOWS) -> DataFrame:
    """(lang, data): windows evenly spread over the texts of about sample_docs documents of each language."""
    labelled = docs.filter(F.col(lang).isNotNull() & F.col(text).rlike(r"\p{L}"))
    rates = {r.lang: sample_docs / r.n for r in labelled.groupBy(F.col(lang).alias("lang")).agg(F.count("*").alias("n")).collect()}
    if not rates:
        return docs.sparkSession.createDataFrame([], "lang string, data binary")
    drawn = F.pmod(F.xxhash64(doc_id, F.lit("language")), F.lit(1 << 20)) / float(1 << 20)
    names, shares = zip(*sorted(rates.items()))
    rate = F.map_from_arrays(F.lit(list(names)), F.lit([float(x) for x in shares]))[F.col(lang)]

    def run(batches):
        for batch in batches:
            langs, data = [], []
            for value, name in zip(utf8(batch.column(0)), batch.column(1).to_pylist()):
                for k in range(min(per_text, -(-len(value) // LENGTH))):
                    begin = k * max(0, len(value) - LENGTH) // max(1, per_text - 1)
                    langs.append(name)
                    data.append(value[begin : begin + LENGTH].ljust(LENGTH))
            yield pa.RecordBatch.from_arrays([pa.array(langs, pa.string()), pa.array(data, pa.binary())], names=["lang", "data"])

    return labelled.filter(drawn < rate).select(text, lang).mapInArrow(run, "lang string, data binary")


def fit(docs: DataFrame, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", sample_docs: int = SAMPLE_DOCS) -> Folded | None:
    rows = sorted((r.lang, bytes(r.data)) for r in training_windows(docs, text, lang, doc_id, sample_docs).collect())
    if not rows:
        return None
    languages = sorted({name for name, _ in rows})
    data = np.frombuffer(b"".join(d for _, d in rows), np.uint8).reshape(-1, LENGTH)
    return Network(languages).train(data, np.array([languages.index(name) for name, _ in rows])).folded()


def predicted(docs: DataFrame, model: Folded | None, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns in keep) with lang_pred and score; the texts alone are looked at."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in ("lang_pred", "score")]

    def run(batches):
        network = shipped.value
        for batch in batches:
            names, scores = [], []
            for _, piece in chunks(utf8(batch.column(text))):
                a, b = network.texts(piece) if network else ([UNKNOWN] * len(piece), [0.0] * len(piece))
                names += a
                scores += b
            yield with_columns(batch, {"lang_pred": pa.array(names, pa.string()), "score": pa.array(scores, pa.float64())}, kept)

    return docs.select(*dict.fromkeys([*kept, text])).mapInArrow(run, extended(docs, "lang_pred string, score double", kept))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = fold("doc_id", 4, 2)
    model = fit(docs.filter(~held_out))
    return predicted(docs.select("doc_id", "text"), model, keep=["doc_id"]).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")
