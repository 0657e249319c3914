"""Quality rules by weak supervision: rules vote or abstain, and a latent-class model weighs their votes.

Each rule says good, bad or nothing about a text. Expectation-maximisation estimates from the votes alone how often each
rule votes what on good and on bad texts, and the share of good texts; a text's posterior probability of being good decides, so
that a symptom which says little is outvoted. The corpus reaches the driver only as counts of distinct vote patterns, at most
3 ** rules of them. Texts are measured once; votes and measures are kept for the verdict.

Words are `[^\\x20\\x09-\\x0D]+`. Null and empty texts have no words and fail the base test (fewer than 20 words). Repeated
rows are judged alike. Columns of the documents named as a result column are replaced.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import covered, cut, extended, mix, renamed, rolling, table, unnamed, with_columns

SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
WINDOW = 8
LEAST_WORDS = 20
MOST_REPEATED_PERCENT = 30
KEPT_FROM = 0.5
RULES = ("symbols", "capitals", "stutter", "repeated windows", "repeated lines", "length", "word length", "shouting", "separators", "variety", "sentences")
#: Prior guesses of each rule's votes: P(bad, good | good text) and P(bad, good | bad text); the rest abstains.
GUESSES = (
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.005, 0.0), (0.05, 0.0)),  # lists and verse repeat lines too
    ((0.02, 0.8), (0.2, 0.5)),
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.0001, 0.0), (0.2, 0.0)),
    ((0.02, 0.8), (0.2, 0.5)),
    ((0.02, 0.8), (0.2, 0.5)),
)
SHARE_GUESS = 0.9
#: What the guesses count, as multiples of all texts, so that the verdict doesn't depend on how many there are. How seldom good texts
#: show a symptom is known well, for the rules were written so; if it weren't, a rare symptom that comes without the common ones would
#: be taken for a habit of good texts. Less is known of the rules that say either, and of what bad texts are like.
SYMPTOM_WEIGHT, EITHER_WEIGHT, BAD_WEIGHT, SHARE_WEIGHT = 10.0, 0.02, 0.01, 0.05
GOOD, BAD, ABSTAIN = 1, 0, 2


def repeated_words(ids: np.ndarray, window: int = WINDOW) -> int:
    """Words in windows that occur twice or more in one text."""
    if len(ids) <= window:
        return 0
    hashes = rolling(mix(ids.astype(np.uint64) + np.uint64(1)), window, 0x9E3779B97F4A7C15)
    order = np.argsort(hashes, kind="stable")
    equal = hashes[order][1:] == hashes[order][:-1]
    if not equal.any():
        return 0
    again = np.zeros(len(hashes), bool)
    again[order[1:][equal]] = True
    again[order[:-1][equal]] = True
    return int(covered(np.flatnonzero(again), window, len(ids)).sum())


def measured(text: str | None) -> tuple[tuple[int, int, int, int, int], tuple[int, ...]]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words) of a text, and each rule's vote."""
    text = text or ""
    words = text.encode("utf-8", "replace").split()
    n = len(words)
    word_chars = len(text) - sum(map(text.count, SPACES))
    counts = {c: text.count(c) for c in SYMBOLS}
    symbols = sum(counts.values())
    known: dict[bytes, int] = {}
    ids = np.fromiter([known.setdefault(w, len(known)) for w in words], np.int64, n)
    lines = [line for line in text.split("\n") if line.strip(SPACES)]
    dup_lines = len(lines) - len(set(lines))
    repeats = repeated_words(ids)
    if not n:
        return (0, word_chars, symbols, dup_lines, 0), (ABSTAIN,) * len(RULES)
    stutter = int((ids[1:] == ids[:-1]).sum())
    upper, lower = sum(map(str.isupper, text)) if n < 200 else _upper(text), word_chars
    marks = text.count("!!")

    def vote(bad: bool, good: bool) -> int:
        return BAD if bad else GOOD if good else ABSTAIN

    stops = text.count(".") + text.count("?")
    votes = (
        vote(symbols > 0.3 * n, False),
        vote(upper > 0.5 * lower, False),
        vote(stutter > 0.2 * n, False),
        vote(repeats > 0.3 * n, False),
        vote(len(lines) > 3 and dup_lines > 0.3 * len(lines), False),
        vote(n < LEAST_WORDS, n >= 50),
        vote(not 2 <= word_chars / n <= 15, False),
        vote(marks > 0.2 * n, False),
        vote(counts["|"] > 0.2 * n, False),
        vote(n >= 50 and len(known) < 0.1 * n, n < 2000 and len(known) >= 0.4 * n),
        vote(n >= 100 and stops < 0.002 * n, 0.01 * n <= stops <= 0.3 * n),
    )
    return (n, word_chars, symbols, dup_lines, repeats), votes


def _upper(text: str) -> int:
    """Capital letters, counted as the characters that lower-casing changes."""
    low = text.lower()
    if len(low) != len(text):
        return sum(map(str.isupper, text))
    a, b = (np.frombuffer(t.encode("utf-32-le", "replace"), np.uint32) for t in (text, low))
    return int((a != b).sum())


def _pattern(votes: tuple[int, ...]) -> int:
    code = 0
    for v in votes:
        code = 3 * code + v
    return code


def base_failed(base: tuple[int, ...]) -> bool:
    return base[0] < LEAST_WORDS or 100 * base[4] > MOST_REPEATED_PERCENT * base[0]


def guesses() -> np.ndarray:
    """GUESSES as [class, rule, vote]."""
    out = np.empty((2, len(RULES), 3))
    for r, pair in enumerate(GUESSES):
        for c, (bad, good) in zip((GOOD, BAD), pair):
            out[c, r, BAD], out[c, r, GOOD], out[c, r, ABSTAIN] = bad, good, 1 - bad - good
    return np.maximum(out, 1e-6)


def posteriors(patterns: np.ndarray, counts: np.ndarray, turns: int = 500) -> tuple[np.ndarray, np.ndarray, float]:
    """Posterior of good for each pattern, P(vote | class) as [class, rule, vote] with class 1 good, and the share of good.

    Starts from the guesses, which then count as so many texts of either class beside those that are there.
    """
    told, share = guesses(), SHARE_GUESS
    if not len(patterns):
        return np.empty(0), told, share
    rules = len(RULES)
    digits = np.stack([patterns // 3 ** (rules - 1 - r) % 3 for r in range(rules)], axis=1)
    one_hot = (digits[:, :, None] == np.arange(3)).astype(float)
    weight = counts.astype(float)
    whole = weight.sum()
    weights = np.array([[BAD_WEIGHT] * rules, [EITHER_WEIGHT if good else SYMPTOM_WEIGHT for (_, good), _ in GUESSES]])
    prior = guesses() * whole * weights[:, :, None]
    good = np.zeros(len(patterns))
    for _ in range(turns):
        log = np.einsum("prv,crv->cp", one_hot, np.log(told)) + np.log([1 - share, share])[:, None]
        new = 1 / (1 + np.exp(np.clip(log[0] - log[1], -50, 50)))
        moved = float(np.abs(new - good).max())
        good = new
        if moved < 1e-9:
            break
        told = np.einsum("cp,p,prv->crv", np.stack((1 - good, good)), weight, one_hot) + prior
        told /= told.sum(axis=2, keepdims=True)
        share = float(((good * weight).sum() + SHARE_GUESS * SHARE_WEIGHT * whole) / (whole * (1 + SHARE_WEIGHT)))
    return good, told, share


MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean"


def voted(docs: DataFrame, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """docs (or its columns in keep) with the base measures, base_failed and vote_pattern, the rules' votes as one number."""
    names = [part.split()[0] for part in MEASURES.split(", ")]
    kept = [c for c in (docs.columns if keep is None else keep) if c.lower() not in (*names, "vote_pattern")]

    def run(batches):
        for batch in batches:
            found = [measured(value) for value in batch.column(text).to_pylist()]
            columns = {name: pa.array([base[k] for base, _ in found], pa.int64()) for k, name in enumerate(names[:5])}
            columns["base_failed"] = pa.array([base_failed(base) for base, _ in found], pa.bool_())
            columns["vote_pattern"] = pa.array([_pattern(votes) for _, votes in found], pa.int64())
            yield with_columns(batch, columns, kept)

    return docs.select(*dict.fromkeys([*kept, text])).mapInArrow(run, extended(docs, MEASURES + ", vote_pattern long", kept))


def fit(votes: DataFrame) -> dict[int, float]:
    """Posterior of good for every pattern of votes of the texts that passed the base test; all of them count."""
    rows = sorted(votes.filter("not base_failed").groupBy("vote_pattern").agg(F.count("*").alias("n")).collect())
    good, _, _ = posteriors(np.array([r.vote_pattern for r in rows], np.int64), np.array([r.n for r in rows], np.int64))
    return {r.vote_pattern: float(g) for r, g in zip(rows, good)}


def judged(docs: DataFrame, model: dict[int, float] | None = None, text: str = "text", keep: list[str] | None = None, kept_from: float = KEPT_FROM) -> DataFrame:
    """docs (or its columns in keep) with the base measures, base_failed, quality (posterior of good) and kept."""
    plain, name = unnamed(docs)
    own = ["quality", "kept", *(part.split()[0] for part in MEASURES.split(", "))]
    wanted = [c for c in (docs.columns if keep is None else keep) if c.lower() not in own]
    votes = cut(voted(plain, name[text], [name[c] for c in wanted]))
    known = fit(votes) if model is None else model
    table = docs.sparkSession.createDataFrame(sorted(known.items()), "vote_pattern long, posterior double")
    good = F.when(F.col("base_failed"), 0.0).otherwise(F.coalesce("posterior", F.lit(0.5)))
    told = votes.join(F.broadcast(table), "vote_pattern", "left").withColumn("quality", good)  # at most 3 ** rules patterns
    return told.select(*[F.col(name[c]).alias(c) for c in wanted], *own[2:], "quality", (~F.col("base_failed") & (F.col("quality") >= kept_from)).alias("kept"))


def accepted(docs: DataFrame, text: str = "text", **options) -> DataFrame:
    """The documents that the rules keep, with their own columns."""
    plain, name = unnamed(docs)
    return renamed(judged(plain, text=name[text], **options).filter("kept"), docs)


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = judged(table(spark, sf_dir, "documents"), keep=["doc_id"])
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality")
