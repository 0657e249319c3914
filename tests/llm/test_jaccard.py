"""Near-duplicates by Jaccard similarity against all pairs, and the pipeline's stage on copies with a few changed words."""

import random
import re

import corpus_pipeline as cp
from quadinv.llm import jaccard

from .test_operators import DOCS, good_text


def all_pairs(texts: dict) -> dict:
    """id -> smallest id of its component, from {id: text}, every pair compared as sets of strings."""
    sets = {}
    for k, text in texts.items():
        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        sets[k] = {" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))}
    keys = sorted(sets)
    root = {k: k for k in keys}
    for a in keys:
        for b in keys:
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                low, high = sorted((root[a], root[b]))
                root = {k: low if r == high else r for k, r in root.items()}
    return root


def changed(text: str, share: float, draw: random.Random) -> str:
    return " ".join("changed%d" % draw.randrange(10**6) if draw.random() < share else w for w in text.split(" "))


def near_copies() -> dict:
    draw = random.Random(3)
    texts = [good_text(k) for k in range(20)]
    for k in range(20):
        texts += [changed(texts[k], share, draw) for share in (0.005, 0.01, 0.02, 0.03, 0.05)]
    texts += [texts[0].upper(), "a b c", "A  b c", "a b d", "", None, "  "]
    return dict(enumerate(texts))


def test_jaccard_all_pairs(spark):
    texts = near_copies()
    want = all_pairs(texts)
    assert 20 < len(set(want.values())) < len(texts) - 30
    docs = spark.createDataFrame([(k, t, "en", "s", 0) for k, t in texts.items()], DOCS)
    for cell_bytes in (jaccard.CELL_BYTES, 1500):  # 1500: every group is cut into slices
        assert {r.doc_id: r.component_id for r in jaccard.near_duplicates(docs, cell_bytes=cell_bytes).collect()} == want


def test_stage_drops_near_copies(spark, tmp_path):
    """Copies at a similarity over 0.8, few of which lie within two bits of each other's SimHash of three words."""
    texts = near_copies()
    want = all_pairs(texts)
    docs = spark.createDataFrame([(k, t, "en", "s", 0) for k, t in texts.items()], DOCS)
    left = cp.near_duplicates(spark, docs, str(tmp_path)).collect()
    assert sorted(r.doc_id for r in left) == sorted(set(want.values()))


def test_threshold_is_exact():
    import numpy as np

    base = np.arange(90, dtype=np.uint64)
    at = np.concatenate([base[:80], np.arange(1000, 1010, dtype=np.uint64)])  # 80 of 100
    below = np.concatenate([base[:79], np.arange(2000, 2011, dtype=np.uint64)])  # 79 of 101
    assert jaccard.similar([base, at]) == [(0, 1)] and jaccard.similar([base, below]) == []
