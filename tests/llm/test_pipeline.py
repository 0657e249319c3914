"""The pipeline's stages against brute-force versions, stage by stage on a small table."""

import random

import corpus_pipeline as cp

from . import brute
from .test_jaccard import all_pairs
from .test_operators import DOCS, good_text


def small(spark, folder):
    draw = random.Random(1)
    texts = [good_text(k).replace(". ", ".\n") for k in range(40)]
    texts += texts[:6] + [good_text(100 + k).upper() for k in range(5)] + ["too short", None, ""]
    leak = good_text(7777)
    texts += [good_text(500) + " " + leak + " " + good_text(501)]
    lines = "\n".join(texts[0].split("\n")[:5])
    texts += [good_text(600 + k).replace(". ", ".\n") + "\n" + lines for k in range(3)]
    rows = [(k, t, "en", f"s{draw.randrange(3)}", len(t or "")) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, DOCS).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(1, leak)], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    return {r[0]: r[1] for r in rows}, {1: leak}


def test_stages(spark, tmp_path):
    folder = str(tmp_path)
    given, items = small(spark, folder)
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    texts = given
    for k, (name, stage) in enumerate(cp.STAGES):
        out = stage(spark, docs, folder)
        out.write.parquet(f"{folder}/{k}")
        out = spark.read.parquet(f"{folder}/{k}")
        rows = out.collect()
        if name == "quality_rules":
            for r in rows:
                assert brute.base(r.text)[0] >= 20
            want = {i: t for i, t in texts.items() if t and len(t.split()) >= 20 and not t.isupper()}
        elif name == "line_dedup":
            keys = sorted(texts)
            want = {i: t for i, t in zip(keys, brute.kept_lines([(i, texts[i]) for i in keys])) if t.split()}
        elif name == "simhash_near_dedup":
            classes = all_pairs(texts)
            want = {i: t for i, t in texts.items() if classes[i] == i}
        elif name == "benchmark_decontamination":
            hits = dict(zip(texts, brute.leaks(list(texts.values()), items)))
            want = {i: t for i, t in texts.items() if not hits[i][1]}
            assert len(want) < len(texts)
        else:
            assert {r.doc_id for r in rows} == set(texts) and sum(r.n_words for r in rows) == sum(len(t.split()) for t in texts.values())
            break
        assert out.columns == docs.columns
        texts = {r.doc_id: r.text for r in rows}
        assert texts == want, name
        assert all(r.n_chars == len(r.text) for r in rows)
        docs = out


def test_run(spark, tmp_path):
    small(spark, str(tmp_path))
    assert cp.run(spark, str(tmp_path)).count() > 0 and 4 <= len(cp.STAGES) <= 5
