"""Candidates of near copies by SimHash beside min-hash."""

from quadinv.llm import jaccard

from .test_operators import good_text


def test_trees_link_what_min_hash_is_not_asked_for(spark, monkeypatch):
    base = " ".join(good_text(k) for k in range(30)).split()
    near = base[:-1] + ["otherwise"]
    texts = {1: " ".join(base), 2: " ".join(near), 3: good_text(900), 4: " ".join(base).upper()}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    monkeypatch.setattr(jaccard, "ties", lambda nodes: spark.createDataFrame([], "a long, b long"))
    found = {r.doc_id: r.component_id for r in jaccard.near_duplicates(docs).collect()}
    assert found == {1: 1, 2: 1, 3: 3, 4: 1}
