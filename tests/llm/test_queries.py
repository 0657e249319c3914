"""The registered queries as a whole: folds, inputs that must not matter, columns and their types."""

import random
import zlib

import pytest

from quadinv.llm.registry import QUERIES

from .test_operators import DOCS, good_text

CLASSIFIERS = {"op2_language_id": (4, 2), "op3_quality_trees": (4, 2), "op7_toxicity": (5, 0)}
COLUMNS = {
    "op1_html_extract": "page_id bigint, url string, text string, n_chars bigint",
    "op2_language_id": "doc_id bigint, held_out boolean, lang_pred string, score double",
    "op3_quality_trees": "doc_id bigint, held_out boolean, score double, predicted int",
    "op5_quality_rules": "doc_id bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean",
    "op7_toxicity": "doc_id bigint, held_out boolean, score double, predicted int",
    "op8_decontaminate": "doc_id bigint, n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean",
    "op9_simhash_bktree": "doc_id bigint, fingerprint string, component_id bigint",
    "op10_substring_dedup": "doc_id bigint, n_words bigint, n_removed bigint, kept_sha256 string",
}


def fold(key, modulus, remainder):
    return zlib.crc32(str(key).encode()) % modulus == remainder


def rows():
    """(doc_id, text, lang, source, quality, toxic)."""
    draw = random.Random(6)
    out = []
    for k in range(240):
        text, toxic, good = good_text(k), int(k % 4 == 0), int(k % 3 > 0)
        words = text.split(" ")
        if toxic:
            words[draw.randrange(len(words))] = "stupidfool"
        if not good:
            words = [w + " ###" for w in words]
        out.append((k, " ".join(words) + (" für und auß" * 9 if k % 2 else " the and of" * 9), ("yy", "xx")[k % 2 == 0], f"s{k % 3}", good, toxic))
    return out


def written(spark, folder, given):
    spark.createDataFrame([(k, t, l, s, len(t)) for k, t, l, s, _, _ in given], DOCS).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(k, q, x) for k, _, _, _, q, x in given], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return str(folder)


@pytest.mark.parametrize("name", CLASSIFIERS)
def test_held_out_rows_teach_nothing(spark, tmp_path, name):
    """held_out is the fold of the contract; labels, languages and sources of its rows don't matter, nor do anybody's sources."""
    modulus, remainder = CLASSIFIERS[name]
    given = rows()
    other = [(k, t, "zz" if fold(k, modulus, remainder) else l, "changed", 1 - q if fold(k, modulus, remainder) else q, 1 - x if fold(k, modulus, remainder) else x) for k, t, l, s, q, x in given]
    one, two = ({r.doc_id: r for r in QUERIES[name](spark, written(spark, tmp_path / part, data)).collect()} for part, data in (("a", given), ("b", other)))
    assert {k: r.held_out for k, r in one.items()} == {k: fold(k, modulus, remainder) for k, *_ in given}
    assert one == two
    truth = {r[0]: {"op2_language_id": r[2], "op3_quality_trees": r[4], "op7_toxicity": r[5]}[name] for r in given}
    told = [(r.lang_pred if name.startswith("op2") else r.predicted) == truth[k] for k, r in one.items() if r.held_out]
    assert sum(told) >= 0.9 * len(told)


def test_columns(spark, tmp_path):
    folder = written(spark, tmp_path, rows()[:40])
    spark.createDataFrame([(1, good_text(3))], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    spark.createDataFrame([(1, "u", "<p>x</p>")], "page_id long, url string, html string").write.parquet(f"{folder}/pages.parquet")
    for name, want in COLUMNS.items():
        found = QUERIES[name](spark, folder)
        assert ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in found.schema).startswith(want), name


def test_very_long_texts(spark, tmp_path):
    """Texts of a megabyte go through the operators on shingles and windows whole: a change at the end is seen."""
    from quadinv.llm import simhash, substring_dedup

    long = " ".join(f"w{k}" for k in range(150_000))
    docs = spark.createDataFrame([(1, long), (2, long), (3, long + " end"), (4, " ".join(reversed(long.split(" "))))], "doc_id long, text string")
    found = {r.doc_id: r.component_id for r in simhash.near_duplicates(docs).collect()}
    assert found[1] == found[2] == found[3] == 1 and found[4] == 4
    left = {r.doc_id: (r.n_words, r.n_removed) for r in substring_dedup.deduplicated(docs).collect()}
    assert left == {1: (150_000, 150_000), 2: (150_000, 150_000), 3: (150_001, 150_000), 4: (150_000, 0)}
