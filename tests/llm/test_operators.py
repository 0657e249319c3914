"""The ten operators against brute force, and their answers for nulls, empty and long texts, ties, repeats and odd columns."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from quadinv.llm import decontaminate, html_extract, langid, line_dedup, packing, quality_rules, quality_trees, simhash, substring_dedup, toxicity
from quadinv.llm.common import covered, rolling
from quadinv.llm.components import components
from quadinv.llm.html_training import labelled_pages

from . import brute

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def draw_texts(n, words, seed, vocabulary="a b c d e F. g Ü".split()):
    draw = random.Random(seed)
    return [" ".join(draw.choice(vocabulary) for _ in range(draw.randint(0, words))) for _ in range(n)]


def frame(spark, texts, parts=3):
    return spark.createDataFrame([(k, t, "en", f"s{k % 2}", len(t or "")) for k, t in enumerate(texts)], DOCS).repartition(parts)


ODD = [None, "", " \n\t", "x", "Ü", "word " * 30000, "a b c\n" * 10, "a b c\n" * 10, "\x00\x1f\x85 q", "no break space"]


# Line dedup


def test_line_dedup_brute_force(spark):
    texts = ["\n".join(random.Random(k).choice("abc") for _ in range(random.Random(k).randint(0, 12))) for k in range(60)] + ["a\n \nb\n\nc", "x\na\nb\nc\nx", "a\n\n\nb\nc\na\nb\nc"]
    for hot in (line_dedup.HOT, 1):  # 1: every repeated window is hot
        got = {r.doc_id: r.text for r in line_dedup.deduplicated(frame(spark, texts), hot=hot).collect()}
        assert [got[k] for k in range(len(texts))] == brute.kept_lines(list(enumerate(texts)))


def test_line_dedup_equal_rows(spark):
    """Of equal rows one is the first; rows of one id and other texts are their own. The SQL says the same."""
    import duckdb

    rows = [(1, "a\nb\nc\nd"), (1, "a\nb\nc\nd"), (1, "a\nb\nc\nd"), (1, "x\na\nb\nc"), (2, "a\nb"), (2, "a\nb"), (None, "q\nr\ns"), (None, "q\nr\ns"), (None, None), (3, "q\nr\n \ns\nt")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    import hashlib

    want = sorted((r.doc_id or 0, r.n_removed) for r in docs.transform(lambda d: line_dedup.deduplicated(d)).selectExpr("doc_id", "removed_lines as n_removed").collect())
    assert sorted(n for i, n in want if i == 1)[-2:] == [4, 4] and [n for i, n in want if i == 0] == [0, 0, 3] and want[-1] == (3, 3)
    pandas = docs.toPandas().astype({"doc_id": "Int64"})
    con = duckdb.connect()
    con.register("documents", pandas)
    sql = sorted((i or 0, n, h) for i, n, h in con.execute(line_dedup.OP4_SQL).fetchall())
    got = sorted((r.doc_id or 0, r.removed_lines, hashlib.sha256((r.text or "").encode()).hexdigest()) for r in line_dedup.deduplicated(docs).collect())
    assert got == sql


def test_line_dedup_odd_texts(spark):
    got = {r.doc_id: r.text for r in line_dedup.deduplicated(frame(spark, ODD)).collect()}
    assert [got[k] for k in range(len(ODD))] == brute.kept_lines(list(enumerate(ODD)))
    assert line_dedup.deduplicated(frame(spark, [])).count() == 0
    twice = spark.createDataFrame([(1, "a\nb\nc", 5), (1, "a\nb\nc", 6), (None, "a\nb\nc", 7)], "doc_id long, text string, lines int")
    assert {(r.doc_id, r.lines): r.text for r in line_dedup.deduplicated(twice).collect()} == {(None, 7): "a\nb\nc", (1, 5): "", (1, 6): ""}


def test_line_dedup_is_native(spark):
    plan = line_dedup.deduplicated(frame(spark, ["a\nb\nc"])).select("text")._jdf.queryExecution().executedPlan().toString()
    assert not any(word in plan for word in ("Python", "Arrow", "Pandas"))


# Quality rules


def test_base_measures(spark):
    texts = ODD[:5] + ODD[6:] + draw_texts(30, 60, 5) + ["# * a\n# * a\n\n<b>|x&y|"] + ["a b c d e f g h i " * 3]
    got = {r.doc_id: r for r in quality_rules.judged(frame(spark, texts), keep=["doc_id"]).collect()}
    for k, text in enumerate(texts):
        r = got[k]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute.base(text), text
        assert r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words) and not (r.base_failed and r.kept)


def good_text(seed):
    draw = random.Random(seed)
    return ". ".join(" ".join("".join(draw.choice("abcdefghij") for _ in range(draw.randint(2, 8))) for _ in range(9)).capitalize() for _ in range(10)) + "."


def test_rules_keep_good_and_drop_bad(spark):
    good = [good_text(k) for k in range(80)]
    bad = [good_text(200 + k).replace(" ", "### ") for k in range(8)] + [good_text(300 + k).upper() for k in range(8)]
    docs = frame(spark, good + bad).withColumn("kept", __import__("pyspark.sql.functions", fromlist=["lit"]).lit("mine"))
    left = quality_rules.accepted(docs).collect()
    assert sorted(r.doc_id for r in left) == list(range(80)) and {r.kept for r in left} == {"mine"} and left[0].asDict().keys() == set(docs.columns)
    assert quality_rules.accepted(frame(spark, [])).count() == 0


def test_accuracies_are_estimated():
    draw = np.random.default_rng(1)
    good = draw.random(4000) < 0.8
    votes = np.full((4000, len(quality_rules.RULES)), 2)
    for r, accuracy in ((5, 0.95), (9, 0.9), (10, 0.85)):
        votes[:, r] = np.where(draw.random(4000) < accuracy, good, ~good)
    for r in (0, 1, 2):
        votes[:, r] = np.where(~good & (draw.random(4000) < 0.7), 0, 2)
    codes = votes @ (3 ** np.arange(votes.shape[1])[::-1])
    patterns, counts = np.unique(codes, return_counts=True)
    posterior, told, share = quality_rules.posteriors(patterns, counts)
    assert abs(share - 0.8) < 0.05 and told[1, 5, 1] > told[1, 10, 1]
    assert ((posterior[np.searchsorted(patterns, codes)] > 0.5) == good).mean() > 0.95
    want = brute.latent_class(votes.tolist(), quality_rules.guesses().tolist(), [[(quality_rules.EITHER_WEIGHT if g else quality_rules.SYMPTOM_WEIGHT) if c else quality_rules.BAD_WEIGHT for (_, g), _ in quality_rules.GUESSES] for c in (0, 1)], quality_rules.SHARE_GUESS, quality_rules.SHARE_WEIGHT, 15)
    short, _, _ = quality_rules.posteriors(patterns, counts, turns=16)
    assert np.allclose(short[np.searchsorted(patterns, codes)], want, atol=1e-6)
    more, _, _ = quality_rules.posteriors(patterns, counts * 1000)
    assert np.allclose(more, posterior)  # the verdict doesn't depend on the size


def test_a_weak_symptom_is_outvoted():
    """Texts that repeat some lines and are fine by all other rules stay; texts with a telling symptom go, whatever the other votes."""
    rules = len(quality_rules.RULES)
    fine = [2] * 5 + [1, 2, 2, 2, 1, 1]
    code = lambda **off: sum(v * 3 ** (rules - 1 - r) for r, v in enumerate([off.get(f"r{r}", v) for r, v in enumerate(fine)]))
    patterns = np.array([code(), code(r4=0), code(r0=0), code(r0=0, r8=0), code(r2=0)])
    posterior, _, _ = quality_rules.posteriors(patterns, np.array([8000, 10, 300, 300, 10]))
    assert (posterior > 0.5).tolist() == [True, True, False, False, False]


# Packing


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(st.integers(1, 10), st.integers(0, 2), st.integers(0, 5)), max_size=40), st.integers(1, 3))
def test_packing_brute_force(items, per_source):
    items = sorted(items, key=lambda x: -x[0])
    sizes, sources, clusters = ([x[k] for x in items] for k in range(3))
    assert packing.packed_group(np.array(sizes, int), sources, np.array(clusters, int), 10, per_source) == brute.packed(items, 10, per_source)


def test_packing_places_every_word_once(spark):
    texts = draw_texts(300, 40, 3) + ["w " * 205, None, "", "same text", "Same  text"]
    rows = packing.packed(frame(spark, texts), capacity=50, group_docs=64, per_source=2).collect()
    fill, words = {}, {}
    for r in rows:
        words.setdefault(r.doc_id, []).append((r.first_word, r.n_words))
        if r.bin_id is None:
            assert r.n_words == 0
        else:
            fill.setdefault(r.bin_id, []).append((r.bin_offset, r.n_words, r.doc_id))
    for k, text in enumerate(texts):
        at = 0
        for first, n in sorted(words[k]):
            assert first == at
            at += n
        assert at == len((text or "").split())
    for held in fill.values():
        at = 0
        for offset, n, _ in sorted(held):
            assert offset >= at
            at = offset + n
        assert at <= 50
        assert len({" ".join((texts[d] or "").lower().split()) for *_, d in held}) == len(held)
        assert max(sum(d % 2 == s for *_, d in held) for s in (0, 1)) <= 2
    assert packing.packed(frame(spark, [])).count() == 0


# Decontamination


def test_decontamination_brute_force(spark):
    draw = random.Random(9)
    words = "ab cd ef Gh ij kl Ü9 q".split()
    items = {k: " ".join(draw.choice(words) for _ in range(draw.choice((0, 1, 3, 9, 10, 11, 25)))) for k in range(40)} | {100: None, 101: " ,.", 102: "ab, CD! ef"}
    texts = [" ".join(draw.choice(words) for _ in range(draw.randint(0, 80))) + ", " + (items[draw.randrange(40)] or "") for _ in range(60)] + ODD
    bench = spark.createDataFrame([(k, t) for k, t in items.items()], "item_id long, text string")
    want = brute.leaks(texts, items)
    for limit, built in ((1 << 20, 1 << 28), (1000, 1 << 28), (1 << 20, 60_000)):
        got = {r.doc_id: (r.n_words, list(r.hit_words), list(r.hit_items)) for r in decontaminate.search(frame(spark, texts), bench, keep=["doc_id"], pattern_bytes=limit, built_bytes=built).collect()}
        assert [got[k] for k in range(len(texts))] == want
    assert decontaminate.search(frame(spark, []), bench).count() == 0
    none = decontaminate.decontaminated(frame(spark, texts), bench.limit(0))
    assert none.count() == len(texts) and none.columns == frame(spark, []).columns


# SimHash


def test_simhash_brute_force(spark):
    draw = random.Random(4)
    base = [draw.choice("abcdefghijklmnop") * 3 + str(k) for k in range(120)]
    texts = []
    for k in range(90):
        words = base[:]
        for _ in range(draw.randint(0, 3)):
            words[draw.randrange(120)] = f"z{draw.randrange(9)}"
        texts.append(" ".join(words))
    texts += [None, "", "one", "one two", "ONE two", *texts[:3]]
    want = brute.simhash(dict(enumerate(texts)))
    for shard_rows in (4, 1024):
        found = simhash.near_duplicates(frame(spark, texts), shard_rows=shard_rows).collect()
        assert {r.doc_id: (f"{r.fp % 2**64:016x}", r.component_id) for r in found} == want
    left = [r.doc_id for r in simhash.one_of_each(frame(spark, texts)).collect()]
    assert sorted(left) == sorted({c for _, c in want.values()})


def test_simhash_odd_rows(spark):
    docs = spark.createDataFrame([(1, "a b c", 1), (1, "a b c", 1), (None, "a b c", 2), (None, "d e f g", 3), (None, "d e f g", 4), (None, "h i j k l", 5), (1, "m n o p q r", 6)], "doc_id long, text string, fp int")
    left = simhash.one_of_each(docs).collect()
    assert sorted((r.doc_id or 0, r.text) for r in left) == [(0, "d e f g"), (0, "h i j k l"), (1, "a b c"), (1, "m n o p q r")] and left[0].asDict().keys() == {"doc_id", "text", "fp"}
    assert simhash.near_duplicates(frame(spark, [])).count() == 0


@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1), min_size=1, max_size=40, unique=True), st.integers(0, 5))
def test_bk_forest(values, radius):
    values = sorted(set(values) | {v ^ 1 for v in values[:5]} | {v ^ 6 for v in values[:3]})
    rows = np.array(values, np.uint64)
    group = np.arange(len(rows)) % 2
    order = np.argsort(group, kind="stable")
    rows, group = rows[order], group[order]
    q, n = simhash.Forest(rows, group).within(rows, group, radius)
    want = {(i, j) for i in range(len(rows)) for j in range(len(rows)) if group[i] == group[j] and bin(int(rows[i]) ^ int(rows[j])).count("1") <= radius}
    assert set(zip(q.tolist(), n.tolist())) == want and len(q) == len(want)


@pytest.mark.parametrize("radius", [0, 1, 3, 6])
def test_links_of_any_radius(spark, radius):
    draw = random.Random(radius)
    prints = [draw.getrandbits(64) for _ in range(40)]
    for k in range(60):
        prints.append(prints[draw.randrange(len(prints))] ^ sum(1 << b for b in draw.sample(range(64), draw.randint(0, radius + 1))))
    prints = sorted(set(prints))
    signed = [p - 2**64 if p >= 2**63 else p for p in prints]
    got = {r.node: r.root for r in components(simhash.links(spark.createDataFrame([(p,) for p in signed], "fp long"), radius, shard_rows=16)).collect()}
    root = {p: p for p in signed}
    for _ in prints:
        for a, x in zip(signed, prints):
            for b, y in zip(signed, prints):
                if bin(x ^ y).count("1") <= radius:
                    root[a] = min(root[a], root[b])
    assert {p: got.get(p, p) for p in signed} == root


def test_components(spark):
    edges = [(k, k + 1) for k in range(30)] + [(100, 100), (200, 300), (300, 250)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{k: 0 for k in range(31)}, 200: 200, 250: 200, 300: 200}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


# Substring dedup


def passages():
    draw = random.Random(2)
    shared = [" ".join(f"s{draw.randrange(50)}" for _ in range(12)) for _ in range(4)]
    texts = [" ".join(f"u{draw.randrange(9)}" for _ in range(draw.randint(0, 30))) + " " + draw.choice(shared + [""]) + " " + " ".join(f"v{draw.randrange(9)}" for _ in range(draw.randint(0, 30))) for _ in range(60)]
    return texts + [None, "", "a b c", "q " * 40, texts[0], texts[1], "long words here " * 9000]


@pytest.mark.parametrize("text_bytes, most_bits, broadcast_bytes", [(1 << 20, 22, 1 << 25), (1 << 9, 6, 1 << 25), (1 << 14, 6, 1 << 25), (1 << 14, 6, 0), (1 << 9, 22, 0)])
def test_substring_dedup_brute_force(spark, text_bytes, most_bits, broadcast_bytes):
    """One shard or many, loaded lightly or to the full, sent to the texts or asked by them: the same result."""
    texts = passages()
    shape = substring_dedup.Shape(text_bytes, most_bits, least_bits=6)
    got = {r.doc_id: r for r in substring_dedup.deduplicated(frame(spark, texts), window=8, gram=4, shape=shape, broadcast_bytes=broadcast_bytes).collect()}
    for k, left in enumerate(brute.repeats(texts, 8)):
        assert got[k].kept_text == " ".join(left) and got[k].n_removed == got[k].n_words - len(left)


def test_sketch_passes_few_at_any_size():
    """The share of single grams let through depends on the load alone, not on the number of shards, and every repeated one passes."""
    draw = np.random.default_rng(0)
    for grams, most_bits in ((4_000, 22), (4_000, 12), (120_000, 12)):
        keys = draw.integers(0, 2**63, grams, dtype=np.uint64)
        again = keys[: grams // 10]
        shape = substring_dedup.Shape(80 * grams, most_bits, least_bits=8)
        assert shape.bytes >= grams and (most_bits == 22) == (shape.shard_bits == 0)
        all_ = np.concatenate((keys, again))
        at = shape.counters(all_) + shape.shard(all_) * 8 * shape.shard_bytes
        many = np.bincount(at.ravel(), minlength=8 * shape.bytes) > 1
        found = substring_dedup.Sketch(shape, np.packbits(many)).repeated(keys)
        assert found[: grams // 10].all() and found[grams // 10 :].mean() < 0.025
    for load, share in ((0.1, 1e-3), (0.4, 0.03), (1.0, 0.25), (4.0, 1.0)):  # of counters: saturation lets all through
        assert (1 - np.exp(-load)) ** substring_dedup.DEPTH < share + 1e-12


def test_substring_dedup_odd_rows(spark):
    lone = [" ".join(f"{c}{k}" for k in range(50)) for c in "abc"]
    docs = spark.createDataFrame([(1, "x", 1), (1, "y " * 50, 2), (None, None, 3), (None, lone[0], 4), (None, lone[1], 5), (1, lone[2], 6)], "doc_id long, text string, singles int")
    for shape, limit in ((None, 1 << 25), (substring_dedup.Shape(64, 3, 3), 1 << 25), (substring_dedup.Shape(64, 3, 3), 0)):
        rows = substring_dedup.deduplicated(docs, shape=shape, broadcast_bytes=limit).collect()
        assert sorted((r.singles, r.n_removed) for r in rows) == [(1, 0), (2, 50), (3, 0), (4, 0), (5, 0), (6, 0)]
    assert substring_dedup.deduplicated(frame(spark, [])).count() == 0
    gaps = np.array([0, 1, 5, 200, 40000, 3_000_000, 2**31], np.int64)
    assert (substring_dedup._ungapped(substring_dedup._gaps(gaps)) == gaps).all() and len(substring_dedup._ungapped(b"")) == 0


def test_rolling_and_covered():
    h = np.arange(1, 40, dtype=np.uint64)
    for width in (1, 2, 5, 16):
        want = [sum(int(h[i + j]) * pow(7, j, 2**64) for j in range(width)) % 2**64 for i in range(len(h) - width + 1)]
        from quadinv.llm.common import mix

        assert (rolling(h, width, 7) == mix(np.array(want, np.uint64))).all()
    assert covered(np.array([1, 2, 6]), 3, 8).tolist() == [False, True, True, True, True, False, True, True]


# HTML


def test_html_layouts():
    model = html_extract.fit(400, seed=1)
    wrong = total = 0
    for page in labelled_pages(80, seed=77):
        dom = html_extract.Dom(page, labelled=True)
        labels, found = dom.labels(), model.marginals(dom)
        nodes = {n for n, pieces in dom.text if "".join(pieces).strip()}
        wrong += sum((found[n] > 0.5) != bool(labels[n]) for n in nodes)
        total += len(nodes)
    assert wrong / total < 0.03


def test_html_messages_are_exact():
    """Marginals by messages equal those by summing over all labellings."""
    import itertools
    import math

    model = html_extract.fit(50)
    dom = html_extract.Dom("<body><nav><a>x</a></nav><div class=post><p>some text</p><p>more</p></div></body>")
    own = [[sum(model.own.get(f, (0, 0))[y] for f in names) for y in (0, 1)] for names in dom.features()]
    weight = [0.0] * len(dom.tag)
    total = 0.0
    for y in itertools.product((0, 1), repeat=len(dom.tag)):
        p = math.exp(model.root[y[0]] + sum(own[k][y[k]] for k in range(len(y))) + sum(model.pair[y[dom.parent[k]]][y[k]] for k in range(1, len(y))))
        total += p
        for k, v in enumerate(y):
            weight[k] += p * v
    assert np.allclose(model.marginals(dom), [w / total for w in weight])


def test_html_parsing():
    dom = html_extract.Dom("<p>a<b>b</b>c<br>d &amp; &eacute;<p>e<script>var x='</p>'</script>f</div> g <!-- no --><ul><li>1<li>2</ul>")
    assert [" ".join("".join(p).split()) for _, p in dom.text] == ["abc d & é", "ef g", "1", "2"]
    assert html_extract.Dom("<p title='a>b'>x").text[0][1] == ["x"] and html_extract.Dom("a < b").text


def test_html_odd_pages(spark):
    pages = [(1, "u", None, "mine"), (2, None, "", "mine"), (3, "u", "<article><p>Plain text of an article here.</p></article>", None), (None, "u", "<<<>><p", ""), (4, "u", "<div>" * 3000 + "deep", "")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string, text string")
    got = {r.page_id: r for r in html_extract.extracted(df).collect()}
    assert got[1].text == "" == got[2].text and got[3].text == "Plain text of an article here." and got[3].n_chars == 30
    assert html_extract.extracted(df.limit(0)).count() == 0


# Models


def language(spark, n):
    draw = random.Random(5)
    kinds = {"xx": "the and ing of".split(), "yy": "für ich und auß".split()}
    rows = [(k, " ".join(draw.choice(kinds[l]) + draw.choice(kinds[l]) for _ in range(60)), l) for k in range(n) for l in [("xx", "yy")[k % 2]]]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string")


def test_language(spark):
    docs = language(spark, 60)
    model = langid.fit(docs)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "12 34 !?"), (4, "fürich " * 5000)], "doc_id long, text string")
    got = {r.doc_id: (r.lang_pred, r.score) for r in langid.predicted(odd, model).collect()}
    marks = spark.createDataFrame([(1, "\u00bd \u00b2 \u2460 \u2167 \u0663 _"), (2, "\u02b0"), (3, "\u01c5 1")], "doc_id long, text string")
    assert {r.doc_id: r.lang_pred == "und" for r in langid.predicted(marks, model).collect()} == {1: True, 2: False, 3: False}
    assert got[1] == got[2] == got[3] == ("und", 0.0) and got[4][0] == "yy" and 0.5 < got[4][1] <= 1
    good = langid.predicted(docs, model).filter("lang = lang_pred").count()
    assert good >= 58
    assert {r.lang_pred for r in langid.predicted(odd, langid.fit(docs.limit(0))).collect()} == {"und"}


def test_language_gradients():
    """Analytic gradients equal differences."""
    net = langid.Network(["a", "b", "c"])
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    draw = np.random.default_rng(0)
    data, target = draw.integers(0, 256, (4, 24)).astype(np.uint8), np.array([0, 1, 2, 1])

    def loss():
        pooled = []
        for w in langid.WIDTHS:
            x = net.p["e"][data]
            pooled.append(sum(x[:, j : 24 - w + 1 + j] @ net.p[f"w{w}"][j] for j in range(w)).max(axis=1) + net.p[f"b{w}"])
        p = langid._softmax(np.maximum(np.concatenate(pooled, axis=1), 0) @ net.p["v"] + net.p["c"])
        return -np.log(p[np.arange(4), target]).mean()

    for name, g in net._gradients(data, target).items():
        flat, at = net.p[name].reshape(-1), int(np.abs(g).argmax())
        flat[at] += 1e-5
        up = loss()
        flat[at] -= 2e-5
        down = loss()
        flat[at] += 1e-5
        assert abs((up - down) / 2e-5 - g.reshape(-1)[at]) < 1e-6, name


def test_trees():
    draw = np.random.default_rng(0)
    x = draw.random((3000, 4))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.3)).astype(float)
    model = quality_trees.grow(x[:2000], y[:2000])
    assert ((model.scores(x[2000:]) > 0.5) == y[2000:]).mean() > 0.95
    one = model.scores(x[:50])
    for k in range(50):  # node by node
        total = model.base
        for f, c, leaf in zip(model.feature, model.cut, model.leaf):
            node, first = 0, 0
            for level in range(quality_trees.DEPTH):
                node, first = 2 * node + int(x[k, f[first + node]] > c[first + node]), first + (1 << level)
            total += leaf[node]
        assert abs(1 / (1 + np.exp(-total)) - one[k]) < 1e-12
    assert len(quality_trees.grow(np.zeros((0, 3)), np.zeros(0)).leaf) == 0
    assert abs(quality_trees.grow(np.zeros((9, 3)), np.ones(9)).scores(np.zeros((1, 3)))[0] - 0.95) < 1e-9


def test_classifiers_on_odd_rows(spark):
    docs = frame(spark, ODD + [good_text(k) for k in range(30)])
    labels = spark.createDataFrame([(k, int(k % 2), None) for k in range(40)] + [(None, 1, 1), (3, None, 0)], "doc_id long, quality int, toxic int")
    trees = quality_trees.scored(docs, quality_trees.fit(docs, labels)).collect()
    machine = toxicity.scored(docs, toxicity.fit(docs, labels)).collect()
    for got in (trees, machine):
        assert len(got) == 40 and all(0 <= r.score <= 1 for r in got)
    assert quality_trees.scored(docs.limit(0), quality_trees.fit(docs.limit(0), labels)).count() == 0


def test_pairs_of_terms_are_learned():
    """Neither term alone is toxic, both together are: additive weights can't say so."""
    draw = np.random.default_rng(0)
    a, b = draw.random(1200) < 0.5, draw.random(1200) < 0.5
    y = (a & b).astype(float)
    noise = draw.integers(100, 160, (1200, 4))
    terms = [np.unique(np.concatenate(([1] * int(a[k]), [2] * int(b[k]), noise[k])).astype(np.int64)) for k in range(1200)]
    model = toxicity.learn(terms[:900], y[:900], epochs=40)
    assert ((model.scores(terms[900:]) > 0.5) == y[900:]).mean() > 0.97


# All queries over a small table, without data where the operator only reads documents.


def test_queries_take_empty_tables(spark, tmp_path):
    from quadinv.llm.registry import QUERIES

    empty = {"documents": DOCS, "labels": "doc_id long, quality int, toxic int", "benchmark": "item_id long, text string", "pages": "page_id long, url string, html string"}
    for name, ddl in empty.items():
        spark.createDataFrame([], ddl).write.parquet(str(tmp_path / f"{name}.parquet"))
    for name, q in QUERIES.items():
        assert q(spark, str(tmp_path)).count() == 0, name
