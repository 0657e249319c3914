"""Components finished in one task or in turns."""

import random

from quadinv.llm.components import components


def test_one_task_and_turns_agree(spark):
    draw = random.Random(4)
    pairs = [(draw.randrange(300), draw.randrange(300)) for _ in range(220)] + [(k, k + 1) for k in range(1000, 1040)] + [(7, 7)]
    edges = spark.createDataFrame(pairs, "a long, b long")
    root = {n: n for p in pairs for n in p}
    for _ in range(400):
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    want = {n: r for n, r in root.items() if any(n in p and p[0] != p[1] for p in pairs)}
    for bound in (0, 10**6):
        rows = components(edges, local_edges=bound).collect()
        assert len(rows) == len(want) and {r.node: r.root for r in rows} == want
    assert components(edges.filter("a < 0")).count() == 0


def test_few_jobs_for_a_small_graph(spark):
    jobs = lambda: spark.sparkContext._jsc.sc().dagScheduler().numTotalJobs()
    edges = spark.createDataFrame([(k, k + 1) for k in range(60)], "a long, b long")
    before = jobs()
    assert {r.root for r in components(edges).collect()} == {0}
    assert jobs() - before <= 8
