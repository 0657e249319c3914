"""Queries that take whole tables, against numpy on small ones."""

import numpy as np

import __spark_entry__ as entry


def cells(rows, n):
    out = np.full((n, n), np.nan)
    for r in rows:
        assert np.isnan(out[r.i, r.j])
        out[r.i, r.j] = r.x
    return out


def test_kernel_takes_every_row(spark, tmp_path):
    n = 530  # more than 100 and 500, and no power of two
    e = np.random.default_rng(5).normal(size=(n, 64)).astype(np.float32)
    spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(e)], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    want = e.astype(float) @ e.astype(float).T
    queries = entry.queries()
    assert np.abs(cells(queries["q_kernel_cells"](spark, str(tmp_path)).collect(), n) - want).max() < 1e-7
    assert np.abs(cells(queries["q_quadinv_kernel_all"](spark, str(tmp_path)).collect(), n) - np.linalg.inv(want + np.eye(n))).max() < 1e-7


def test_price_takes_every_row(spark, tmp_path):
    rows = 130 * 130 + 7  # more than 128 x 128, and no square: the order is 131
    draw = np.random.default_rng(6)
    prices = np.round(draw.random(rows) * 90000 + 900, 2)
    lines = [(k // 4, k % 4, 1, 1, float(x)) for k, x in enumerate(prices)]
    draw.shuffle(lines)
    ddl = "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_extendedprice double"
    spark.createDataFrame([(int(a), int(b), int(c), int(e), float(x)) for a, b, c, e, x in lines], ddl).write.parquet(f"{tmp_path}/lineitem.parquet")
    want = np.zeros(131 * 131)
    want[:rows] = np.round(prices * 100).astype(np.int64) % 100000 / 100000
    want = want.reshape(131, 131)
    queries = entry.queries()
    run = lambda name: cells(queries[name](spark, str(tmp_path)).collect(), 131)
    assert np.abs(run("q_price_cells_all") - want).max() < 1e-7
    assert np.abs(run("q_multiply_price_all") - want @ want).max() < 1e-5
    inverse = np.linalg.inv(want + 131 * np.eye(131))
    assert np.abs(run("q_quadinv_price_dom_all") - inverse).max() < 1e-9 and np.abs(run("q_blocklu_price_dom_all") - inverse).max() < 1e-9


def test_folded_prices_take_every_row(spark, tmp_path):
    draw = np.random.default_rng(8)
    rows = [(int(a), int(b), float(np.round(x, 2))) for a, b, x in zip(draw.integers(0, 3000, 9000), draw.integers(0, 800, 9000), draw.random(9000) * 90000)]
    rows += [(None, 5, 1.25), (7, None, 2.5), (7, 8, None)]
    ddl = "l_orderkey long, l_partkey long, l_extendedprice double"
    spark.createDataFrame(rows, ddl).write.parquet(f"{tmp_path}/lineitem.parquet")
    want = np.zeros((128, 128), np.int64)
    for a, b, x in rows:
        want[(a or 0) % 128, (b or 0) % 128] += round((x or 0) * 100)
    queries = entry.queries()
    assert np.abs(cells(queries["q_price_cells"](spark, str(tmp_path)).collect(), 128) - want % 100000 / 100000).max() < 1e-9


def test_kernel_cells_of_packs_and_nulls(spark):
    from quadinv.sources import matrices

    e = np.random.default_rng(9).normal(size=(300, 3)).round(3)  # more than a pack
    rows = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(e)] + [(300, None)], "i long, e array<double>").coalesce(1)
    found = {(r.i, r.j): r.x for r in matrices.dots(rows, 8).collect()}
    assert len(found) == 301 * 301 and all((found[k] is None) == (300 in k) for k in found)
    assert all(abs(found[i, j] - e[i] @ e[j]) < 1e-8 for i in range(300) for j in range(300))


def test_kernel_comes_in_blocks_without_a_larger_order(spark, tmp_path):
    import pytest

    from quadinv.operators.blocks import to_numpy
    from quadinv.queries import kernel_block
    from quadinv.sources import matrices

    for n in (5, 530, 2000, 8192, 8193, 10256, 51282):
        sides = -(-n // kernel_block(n))
        grid = 1 << (sides - 1).bit_length()
        assert kernel_block(n) <= 2048 and grid * kernel_block(n) < n + grid  # blocks of 1024 made 16384 of 10256
    e = np.random.default_rng(12).normal(size=(21, 3)).astype(np.float32)
    rows = [(100 - 3 * k, v.tolist()) for k, v in enumerate(e)]
    ddl = "vec_id long, embedding array<float>"
    spark.createDataFrame(rows, ddl).write.parquet(f"{tmp_path}/a/embeddings.parquet")
    x = e[::-1].astype(float)  # in the order of vec_id
    a = matrices.kernel(spark, f"{tmp_path}/a", 21, kernel_block(21))
    assert a.meta.symmetric and a.meta.grid_rows == 4 and np.abs(to_numpy(a) - x @ x.T - np.eye(21)).max() < 1e-12
    spark.createDataFrame(rows + [(7, None)], ddl).write.parquet(f"{tmp_path}/b/embeddings.parquet")
    with pytest.raises(Exception, match="an embedding is null"):
        a = matrices.kernel(spark, f"{tmp_path}/b", 22, kernel_block(22))
        to_numpy(a)


def test_suppliers_are_inverted_part_by_part(spark, tmp_path, monkeypatch):
    from quadinv.operators import parts

    # Ten suppliers: a chain of six, a pair, two alone; keys not in the order of parts.
    groups = [[3, 14], [14, 7], [7, 21, 30], [30, 2], [5, 9]]
    keys = [2, 3, 5, 7, 9, 14, 21, 30, 40, 50]
    lines = [(k, v) for k, g in enumerate(groups) for v in g] + [(0, 3), (9, 40), (None, 40), (None, 50), (8, None)]
    spark.createDataFrame(lines, "l_orderkey long, l_suppkey long").write.parquet(f"{tmp_path}/lineitem.parquet")
    spark.createDataFrame([(k,) for k in keys], "s_suppkey long").write.parquet(f"{tmp_path}/supplier.parquet")
    want = np.eye(10)
    for g in groups:
        for a in g:
            for b in g:
                if a != b:
                    want[keys.index(a), keys.index(b)] -= 1
                    want[keys.index(a), keys.index(a)] += 1
    want = np.linalg.inv(want)
    run = entry.queries()["q_quadinv_supplier100"]
    ran = []
    monkeypatch.setattr(parts, "quad_inverse", lambda a, f=parts.quad_inverse: ran.append(a.meta.logical_rows) or f(a))
    assert np.abs(cells(run(spark, str(tmp_path)).collect(), 10) - want).max() < 1e-8
    assert ran == []  # no inverse of the whole order
    monkeypatch.setattr(parts, "LOCAL_ORDER", 4)
    assert np.abs(cells(run(spark, str(tmp_path)).collect(), 10) - want).max() < 1e-8
    assert ran == [6]


def test_every_brand_counts(spark, tmp_path):
    draw = np.random.default_rng(14)
    brands, types = [f"Brand#{k:03d}" for k in range(40)], list("abc")  # more than 25
    counts = draw.integers(1, 4, (40, 3))
    rows = [(b, t) for b, c in zip(brands, counts) for t, k in zip(types, c) for _ in range(k)]
    spark.createDataFrame(rows, "p_brand string, p_type string").write.parquet(f"{tmp_path}/part.parquet")
    want = np.linalg.inv(counts @ counts.T + 25.0 * np.eye(40))
    assert np.abs(cells(entry.queries()["q_quadinv_brand25"](spark, str(tmp_path)).collect(), 40) - want).max() < 1e-8


def test_zeros_between_parts_take_little_disk(spark, tmp_path):
    from quadinv.operators import parts

    n = 3000  # in three parts, rows not numbered in their order
    known = spark.range(n).selectExpr("id as pos", f"id * 7 % {n} as v", "id div 1000 * 1000 as start", "id div 1000 * 1000 + 1000 as stop")
    zeros = parts._between(known.repartition(1).sortWithinPartitions("pos"), n)
    zeros.write.parquet(f"{tmp_path}/out")
    found = spark.read.parquet(f"{tmp_path}/out").toPandas()
    part = np.empty(n, int)
    part[np.arange(n) * 7 % n] = np.arange(n) // 1000
    away = np.zeros((n, n), int)
    np.add.at(away, (found.i, found.j), 1)
    assert (found.x == 0).all() and (away == (part[:, None] != part[None])).all()
    assert sum(f.stat().st_size for f in (tmp_path / "out").glob("*.parquet")) < 0.3 * len(found)  # bytes a cell; row after row takes 1.5


def test_symmetric_parts_from_half_of_their_cells(spark):
    from quadinv.operators import parts

    a = np.random.default_rng(15).random((5, 5))
    a = a + a.T + 10 * np.eye(5)
    given = [(i, j, float(a[i, j])) for i in range(5) for j in range(5)] + [(5, 5, 2.0)]
    inside, between = parts.inverse_by_parts(spark.createDataFrame(given, "i long, j long, x double"), 6, 4, symmetric=True)
    want = np.zeros((6, 6))
    want[:5, :5], want[5, 5] = np.linalg.inv(a), 0.5
    assert np.abs(cells(inside.unionByName(between).collect(), 6) - want).max() < 1e-12
