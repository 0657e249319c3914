"""Workload matrices: cells (i, j, x) from the tables, and generated ones with known inverses."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators.blocks import BLOCK_DDL, BlockFrame, generated, meta_for, record
from ..plans.lineage import materialize


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows of a pack of vectors; two packs give a batch of PACK_ROWS ** 2 dot products.
PACK_ROWS = 256
PRICE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]


def numbered(df: DataFrame, keys: list[str], name: str = "k") -> DataFrame:
    """df with name, the row's number from 0 in the order of keys, without gathering the rows in one task.

    Rows are range-partitioned and numbered inside of their partition; the partitions' sizes, one row each, give the offsets.
    The partitions are materialised, for both passes must see the same ones.
    """
    dealt = materialize(df.repartitionByRange(*keys).withColumn("part_", F.spark_partition_id()))
    inner = dealt.withColumn("at_", F.row_number().over(Window.partitionBy("part_").orderBy(*keys)) - 1)
    sizes = dealt.groupBy("part_").count()
    upto = F.sum("count").over(Window.orderBy("part_").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select("part_", F.coalesce(upto, F.lit(0)).alias("off_"))
    return inner.join(F.broadcast(offsets), "part_").withColumn(name, F.col("off_") + F.col("at_")).drop("part_", "at_", "off_")


def price(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """Dense and non-symmetric: all prices folded by order and part, the cell (order mod n, part mod n) the fraction of their sum.

    Sums are of whole cents, so they don't depend on the order of rows; a null key counts as 0, a null price adds nothing, a cell
    without rows is zero.
    """
    cents = F.coalesce(F.round(F.col("l_extendedprice") * 100).cast("long"), F.lit(0).cast("long")).alias("c")
    place = lambda key: F.coalesce(F.pmod(F.col(key), F.lit(n)).cast("long"), F.lit(0).cast("long"))
    lines = table(spark, sf_dir, "lineitem").select(place("l_orderkey").alias("i"), place("l_partkey").alias("j"), cents)
    every = spark.range(n * n).select(F.floor(F.col("id") / n).alias("i"), (F.col("id") % n).alias("j"), F.lit(0).cast("long").alias("c"))
    sums = lines.unionByName(every).groupBy("i", "j").agg(F.sum("c").alias("c"))
    return sums.select("i", "j", (F.pmod(F.col("c"), F.lit(100000)) / 100000.0).alias("x"))


def price_order(rows: int) -> int:
    """Order of the smallest square that holds so many rows."""
    return math.isqrt(rows - 1) + 1 if rows else 0


def price_all(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """The fractions of all prices row by row, in the order of PRICE_KEY: the cells and the order, the least that holds all rows.

    Cells behind the last row are zero.
    """
    lines = table(spark, sf_dir, "lineitem").select(PRICE_KEY)
    count = lines.count()
    n = price_order(count)
    cents = F.round(F.col("l_extendedprice") * 100).cast("long")
    given = numbered(lines, PRICE_KEY).select("k", (F.pmod(cents, F.lit(100000)) / 100000.0).alias("x"))
    cells = given.unionByName(spark.range(count, n * n).select(F.col("id").alias("k"), F.lit(0.0).alias("x")))
    return cells.select(F.floor(F.col("k") / n).alias("i"), (F.col("k") % n).alias("j"), "x"), n


def shifted(cells: DataFrame, s: float) -> DataFrame:
    """The cells of x + s I, for cells that hold the whole diagonal."""
    return cells.select("i", "j", (F.col("x") + F.when(F.col("i") == F.col("j"), F.lit(float(s))).otherwise(0.0)).alias("x"))


def price_dom(spark: SparkSession, sf_dir: str, n: int) -> DataFrame:
    """price + n I: diagonally dominant."""
    return shifted(price(spark, sf_dir, n), n)


def gram_of(vectors: DataFrame, column: str, width: int) -> DataFrame:
    """Sum of x x' over all rows, in one pass: each task adds its rows' outer products, the sums are added by cell."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        total = np.zeros((width, width))
        for batch in batches:
            values = batch.column(0)
            rows = np.asarray(values.flatten().to_numpy(), dtype=float).reshape(-1, width)
            total += rows.T @ rows
        i, j = np.divmod(np.arange(width * width), width)
        yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j), pa.array(total.ravel())], names=["i", "j", "x"])

    return vectors.filter(F.col(column).isNotNull()).select(column).mapInArrow(run, "i long, j long, x double").groupBy("i", "j").agg(F.sum("x").alias("x"))


def gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sum of x x' over the embeddings, plus I: symmetric positive definite, 64 x 64."""
    return shifted(gram_of(table(spark, sf_dir, "embeddings"), "embedding", 64), 1.0)


def packed(rows: DataFrame) -> DataFrame:
    """(ids, flat): the rows (i, e) in packs of at most PACK_ROWS, e one behind another."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, PACK_ROWS):
                piece = batch.slice(at, PACK_ROWS)
                ids, flat = piece.column(0).to_numpy(), piece.column(1).flatten().to_numpy()
                lists = [pa.ListArray.from_arrays(pa.array(np.array([0, len(x)], np.int32)), pa.array(x)) for x in (ids, flat)]
                yield pa.RecordBatch.from_arrays(lists, names=["ids", "flat"])

    return rows.select(F.col("i").cast("long"), "e").mapInArrow(run, "ids array<long>, flat array<double>")


def dots(rows: DataFrame, digits: int | None = None) -> DataFrame:
    """(i, j, x): the dot products of all pairs of rows (i, e), any number of them, e of one width; rounded half away from zero to digits, null where an e is null.

    Packs of rows meet, small sets by broadcast and large ones as a product of partitions. Terms are added in the order of the
    elements, as by a plain sum.
    """
    import numpy as np
    import pyarrow as pa

    known, blank, x = rows.filter("e is not null"), rows.filter("e is null").select("i"), F.lit(None).cast("double").alias("x")
    empty = blank.crossJoin(rows.select(F.col("i").alias("j"))).unionByName(known.select("i").crossJoin(blank.select(F.col("i").alias("j"))))
    packs = materialize(packed(known))
    packs = packs.repartition(max(1, min(packs.count(), 4096)))

    def run(batches):
        for batch in batches:
            for ids, flat, others, other in zip(*(batch.column(c) for c in ("ids", "flat", "others", "other"))):
                ids, flat, others, other = (x.values.to_numpy() for x in (ids, flat, others, other))
                one, two = flat.reshape(len(ids), -1), np.ascontiguousarray(other.reshape(len(others), -1).T)
                sums, part = np.zeros((len(ids), len(others))), np.empty((len(ids), len(others)))
                for k in range(one.shape[1]):
                    sums += np.multiply(one[:, k, None], two[k], out=part)
                x = sums.ravel()
                if digits is not None:
                    y = x * 10.0**digits
                    whole = np.trunc(y)
                    x = (whole + np.where(np.abs(y - whole) >= 0.5, np.copysign(1.0, y), 0.0)) / 10.0**digits + 0.0
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, len(others))), pa.array(np.tile(others, len(ids))), pa.array(x)], names=["i", "j", "x"])

    pairs = packs.crossJoin(packs.select(F.col("ids").alias("others"), F.col("flat").alias("other")))
    return pairs.mapInArrow(run, "i long, j long, x double").unionByName(empty.select("i", "j", x))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, e) of all embeddings, in doubles."""
    return table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))


def kernel(spark: SparkSession, sf_dir: str, n: int, block: int) -> BlockFrame:
    """X X' + I over all n embeddings, numbered by vec_id: symmetric positive definite.

    Blocks are products of strips of `block` rows, made where they are needed; cells are never moved one by one.
    """
    import numpy as np
    import pyarrow as pa

    meta = meta_for(n, n, block, symmetric=True)
    rows = numbered(vectors(spark, sf_dir), ["vec_id"], "i").select(F.expr(f"i div {block} as bi"), F.expr(f"i % {block} as at"), "e")

    def strip(key, group):
        bi, e = key[0].as_py(), group.column("e").combine_chunks()
        here = min(block, n - bi * block)
        flat = e.flatten()
        if e.null_count or flat.null_count or group.num_rows != here or len(flat) % here or len(set(e.value_lengths().to_pylist())) > 1:
            raise ValueError("an embedding is null or of another width")
        out = np.zeros((block, len(flat) // here))
        out[group.column("at").to_numpy()] = flat.to_numpy().reshape(here, -1)
        if not np.isfinite(out).all():
            raise ValueError("a value that is not finite")
        return pa.table({"bi": pa.array([bi], pa.int64()), "e": pa.array([out.ravel()], pa.list_(pa.float64()))})

    strips = materialize(rows.groupBy("bi").applyInArrow(strip, "bi long, e array<double>"))
    strips = strips.repartition(meta.grid_rows)

    def run(batches):
        for batch in batches:
            for bi, bj, one, two in zip(batch.column("bi").to_pylist(), batch.column("bj").to_pylist(), batch.column("e"), batch.column("f")):
                # Both operands are copies of one row-major strip, so that block (i, j) is the transpose of block (j, i).
                x = one.values.to_numpy().reshape(block, -1) @ two.values.to_numpy().reshape(block, -1).T
                if bi == bj:
                    x[np.diag_indices(block)] += 1.0
                yield record([(bi, bj)], [x])

    pairs = strips.crossJoin(strips.select(F.col("bi").alias("bj"), F.col("e").alias("f")))
    return BlockFrame(pairs.mapInArrow(run, BLOCK_DDL), meta)


def flow_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, j, x) for all pairs of nations: share of the revenue of customers' nation i that suppliers' nation j takes."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long").alias("cents"))
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c_custkey"))
    buyers = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("i"))
    sellers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("j"))
    sums = lines.join(orders, "l_orderkey").join(buyers, "c_custkey").join(sellers, "l_suppkey").groupBy("i", "j").agg(F.sum("cents").alias("cents"))
    nations = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("i"))
    pairs = nations.crossJoin(nations.select(F.col("i").alias("j")))
    row = F.sum("c").over(Window.partitionBy("i"))
    full = pairs.join(sums, ["i", "j"], "left").select("i", "j", F.coalesce("cents", F.lit(0)).alias("c"))
    return full.select("i", "j", F.when(row > 0, F.col("c") / row).otherwise(0.0).alias("x"))


def damped(shares: DataFrame, factor: float = 0.9) -> DataFrame:
    """I - factor * shares."""
    return shares.select("i", "j", (F.when(F.col("i") == F.col("j"), 1.0).otherwise(0.0) - F.lit(factor) * F.col("x")).alias("x"))


def flow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return damped(flow_shares(spark, sf_dir))


def supplier_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Laplacian of the graph of suppliers, weighted by the orders that two of them share, plus I; only its cells that aren't zero."""
    numbers = materialize(numbered(table(spark, sf_dir, "supplier").select("s_suppkey"), ["s_suppkey"], "i").withColumnRenamed("s_suppkey", "l_suppkey"))
    lines = table(spark, sf_dir, "lineitem").filter("l_orderkey is not null").select("l_orderkey", "l_suppkey")
    found = lines.join(F.broadcast(numbers) if numbers.count() <= 1 << 20 else numbers, "l_suppkey")
    # Dealt by order once: the distinct pairs and their join need no further exchange. Each edge is counted one way.
    one = found.select("l_orderkey", "i").repartition("l_orderkey").distinct()
    two = one.select("l_orderkey", F.col("i").alias("j"))
    edges = materialize(one.join(two, "l_orderkey").filter("i < j").groupBy("i", "j").agg(F.count("*").cast("double").alias("w")))
    ends = edges.select("i", "w").unionByName(edges.select(F.col("j").alias("i"), "w"))
    degree = materialize(numbers.select("i").join(ends.groupBy("i").agg(F.sum("w").alias("w")), "i", "left").select("i", F.col("i").alias("j"), (F.coalesce("w", F.lit(0.0)) + 1.0).alias("x")))
    away = -F.col("w")
    return edges.select("i", "j", away.alias("x")).unionByName(edges.select(F.col("j").alias("i"), F.col("i").alias("j"), away.alias("x"))).unionByName(degree)


NORMAL = ["1.0", "l_quantity", "100 * l_discount", "100 * l_tax"]


def normal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Z'Z for Z = (1, quantity, 100 discount, 100 tax) of the lines, in one pass."""
    lines = table(spark, sf_dir, "lineitem").select(*[F.expr(e).cast("double").alias(f"z{k}") for k, e in enumerate(NORMAL)])
    sums = lines.agg(*[F.sum(F.col(f"z{i}") * F.col(f"z{j}")).alias(f"s{i}{j}") for i in range(4) for j in range(i, 4)])
    return sums.select(F.explode(F.array(*[F.struct(F.lit(i).cast("long").alias("i"), F.lit(j).cast("long").alias("j"), F.col(f"s{min(i, j)}{max(i, j)}").alias("x")) for i in range(4) for j in range(4)])).alias("c")).select("c.*")


def event_numbers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, k): the types in alphabetical order, counted from 0. One row a type."""
    types = table(spark, sf_dir, "events").filter("event_type is not null").select("event_type").distinct()
    return types.withColumn("k", (F.row_number().over(Window.orderBy("event_type")) - 1).cast("long"))


def transitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, j, x) for all pairs of event types: share of j among the successors of i, user by user."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    steps = table(spark, sf_dir, "events").select("event_type", F.lead("event_type").over(w).alias("next")).filter("next is not null and event_type is not null")
    counts = steps.groupBy("event_type", "next").agg(F.count("*").alias("c"))
    k = event_numbers(spark, sf_dir)
    first, second = k.select("event_type", F.col("k").alias("i")), k.select(F.col("event_type").alias("next"), F.col("k").alias("j"))
    full = first.crossJoin(second).join(counts, ["event_type", "next"], "left").select("i", "j", F.coalesce("c", F.lit(0)).alias("c"))
    row = F.sum("c").over(Window.partitionBy("i"))
    return full.select("i", "j", F.when(row > 0, F.col("c") / row).otherwise(0.0).alias("x"))


def markov(spark: SparkSession, sf_dir: str) -> DataFrame:
    return damped(transitions(spark, sf_dir))


def brand_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    """C C' + 25 I for the counts C of parts by brand and type."""
    counts = table(spark, sf_dir, "part").groupBy("p_brand", "p_type").agg(F.count("*").alias("c"))
    brands = counts.select("p_brand").distinct().withColumn("i", (F.row_number().over(Window.orderBy(F.asc_nulls_last("p_brand"))) - 1).cast("long"))
    one = counts.join(brands, "p_brand").select("i", "p_type", "c")
    two = one.select(F.col("i").alias("j"), "p_type", F.col("c").alias("d"))
    sums = one.join(two, "p_type").groupBy("i", "j").agg(F.sum(F.col("c") * F.col("d")).cast("double").alias("x"))
    every = brands.select("i").crossJoin(brands.select(F.col("i").alias("j")))
    return shifted(every.join(sums, ["i", "j"], "left").select("i", "j", F.coalesce("x", F.lit(0.0)).alias("x")), 25.0)


# Generated matrices; (i, j) are arrays of row and column numbers from 0.


def min_ij(spark: SparkSession, n: int, block: int) -> BlockFrame:
    """min(i, j) + 1: all leading minors are 1, the inverse is tridiagonal with whole numbers."""
    import numpy as np

    return generated(spark, n, block, lambda i, j: np.minimum(i, j) + 1.0)


def ones_shift(spark: SparkSession, n: int, block: int, a: float = 3.0, b: float = 2.0) -> BlockFrame:
    """a I + b J; inverse (I - b / (a + n b) J) / a."""
    return generated(spark, n, block, lambda i, j: a * (i == j) + b)


def hadamard(spark: SparkSession, n: int, block: int) -> BlockFrame:
    """Parity of the common bits of i and j, for n a power of two; inverse H' / n."""
    import numpy as np

    return generated(spark, n, block, lambda i, j: 1.0 - 2.0 * (np.bitwise_count(i & j) % 2))


def hilbert(spark: SparkSession, n: int, block: int) -> BlockFrame:
    """1 / (i + j + 1): ill-conditioned, inverse of whole numbers."""
    return generated(spark, n, block, lambda i, j: 1.0 / (i + j + 1))


def low_rank_corner(spark: SparkSession, n: int, block: int) -> BlockFrame:
    """[[E, I], [I, 0]] with E of rank one but for rounding: regular, though its leading quadrant is not. The inverse is [[0, I], [I, -E]]."""
    import numpy as np

    h = n // 2

    def cell(i, j):
        e = (i % 7 + 1) / 3.0 * ((j % 5 + 1) / 7.0)
        return np.where((i < h) & (j < h), e, (np.abs(i - j) == h).astype(float))

    return generated(spark, n, block, cell)


def swap(spark: SparkSession, n: int, block: int) -> BlockFrame:
    """[[0, I], [I, 0]]: its own inverse, with a singular leading quadrant."""
    return generated(spark, n, block, lambda i, j: ((i + n // 2) % n == j).astype(float))


def random_dense(spark: SparkSession, n: int, block: int, seed: int = 0) -> BlockFrame:
    """Uniform random cells, the same for every division into blocks; the diagonal is raised by n for a safe inverse."""
    import numpy as np

    def cell(i, j):
        with np.errstate(over="ignore"):
            x = (i.astype(np.uint64) * np.uint64(n) + j.astype(np.uint64) + np.uint64(seed << 40)) * np.uint64(0x9E3779B97F4A7C15)
            x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return (x >> np.uint64(11)) / 2.0**53 + n * (i == j)

    return generated(spark, n, block, cell)
