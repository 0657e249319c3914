"""Registered queries of the engine, each with the SQL that answers the same question where SQL can."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import apps
from . import oracles as O
from .functions.local import quad_invert
from .operators import baselines, blocklu, ops
from .operators.blocks import BlockFrame, crop, from_coo, from_numpy, from_rows, pad, reblock, to_coo, to_numpy, to_rows
from .operators.gemm import multiply
from .operators.invert import InvertOptions, quad_inverse
from .operators.parts import inverse_by_parts
from .plans import costmodel, metrics, published
from .plans.expr import Inverse, Matrix, evaluate
from .plans.lineage import shared_folder
from .sources import io, matrices
from .sources.matrices import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def shown(cells: DataFrame, digits: int) -> DataFrame:
    return cells.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), rounded("x", digits).alias("x"))


def rounded(x: str | Column, digits: int) -> Column:
    return F.round(F.col(x) if isinstance(x, str) else x, digits) + F.lit(0.0)


def whole_block(n: int) -> int:
    """Blocks of 128, and from n = 2049 on a power of two that makes at most 16 a side."""
    return max(128, 1 << ((n - 1) // 16).bit_length())


def kernel_block(n: int) -> int:
    """Order of the blocks that divide n into 4 a side, or the next power of two for which they are 2048 at most; padding is below a block a side."""
    b = max(4, 1 << (-(-n // 2048) - 1).bit_length())
    return -(-n // b)


def gram(spark: SparkSession, sf_dir: str, b: int, **known) -> BlockFrame:
    return from_coo(matrices.gram(spark, sf_dir), 64, 64 // b, **known)


def price_dom(spark: SparkSession, sf_dir: str, b: int, n: int = 128) -> BlockFrame:
    return from_coo(matrices.price_dom(spark, sf_dir, n), n, n // b)


GRAM_SQL = O.cells(O.inverse(O.GRAM, 64), 8)
PRICE_SQL = O.cells(O.inverse(O.price(128, 128), 128), 10)

# The method: divisions, options, sources.

for b in (1, 2, 4, 8):
    query(f"q_quadinv_gram64_b{b}", GRAM_SQL)(lambda s, d, b=b: shown(to_coo(quad_inverse(gram(s, d, b))), 8))
for b in (4, 8):
    query(f"q_quadinv_price_dom128_b{b}", PRICE_SQL)(lambda s, d, b=b: shown(to_coo(quad_inverse(price_dom(s, d, b))), 10))

OPTIONS = {
    **{f"q_leaf_{k}_gram64": InvertOptions(leaf_solver=k) for k in ("lu", "qr", "svd", "cholesky", "gauss_jordan")},
    "q_leaf_threshold_gram64": InvertOptions(leaf_blocks=2),
    "q_leaf_driver_gram64": InvertOptions(leaf_site="driver"),
    "q_split_tagged_gram64": InvertOptions(split_mode="tagged"),
    "q_schur_plain_gram64": InvertOptions(schur="plain"),
    "q_unfused_gram64": InvertOptions(fuse=False),
    "q_refined_gram64": InvertOptions(refine=1),
    "q_parallel_panels_gram64": InvertOptions(parallel_panels=True),
    "q_symmetric_gram64": InvertOptions(symmetric=True),
    "q_materialize_parquet_gram64": InvertOptions(materialize="parquet"),
    "q_materialize_persist_gram64": InvertOptions(materialize="persist"),
    **{f"q_quadinv_{k}_gram64": InvertOptions(strategy=k) for k in ("replicate", "contract", "broadcast")},
    "q_quadinv_timed_gram64": InvertOptions(timed=True),
}
for name, opts in OPTIONS.items():
    # A Cholesky leaf takes positive definite blocks, so the complement's sign isn't turned there.
    made = InvertOptions(**{**{k: v for k, v in vars(opts).items() if k != "trace"}, "schur": "plain"}) if "cholesky" in name else opts
    query(name, GRAM_SQL)(lambda s, d, o=made: shown(to_coo(quad_inverse(gram(s, d, 2 if o.leaf_blocks == 1 else 4), InvertOptions(**{k: v for k, v in vars(o).items() if k != "trace"}))), 8))


@query("q_serial_quad_price64", O.cells(O.inverse(O.price(64, 64), 64), 10))
def serial(s, d):
    return shown(to_coo(from_numpy(s, quad_invert(to_numpy(price_dom(s, d, 2, 64)), 8), 32)), 10)


@query("q_quadinv_price128_residual", f"SELECT CAST(128 AS BIGINT) AS n, max(abs(x - CASE WHEN i = j THEN 1.0 ELSE 0.0 END)) < 1e-6 AS accurate FROM {O.product(O.price(128), O.inverse(O.price(128), 128))} AS c")
def price_residual(s, d):
    a = from_coo(matrices.price(s, d, 128), 128, 32)
    return metrics.residual(a, quad_inverse(a)).select(F.lit(128).cast("long").alias("n"), (F.col("max_abs") < 1e-6).alias("accurate"))


def price_all(s, d, dominant: bool = True) -> BlockFrame:
    """The matrix of all prices, as it is or with its order added on the diagonal."""
    cells, n = matrices.price_all(s, d)
    return from_coo(matrices.shifted(cells, n) if dominant else cells, n, whole_block(n))


query("q_quadinv_price_dom_all")(lambda s, d: shown(to_coo(quad_inverse(price_all(s, d))), 10))
query("q_blocklu_price_dom_all")(lambda s, d: shown(to_coo(blocklu.lu_inverse(price_all(s, d))), 10))
query("q_multiply_price_all")(lambda s, d: shown(to_coo(multiply(price_all(s, d, False), price_all(s, d, False))), 6))


# (X X' + I)^-1 = I - X (I + X'X)^-1 X', so elimination of 64 x 64 answers for as many rows as there are.
KERNEL_SQL = f"""WITH v AS (SELECT row_number() OVER (ORDER BY vec_id) - 1 AS i, embedding FROM embeddings), f AS (SELECT i, CAST(unnest(embedding) AS DOUBLE) AS p, unnest(range(64)) AS k FROM v),
 h AS (SELECT f.i, g.j AS k, sum(f.p * g.x) AS y FROM f JOIN {O.inverse(O.GRAM, 64)} AS g ON g.i = f.k GROUP BY 1, 2)
 SELECT CAST(h.i AS BIGINT) AS i, CAST(f.i AS BIGINT) AS j, round(CASE WHEN h.i = f.i THEN 1.0 ELSE 0.0 END - sum(h.y * f.p), 8) + 0.0 AS x FROM h JOIN f ON f.k = h.k GROUP BY h.i, f.i"""


@query("q_quadinv_kernel_all", KERNEL_SQL)
def kernel_all(s, d):
    """The kernel of all embeddings, its order their number."""
    n = table(s, d, "embeddings").count()
    return shown(to_coo(quad_inverse(matrices.kernel(s, d, n, kernel_block(n)))), 8)


query("q_quadinv_flow25", O.cells(O.inverse(O.damped(O.FLOW_SHARES), 25), 8))(lambda s, d: shown(to_coo(quad_inverse(from_coo(matrices.flow(s, d), 25, 8))), 8))


@query("q_quadinv_brand25", O.cells(O.inverse(O.BRANDS, 25), 9))
def brand25(s, d):
    """All brands, 25 in the given tables."""
    n = table(s, d, "part").select("p_brand").distinct().count()
    return shown(to_coo(quad_inverse(from_coo(matrices.brand_type(s, d), n, max(8, kernel_block(n))))), 9)


@query("q_quadinv_supplier100", O.cells(O.inverse(O.SUPPLIERS, 100), 9))
def supplier100(s, d):
    """Of suppliers that no chain of shared orders links, the cells are zero; the others are inverted part by part."""
    n = table(s, d, "supplier").count()
    inside, between = inverse_by_parts(matrices.supplier_graph(s, d), n, max(32, min(2048, -(-n // 16))), symmetric=True)
    cells = shown(inside, 9)
    return cells.unionByName(between) if between is not None else cells


NUMBERS = "range({n}) a(i), range({n}) b(j)"
query("q_quadinv_min_ij64", f"SELECT i, j, CASE WHEN i = j THEN CASE WHEN i = 63 THEN 1.0 ELSE 2.0 END WHEN abs(i - j) = 1 THEN -1.0 ELSE 0.0 END::DOUBLE AS x FROM {NUMBERS.format(n=64)}")(lambda s, d: shown(to_coo(quad_inverse(matrices.min_ij(s, 64, 16))), 8))
query("q_quadinv_ones_shift64", f"SELECT i, j, round((CASE WHEN i = j THEN 1.0 ELSE 0.0 END - 2.0 / 131.0) / 3.0, 8) + 0.0 AS x FROM {NUMBERS.format(n=64)}".replace("2.0 / 131.0", "2.0::DOUBLE / 131.0::DOUBLE").replace("/ 3.0,", "/ 3.0::DOUBLE,"))(lambda s, d: shown(to_coo(quad_inverse(matrices.ones_shift(s, 64, 16))), 8))
query("q_quadinv_hadamard64", f"SELECT i, j, (CASE WHEN bit_count(i & j) % 2 = 0 THEN 1.0 ELSE -1.0 END)::DOUBLE / 64 AS x FROM {NUMBERS.format(n=64)}")(lambda s, d: shown(to_coo(quad_inverse(matrices.hadamard(s, 64, 16))), 8))
query("q_quadinv_hilbert6", O.cells(O.inverse(O.HILBERT6, 6), 2))(lambda s, d: shown(to_coo(quad_inverse(matrices.hilbert(s, 6, 3))), 2))
query("q_quadinv_swap16", f"SELECT i, j, (CASE WHEN (i + 8) % 16 = j THEN 1.0 ELSE 0.0 END)::DOUBLE AS x FROM {NUMBERS.format(n=16)}")(lambda s, d: shown(to_coo(quad_inverse(matrices.swap(s, 16, 4))), 8))

for n in (64, 128):
    for b in (2, 4):
        corner = f"SELECT i, j, round(CASE WHEN i >= {n // 2} AND j >= {n // 2} THEN -((i - {n // 2}) % 7 + 1) / 3.0::DOUBLE * (((j - {n // 2}) % 5 + 1) / 7.0::DOUBLE) WHEN abs(i - j) = {n // 2} THEN 1.0 ELSE 0.0 END::DOUBLE, 4) + 0.0 AS x FROM {NUMBERS.format(n=n)}"
        query(f"q_quadinv_low_rank_corner{n}_b{b}", corner)(lambda s, d, n=n, b=b: shown(to_coo(quad_inverse(matrices.low_rank_corner(s, n, n // b))), 4))

# Operations on blocks.

PRICE64 = O.price(64)
p64 = lambda s, d, b=4: from_coo(matrices.price(s, d, 64), 64, 64 // b)


@query("q_split_tags", "SELECT CAST(2 * (bi // 2) + bj // 2 AS INTEGER) AS q, CAST(bi % 2 AS BIGINT) AS bi, CAST(bj % 2 AS BIGINT) AS bj, CAST(16 AS INTEGER) AS nr, CAST(16 AS INTEGER) AS nc FROM range(4) a(bi), range(4) b(bj)")
def split_tags(s, d):
    return ops.split(p64(s, d)).drop("v")


for x in (1, 2):
    for y in (1, 2):
        rows, cols = 32 * (x - 1), 32 * (y - 1)
        sql = f"SELECT CAST(i - {rows} AS BIGINT) AS i, CAST(j - {cols} AS BIGINT) AS j, round(x, 8) + 0.0 AS x FROM {PRICE64} AS c WHERE i // 32 = {x - 1} AND j // 32 = {y - 1}"
        query(f"q_quadrant_{x}{y}", sql)(lambda s, d, x=x, y=y: shown(to_coo(ops.quadrant(p64(s, d), x, y)), 8))


@query("q_assemble_roundtrip", O.cells(PRICE64, 8))
def assemble_roundtrip(s, d):
    a = p64(s, d)
    return shown(to_coo(ops.assemble(*(ops.quadrant(a, x, y) for x in (1, 2) for y in (1, 2)))), 8)


query("q_scale_neg", O.cells(f"(SELECT i, j, -x AS x FROM {PRICE64})", 8))(lambda s, d: shown(to_coo(ops.scale(p64(s, d), -1)), 8))
query("q_transpose", O.cells(f"(SELECT j AS i, i AS j, x FROM {PRICE64})", 8))(lambda s, d: shown(to_coo(ops.transpose(p64(s, d))), 8))
query("q_subtract", O.cells(f"(SELECT a.i, a.j, a.x - b.x AS x FROM {PRICE64} a JOIN {PRICE64} b ON a.i = b.j AND a.j = b.i)", 8))(lambda s, d: shown(to_coo(ops.subtract(a := p64(s, d), ops.transpose(a))), 8))
query("q_add", O.cells(f"(SELECT a.i, a.j, a.x + b.x AS x FROM {PRICE64} a JOIN {PRICE64} b ON a.i = b.j AND a.j = b.i)", 8))(lambda s, d: shown(to_coo(ops.add(a := p64(s, d), ops.transpose(a))), 8))
query("q_coo_roundtrip", O.cells(PRICE64, 8))(lambda s, d: shown(to_coo(reblock(p64(s, d), 24)), 8))
query("q_rows_roundtrip", O.cells(PRICE64, 8))(lambda s, d: shown(to_coo(from_rows(to_rows(p64(s, d)), 64, 16)), 8))
query("q_pad_crop", O.cells(PRICE64, 8))(lambda s, d: shown(to_coo(crop(pad(from_coo(matrices.price(s, d, 64), 64, 24)), 64)), 8))
for k in ("grid3d", "replicate", "contract", "broadcast", "cells", "seven_product"):
    query(f"q_multiply_{k}", O.cells(O.product(PRICE64, PRICE64), 10))(lambda s, d, k=k: shown(to_coo(multiply(a := p64(s, d), a, k, cells=2 if k == "grid3d" else None)), 10))
query("q_multiply_fused", O.cells(f"(SELECT p.i, p.j, 2.0 * p.x - q.x AS x FROM {O.product(PRICE64, PRICE64)} p JOIN {PRICE64} q ON p.i = q.i AND p.j = q.j)", 10))(lambda s, d: shown(to_coo(multiply(a := p64(s, d), a, alpha=2.0, beta=-1.0, c=a)), 10))


@query("q_udtf_cells", O.cells(PRICE64, 8))
def udtf_cells(s, d):
    from .functions.udfs import register

    register(s)
    view = f"blocks_{uuid.uuid4().hex}"
    p64(s, d).df.createOrReplaceTempView(view)
    return shown(s.sql(f"SELECT b.bi * 16 + t.r AS i, b.bj * 16 + t.c AS j, t.x FROM {view} b, LATERAL block_cells(b.v, b.nr) t"), 8)


@query("q_sql_block_inverse", O.cells(O.inverse(O.price(64, 64), 64), 10))
def sql_block_inverse(s, d):
    from .functions.udfs import register

    register(s)
    a = price_dom(s, d, 1, 64)
    return shown(to_coo(a.of(a.df.selectExpr("bi", "bj", "nr", "nc", "block_inverse(v, nr) AS v"))), 10)


@query("q_load_coo_roundtrip", O.cells(PRICE64, 8))
def load_coo_roundtrip(s, d):
    path = f"{shared_folder(s)}/coo-{uuid.uuid4().hex}"
    io.save(p64(s, d), path)
    return shown(to_coo(io.load(s, path)), 8)


@query("q_expr_simplified_gram64", GRAM_SQL)
def expr_simplified(s, d):
    """The double transpose, the double sign and the product with I go before anything is computed."""
    a = Matrix(gram(s, d, 2))
    return shown(to_coo(evaluate(-(-Inverse(a.T.T)))), 8)


# Baselines.

query("q_blocklu_gram64", GRAM_SQL)(lambda s, d: shown(to_coo(blocklu.lu_inverse(gram(s, d, 4))), 8))
query("q_blocklu_price_dom128", PRICE_SQL)(lambda s, d: shown(to_coo(blocklu.lu_inverse(price_dom(s, d, 4))), 10))
query("q_blocklu_parquet_gram64", GRAM_SQL)(lambda s, d: shown(to_coo(blocklu.lu_inverse(gram(s, d, 2), InvertOptions(materialize="parquet"))), 8))
query("q_gauss_jordan_blocks_gram64", GRAM_SQL)(lambda s, d: shown(to_coo(baselines.gauss_jordan_blocks(gram(s, d, 4))), 8))
query("q_cholesky_blocks_gram64", GRAM_SQL)(lambda s, d: shown(to_coo(baselines.cholesky_blocks(gram(s, d, 4))), 8))
query("q_local_inverse_gram64", GRAM_SQL)(lambda s, d: shown(to_coo(baselines.local_inverse(gram(s, d, 4))), 8))


@query("q_blocklu_factors_gram64", f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(l, 8) + 0.0 AS l, round(u, 7) + 0.0 AS u FROM {O.lu_factors(O.GRAM, 64)} AS c")
def lu_pieces(s, d):
    lower, upper = blocklu.lu_factors(gram(s, d, 4))
    other = to_coo(upper).select("i", "j", F.col("x").alias("u"))
    return to_coo(lower).join(other, ["i", "j"]).select("i", "j", rounded("x", 8).alias("l"), rounded("u", 7).alias("u"))


# Counts, cost model, published numbers.


def counted(trace, spark) -> DataFrame:
    return trace.frame(spark).groupBy("op").agg(F.sum("calls").alias("calls"))


def _counts_sql(b_columns: dict[str, str], b: int) -> str:
    return " UNION ALL ".join(f"SELECT '{op}' AS op, CAST({e.replace('b', str(b))} AS BIGINT) AS calls" for op, e in b_columns.items())


QUADINV_COUNTS = {"leaf": "b", "multiply": "6 * (b - 1)", "subtract": "2 * (b - 1)", "scale": "b - 1", "split": "b - 1", "assemble": "b - 1", "quadrant": "4 * (b - 1)"}
LU_COUNTS = {"local_lu": "b", "local_inverse": "2 * b", "local_multiply": "3 * b // 2", "local_subtract": "b // 2", "multiply": "11 * (b // 2 - 1) + 7", "subtract": "b // 2 - 1", "scale": "4 * (b // 2 - 1)"}


@query("q_trace_counts_quadinv", _counts_sql(QUADINV_COUNTS, 4))
def trace_counts(s, d):
    opts = InvertOptions()
    quad_inverse(matrices.random_dense(s, 32, 8), opts)
    return counted(opts.trace, s)


@query("q_trace_counts_lu", _counts_sql(LU_COUNTS, 4))
def trace_counts_lu(s, d):
    opts = InvertOptions()
    blocklu.lu_inverse(matrices.random_dense(s, 32, 8), opts)
    return counted(opts.trace, s)


@query("q_trace_levels", "SELECT CAST(level AS INTEGER) AS level, CAST(2 ** level AS BIGINT) AS nodes, CAST(6 * 2 ** level AS BIGINT) AS products, CAST(6 * 2 ** level * (32 / 2 ** (level + 1)) ** 2 AS BIGINT) AS elements FROM range(2) r(level)")
def trace_levels(s, d):
    opts = InvertOptions()
    quad_inverse(matrices.random_dense(s, 32, 8), opts)
    return opts.trace.frame(s).filter("op = 'multiply'").groupBy("level").agg(F.countDistinct("node").alias("nodes"), F.sum("calls").alias("products"), F.sum("elements").alias("elements"))


@query("q_running_trace", "SELECT CAST(k AS BIGINT) AS step, CAST(k AS BIGINT) AS done FROM range(1, 19) r(k)")
def running_trace(s, d):
    """Products done so far, in the order of the run."""
    opts = InvertOptions()
    quad_inverse(matrices.random_dense(s, 32, 8), opts)
    from pyspark.sql import Window

    w = Window.orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    rows = [(k, r[7]) for k, r in enumerate((r for r in opts.trace.rows if r[6] == "multiply"), 1)]
    return s.createDataFrame(rows, "step long, calls long").select("step", F.sum("calls").over(w).alias("done"))


B_SQL = "(VALUES (2), (4), (8), (16), (32), (64)) t(b0)"
#: For each supplier the order of a matrix with a row for each of its lines: (n0, matrices), one row an order.
ORDERS_SQL = "(SELECT n0, count(*) AS matrices FROM (SELECT count(*) AS n0 FROM lineitem WHERE l_suppkey IS NOT NULL GROUP BY l_suppkey) GROUP BY n0)"
SIZES_SQL = f"(SELECT n0, b0 FROM {ORDERS_SQL}, {B_SQL})"
DIVISIONS = (2, 4, 8, 16, 32, 64)
# Costs are shown in units of 1,000,003, a prime: in millions, n^3 / b^2 often lies just between two roundings, where SQL and Spark may differ.


def orders(s, d) -> list[tuple[int, int]]:
    """(n, matrices): how many suppliers have n lines. Of N lines at most sqrt(2 N) orders differ."""
    counts = table(s, d, "lineitem").filter("l_suppkey is not null").groupBy("l_suppkey").count()
    return sorted((r[0], r[1]) for r in counts.groupBy("count").agg(F.count("*")).collect())


def sizes(s, d) -> list[tuple[int, int]]:
    return [(n, b) for n, _ in orders(s, d) for b in DIVISIONS]


@query("q_block_gemms", f"SELECT CAST(b AS INTEGER) AS b, CAST((SELECT sum(matrices) FROM {ORDERS_SQL}) * sum(6 * 2 ** i * (b / 2 ** (i + 1)) ** 3) AS BIGINT) AS gemms FROM (VALUES (2), (4), (8), (16), (32), (64)) t(b), range(6) r(i) WHERE 2 ** (i + 1) <= b GROUP BY b")
def gemms(s, d):
    """Block products for inverting the matrices of all suppliers."""
    matrices_ = sum(m for _, m in orders(s, d))
    return s.createDataFrame([(b, matrices_ * costmodel.block_gemms(b)) for b in DIVISIONS], "b int, gemms long")


# n, b, i and the four factors as doubles, for one level policy.
BASE_SQL = f"""(SELECT n0, b0, CAST(n0 AS DOUBLE) AS n, CAST(b0 AS DOUBLE) AS b, least(b0 * b0 / 4.0 ** i, 30.0) AS p0, least(b0 * b0 / 4.0 ** (i + 1), 30.0) AS p1, least(b0 * b0 / 4.0 ** (i + 2), 30.0) AS p2,
 least(n0 * n0 / 4.0 ** i, 30.0) AS e0, least(n0 * n0 / 4.0 ** (i + 1), 30.0) AS e1, least(n0 * n0 / 4.0, 30.0) AS ea FROM (SELECT n0, b0, greatest(CAST(round(log2(b0)) AS INTEGER) - 1, 0) AS i FROM {SIZES_SQL}))"""
TOTALS = {
    ("quadinv", "printed"): "n**3/b**2 + (10*b**2 - 6*b)/p0 + ((b-1) + (9*b**2 + n**2*(b+1)))/(b*p1) + n**2*(b**2*n + b**2 - 2*n)/(b**2*e1)",
    ("quadinv", "fixed"): "n**3/b**2 + (10*b**2 - 6*b)/p0 + ((b-1) * (9*b**2 + n**2*(b+1)))/(b*p1) + n**2*(b**2*n - n + b**2 - b)/(b**2*e1)",
    ("blocklu", "printed"): "9*n**3/b**2 + (b-1)*(210*b**2*(b-2) + 64*n**2*(b+1)*(b**2-14))/(105*b**2*p0) + (b-1)*(70*b**2*(b-2) + 8*n**2*(b+1)*(b**2-14))/(105*b**2*p1) + (b-1)*(b-2)/(105*b**2*p2) + 2*n**2*(b-1)*(8*n*(b**2+b+6) + 7*b*(b-2))/(21*b**3*e0) + 8*n**3*(b-1)*(b**2+b-6)/(42*b**3*e1) + 7*n**3/(8*ea)",
    ("blocklu", "fixed"): "9*n**3/b**2 + (b-1)*(210*b**2*(b-2) + 64*n**2*(b+1)*(b**2-14))/(105*b**2*p0) + (b-1)*(70*b**2*(b-2) + 8*n**2*(b+1)*(b**2-14))/(105*b**2*p1) + (b-1)*(b-2)/(6*p2) + 2*n**2*(b-1)*(8*n*(b**2+b-6) + 7*b*(b-2))/(21*b**3*e0) + 8*n**3*(b-1)*(b**2+b-6)/(42*b**3*e1) + 7*n**3/(8*ea)",
}
REDERIVED_SQL = f"""SELECT CAST(n0 AS BIGINT) AS n, CAST(b0 AS INTEGER) AS b, round((n**3/b**2 + s) / 1000003.0, 6) AS mcost FROM (
 SELECT n0, b0, CAST(n0 AS DOUBLE) AS n, CAST(b0 AS DOUBLE) AS b, sum(2.0**i * (
   5 * b0**2/4.0**i / least(b0**2/4.0**i, 30.0) + (4*b0**2/4.0**(i+1) + 6*2*(b0/2.0**(i+1))*n0**2/4.0**(i+1) + 5*b0**2/4.0**(i+1)) / least(b0**2/4.0**(i+1), 30.0)
   + (6*CAST(n0 AS DOUBLE)**3/8.0**(i+1) + 2*n0**2/4.0**(i+1)) / least(n0**2/4.0**(i+1), 30.0))) AS s
 FROM {SIZES_SQL}, range(6) r(i) WHERE 2**(i+1) <= b0 GROUP BY n0, b0)"""


def totals(method: str, edition: str):
    policy = "per_level" if edition == "rederived" else "deepest"

    def run(s, d):
        rows = [(n, b, costmodel.cost(method, n, b, 30, edition, policy)) for n, b in sizes(s, d)]
        return s.createDataFrame(rows, "n long, b int, cost double").select("n", "b", F.round(F.col("cost") / 1000003.0, 6).alias("mcost"))

    return run


for (method, edition), formula in TOTALS.items():
    query(f"q_cost_{'quadinv' if method == 'quadinv' else 'lu'}_{edition}", f"SELECT CAST(n0 AS BIGINT) AS n, CAST(b0 AS INTEGER) AS b, round(({formula}) / 1000003.0, 6) AS mcost FROM {BASE_SQL} AS t")(totals(method, edition))
query("q_cost_quadinv_rederived", REDERIVED_SQL)(totals("quadinv", "rederived"))
LU_REDERIVED_SQL = f"""SELECT CAST(n0 AS BIGINT) AS n, CAST(b0 AS INTEGER) AS b, round((9*n**3/b**2 + s + 7*n**3/8/least(n**2/4, 30.0)) / 1000003.0, 6) AS mcost FROM (
 SELECT n0, b0, any_value(n) AS n, any_value(b) AS b, sum(CASE WHEN 2**(i+2) > b THEN 0.0 ELSE (2.0**(i+1) - 1) * (
   (b**2/4.0**i + 8*(b/2.0**(i+1))*n**2/4.0**(i+1) + 4*b**2/4.0**(i+2)) / least(b**2/4.0**i, 30.0) + (b**2/4.0**i + 16*(b/2.0**(i+2))*n**2/4.0**(i+2)) / least(b**2/4.0**(i+1), 30.0)
   + b**2/4.0**(i+1) / least(b**2/4.0**(i+2), 30.0) + (4*n**3/8.0**(i+1) + n**2/4.0**(i+1)) / least(n**2/4.0**i, 30.0) + 8*n**3/8.0**(i+2) / least(n**2/4.0**(i+1), 30.0)) END) AS s
 FROM (SELECT n0, b0, CAST(n0 AS DOUBLE) AS n, CAST(b0 AS DOUBLE) AS b FROM {SIZES_SQL}), range(6) r(i) GROUP BY n0, b0)"""
query("q_cost_lu_rederived", LU_REDERIVED_SQL)(totals("blocklu", "rederived"))

ROW_SQL = {
    "quadinv": {"leaf": ("n**3/b**2", "1.0"), "split": ("2*b**2 - 2*b", "p0"), "quadrant_filter": ("8*b**2 - 4*b", "p0"), "quadrant_map": ("2*b**2 - 2*b", "p1"), "multiply": ("n**3*(b**2-1)/(6*b**2)", "e1"), "multiply_comm": ("n**2*(b**2-1)/(6*b)", "p1"), "subtract": ("n**2*(b-1)/(2*b)", "e1"), "scale": ("b*(b-1)/2", "p1"), "assemble": ("b*(b-1)/2", "p1")},
    "blocklu": {"leaf": ("9*n**3/b**2", "1.0"), "split": ("2.0/3*(b**2-3*b+2)", "p0"), "quadrant_filter": ("2.0/3*(b**2-3*b+2)", "p1"), "quadrant_map": ("(b**2-3*b+2)/6", "p2"), "multiply_large": ("16*n**3/(21*b**3)*(b**3-7*b+6)", "e0"), "multiply_comm_large": ("8*n**2*(b**2-1)*(8*b**2-112)/(105*b**2)", "p0"), "multiply_small": ("8*n**3/(42*b**3)*(b**3-7*b+6)", "e1"), "multiply_comm_small": ("n**2*(b**2-1)*(8*b**2-112)/(105*b**2)", "p1"), "subtract": ("2*n**2/(3*b**2)*(b**2-3*b+2)", "e0"), "scale": ("4.0/3*(b**2-3*b+2)", "p0"), "additional": ("7*n**3/8", "ea")},
}


@query("q_cost_table", " UNION ALL ".join(f"SELECT '{m}' AS method, CAST(n0 AS BIGINT) AS n, CAST(b0 AS INTEGER) AS b, '{step}' AS step, round(({comp}) / 1000003.0, 6) + 0.0 AS mcomp, round({p}, 6) AS pf FROM {BASE_SQL} AS t" for m, rows in ROW_SQL.items() for step, (comp, p) in rows.items()))
def cost_table(s, d):
    return costmodel.table(s, sizes(s, d), policy="deepest").select("method", "n", "b", "step", rounded(F.col("comp") / 1000003.0, 6).alias("mcomp"), F.round("pf", 6).alias("pf"))


@query("q_pf", f"SELECT CAST(n0 AS BIGINT) AS n, CAST(b0 AS INTEGER) AS b, CAST(i AS INTEGER) AS level, least(b0 * b0 / 4.0 ** i, 30.0)::DOUBLE AS blocks, least(n0 * n0 / 4.0 ** i, 30.0)::DOUBLE AS elements FROM {SIZES_SQL}, range(6) r(i) WHERE 2 ** i < b0")
def pfs(s, d):
    rows = [(n, b, i, float(costmodel.pf(b * b / 4**i, 30)), float(costmodel.pf(n * n / 4**i, 30))) for n, b in sizes(s, d) for i in range(costmodel.levels(b))]
    return s.createDataFrame(rows, "n long, b int, level int, blocks double, elements double")


@query("q_cost_argmin", f"SELECT CAST(n0 AS BIGINT) AS n, CAST(arg_min(b0, c) AS INTEGER) AS best_b FROM (SELECT n0, b0, {TOTALS['quadinv', 'fixed']} AS c FROM {BASE_SQL} AS t) GROUP BY n0")
def cost_argmin(s, d):
    rows = [(n, "quadinv", b, costmodel.cost("quadinv", n, b, 30, "fixed", "deepest")) for n, b in sizes(s, d)]
    return metrics.best(s.createDataFrame(rows, "n long, method string, b int, seconds double")).select("n", "best_b")


SWEEP_SQL = published.values_sql([(n, m, b, s) for (m, n), row in published.SWEEP.items() for b, s in row.items()], "n, method, b, seconds")
BEST_SQL = published.values_sql([(n, m, s) for m, row in published.BEST.items() for n, s in row.items()], "n, method, seconds")
SCALING_SQL = published.values_sql([(n, c, s) for n, row in published.SCALING.items() for c, s in row.items()], "n, cores, seconds")


def placed_sql(published_: str) -> str:
    """The orders of the suppliers' matrices, each with the least published order that holds it, or else the largest one."""
    return f"(SELECT n0, matrices, coalesce((SELECT min(n) FROM {published_} p WHERE p.n >= n0), (SELECT max(n) FROM {published_} p)) AS n FROM {ORDERS_SQL} o)"


def placed(s, d, known) -> DataFrame:
    """(order, matrices, n) for the orders of the suppliers' matrices; n as in placed_sql."""
    rows = [(o, m, min((n for n in known if n >= o), default=max(known))) for o, m in orders(s, d)]
    return s.createDataFrame(rows, "order long, matrices long, n long")


@query("q_published_best_ratio", f"SELECT CAST(n0 AS BIGINT) AS \"order\", CAST(matrices AS BIGINT) AS matrices, CAST(n AS BIGINT) AS n, round(a.seconds::DOUBLE / b.seconds, 6) AS ratio FROM (SELECT * FROM {BEST_SQL} WHERE method = 'blocklu') a JOIN (SELECT * FROM {BEST_SQL} WHERE method = 'quadinv') b USING (n) JOIN {placed_sql(BEST_SQL)} USING (n)")
def best_ratio(s, d):
    """What the published best times say about the suppliers' matrices."""
    times = published.best_times(s).withColumn("b", F.lit(0))
    ratios = metrics.ratio(times, "blocklu", "quadinv").select("n", F.round("ratio", 6).alias("ratio"))
    return placed(s, d, published.BEST["quadinv"]).join(ratios, "n").select("order", "matrices", "n", "ratio")


@query("q_published_sweep_ratio", f"SELECT CAST(n AS BIGINT) AS n, CAST(b AS INTEGER) AS b, round(a.seconds::DOUBLE / c.seconds, 6) AS ratio FROM (SELECT * FROM {SWEEP_SQL} WHERE method = 'blocklu') a JOIN (SELECT * FROM {SWEEP_SQL} WHERE method = 'quadinv') c USING (n, b)")
def sweep_ratio(s, d):
    return metrics.ratio(published.sweep(s), "blocklu", "quadinv").select("n", "b", F.round("ratio", 6).alias("ratio"))


@query(
    "q_published_u_shape",
    f"""WITH s AS (SELECT * FROM {SWEEP_SQL}), m AS (SELECT n, method, arg_min(b, seconds) AS best_b FROM s GROUP BY n, method),
 c AS (SELECT s.n, s.method, s.b, m.best_b, s.seconds - lag(s.seconds) OVER (PARTITION BY s.n, s.method ORDER BY s.b) AS change FROM s JOIN m ON s.n = m.n AND s.method = m.method)
 SELECT CAST(n AS BIGINT) AS n, method, CAST(any_value(best_b) AS INTEGER) AS argmin_b, bool_and(change IS NULL OR CASE WHEN b <= best_b THEN change < 0 ELSE change > 0 END) AS u_shaped FROM c GROUP BY n, method""",
)
def published_u(s, d):
    return metrics.u_shape(published.sweep(s))


@query("q_published_scaling_eff", f"SELECT CAST(n0 AS BIGINT) AS \"order\", CAST(matrices AS BIGINT) AS matrices, CAST(n AS BIGINT) AS n, CAST(cores AS INTEGER) AS cores, round(t5 * 5 / (seconds * cores)::DOUBLE, 6) AS efficiency FROM {SCALING_SQL} JOIN (SELECT n, seconds::DOUBLE AS t5 FROM {SCALING_SQL} WHERE cores = 5) USING (n) JOIN {placed_sql(SCALING_SQL)} USING (n)")
def scaling_eff(s, d):
    """The published scaling at the order that holds each of the suppliers' matrices."""
    found = metrics.efficiency(published.scaling(s)).select("n", "cores", F.round("efficiency", 6).alias("efficiency"))
    return placed(s, d, published.SCALING).join(found, "n").select("order", "matrices", "n", "cores", "efficiency")


THEORY_SQL = published.values_sql([(n, b, t, m) for n, row in published.THEORY.items() for b, (t, m) in row.items()], "n, b, predicted, measured")
STEPS_SQL = published.values_sql([(st, b, ms) for st, row in published.STEPS.items() for b, ms in row.items()], "step, b, ms")


@query("q_published_theory", f"SELECT CAST(n AS BIGINT) AS n, CAST(b AS INTEGER) AS b, round(predicted::DOUBLE / measured, 6) AS quotient FROM {THEORY_SQL}")
def published_theory(s, d):
    both = published.theory(s)
    pick = lambda c: both.select("n", "b", F.col(c).alias("seconds"))
    return metrics.compare_curves(pick("predicted"), pick("measured")).select("n", "b", F.round("quotient", 6).alias("quotient"))


@query("q_published_step_share", f"SELECT step, CAST(b AS INTEGER) AS b, round(ms::DOUBLE / sum(ms) OVER (PARTITION BY b), 6) AS share FROM {STEPS_SQL}")
def step_share(s, d):
    from pyspark.sql import Window

    return published.step_times(s).select("step", "b", F.round(F.col("ms") / F.sum("ms").over(Window.partitionBy("b")), 6).alias("share"))


# Uses of the inverse.

SOLVE_SQL = """WITH z AS (SELECT [1.0::DOUBLE, l_quantity, 100 * l_discount, 100 * l_tax] AS z, l_extendedprice AS y FROM lineitem), r AS (SELECT i, sum(z[i + 1] * y) AS t FROM z, range(4) a(i) GROUP BY i)
 SELECT CAST(v.i AS BIGINT) AS i, round(sum(v.x * r.t), 3) + 0.0 AS y FROM {inverse} AS v JOIN r ON r.i = v.j GROUP BY v.i"""


@query("q_solve_normal4", SOLVE_SQL.replace("{inverse}", O.inverse(O.NORMAL, 4)))
def solve_normal(s, d):
    lines = table(s, d, "lineitem").select("l_quantity", (100 * F.col("l_discount")).alias("d"), (100 * F.col("l_tax")).alias("t"), "l_extendedprice")
    return apps.linear_regression(lines, ["l_quantity", "d", "t"], "l_extendedprice").select("i", rounded("y", 3).alias("y"))


@query("q_solve_gram64", f"SELECT CAST(i AS BIGINT) AS i, CAST(0 AS BIGINT) AS j, round(sum(x), 8) + 0.0 AS x FROM {O.inverse(O.GRAM, 64)} AS v GROUP BY i")
def solve_ones(s, d):
    import numpy as np

    return shown(to_coo(apps.solve(gram(s, d, 2), from_numpy(s, np.ones((64, 1)), 32))).filter("j = 0"), 8)


@query("q_markov_fundamental", O.cells(O.inverse(O.damped(O.TRANSITIONS), 5), 8))
def fundamental(s, d):
    return shown(apps.markov_fundamental(matrices.markov(s, d), 5), 8)


@query("q_leontief_flow", f"SELECT CAST(v.i AS BIGINT) AS i, round(sum(v.x * (v.j + 1)), 6) + 0.0 AS y FROM {O.inverse(O.damped(O.FLOW_SHARES), 25)} AS v GROUP BY v.i")
def leontief_flow(s, d):
    demand = s.range(25).select(F.col("id").alias("j"), (F.col("id") + 1.0).alias("x"))
    return apps.leontief(matrices.flow(s, d), demand, 25).select("i", rounded("y", 6).alias("y"))


@query(
    "q_mahalanobis_embeddings",
    f"""WITH f AS (SELECT vec_id, CAST(unnest(embedding) AS DOUBLE) AS p, unnest(range(64)) AS k FROM embeddings)
 SELECT a.vec_id, round(sum(a.p * v.x * b.p), 8) + 0.0 AS d2 FROM f a JOIN {O.inverse(O.GRAM, 64)} AS v ON v.i = a.k JOIN f b ON b.vec_id = a.vec_id AND b.k = v.j GROUP BY a.vec_id""",
)
def mahalanobis(s, d):
    found = apps.mahalanobis(table(s, d, "embeddings"), "vec_id", "embedding", quad_inverse(gram(s, d, 2)))
    return found.select("vec_id", rounded("d2", 8).alias("d2"))


@query("q_det_gram64", f"SELECT 1.0::DOUBLE AS sign, round(sum(ln(u)), 6) AS logdet FROM {O.lu_factors(O.GRAM, 64)} AS c WHERE i = j")
def det(s, d):
    sign, log = apps.logdet(gram(s, d, 2))
    return s.createDataFrame([(float(sign), round(float(log), 6))], "sign double, logdet double")


NORMS_SQL = f"""WITH c AS (SELECT * FROM {PRICE64} AS p) SELECT round(sum(CASE WHEN i = j THEN x ELSE 0.0 END), 6) AS trace, round(sqrt(sum(x * x)), 6) AS norm_fro, round(max(abs(x)), 6) AS norm_max,
 round((SELECT max(s) FROM (SELECT sum(abs(x)) AS s FROM c GROUP BY j)), 6) AS norm_1, round((SELECT max(s) FROM (SELECT sum(abs(x)) AS s FROM c GROUP BY i)), 6) AS norm_inf FROM c"""


@query("q_norms", NORMS_SQL)
def norms(s, d):
    return metrics.norms(p64(s, d)).select(*[F.round(c, 6).alias(c) for c in ("trace", "norm_fro", "norm_max", "norm_1", "norm_inf")])


query("q_trace", f"SELECT round(sum(x), 6) AS trace FROM {PRICE64} AS c WHERE i = j")(lambda s, d: metrics.norms(p64(s, d)).select(F.round("trace", 6).alias("trace")))


@query("q_cond1", f"WITH a AS (SELECT * FROM {O.GRAM} AS g), v AS (SELECT * FROM {O.inverse(O.GRAM, 64)} AS g) SELECT round((SELECT max(s) FROM (SELECT sum(abs(x)) AS s FROM a GROUP BY j)) * (SELECT max(s) FROM (SELECT sum(abs(x)) AS s FROM v GROUP BY j)), 6) AS cond1")
def cond(s, d):
    a = gram(s, d, 2)
    return metrics.cond1(a, quad_inverse(a)).select(F.round("cond1", 6).alias("cond1"))


@query("q_topk_inverse", f"SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(x, 8) + 0.0 AS x FROM {O.inverse(O.damped(O.FLOW_SHARES), 25)} AS v ORDER BY round(abs(x), 8) DESC, i, j LIMIT 10")
def topk(s, d):
    cells = to_coo(quad_inverse(from_coo(matrices.flow(s, d), 25, 8)))
    return shown(cells.orderBy(F.round(F.abs("x"), 8).desc(), "i", "j").limit(10), 8)
