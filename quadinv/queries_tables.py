"""Registered queries around the matrices: building cells, joins, windows, roll-ups and streams on the tables."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from . import oracles as O
from .queries import PRICE64, p64, query, rounded, shown
from .operators.blocks import to_coo
from .sources import matrices
from .sources.matrices import table
from .streaming import streams

query("q_price_cells", O.cells(O.price(128), 8))(lambda s, d: shown(matrices.price(s, d, 128), 8))
query("q_price_cells_all")(lambda s, d: shown(matrices.price_all(s, d)[0], 8))
query("q_gram_cells", O.cells(O.GRAM, 8))(lambda s, d: shown(matrices.gram(s, d), 8))
query("q_markov_cells", O.cells(O.TRANSITIONS, 8))(lambda s, d: shown(matrices.transitions(s, d), 8))
query("q_flow_cells", O.cells(O.FLOW_SHARES, 8))(lambda s, d: shown(matrices.flow_shares(s, d), 8))
query("q_brand_cells", O.cells(O.BRANDS, 6))(lambda s, d: shown(matrices.brand_type(s, d), 6))
query("q_normal_cells", O.cells(O.NORMAL, 2))(lambda s, d: shown(matrices.normal(s, d), 2))
query("q_supplier_cells", O.cells(f"(SELECT * FROM {O.SUPPLIERS} AS q WHERE x <> 0)", 6))(lambda s, d: shown(matrices.supplier_graph(s, d), 6))
query("q_band_cells", O.cells(f"(SELECT * FROM {PRICE64} AS p WHERE abs(i - j) <= 2)", 8))(lambda s, d: shown(to_coo(p64(s, d)).filter(F.abs(F.col("i") - F.col("j")).between(0, 2)), 8))


@query("q_kernel_cells", "SELECT a.vec_id AS i, b.vec_id AS j, round(list_sum(list_transform(range(1, 65), lambda k: CAST(a.embedding[k] AS DOUBLE) * CAST(b.embedding[k] AS DOUBLE))), 8) + 0.0 AS x FROM embeddings a, embeddings b")
def kernel_cells(s, d):
    """All pairs of all embeddings, pack by pack."""
    return matrices.dots(matrices.vectors(s, d).withColumnRenamed("vec_id", "i"), 8)


@query("q_dot_products", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE))), 8) + 0.0 AS x FROM embeddings")
def dot_products(s, d):
    wide = F.transform("embedding", lambda v: v.cast("double"))
    return table(s, d, "embeddings").select("vec_id", rounded(F.aggregate(F.zip_with(wide, wide, lambda a, b: a * b), F.lit(0.0), lambda t, v: t + v), 8).alias("x"))


@query("q_upper_triangle", f"SELECT a.i AS i, b.i AS j, round(a.x + b.x, 8) + 0.0 AS x FROM (SELECT * FROM {PRICE64} AS p WHERE i = j) a JOIN (SELECT * FROM {PRICE64} AS p WHERE i = j) b ON a.i <= b.i")
def upper_triangle(s, d):
    one = to_coo(p64(s, d)).filter("i = j").select("i", "x")
    two = one.select(F.col("i").alias("j"), F.col("x").alias("y"))
    return one.join(F.broadcast(two), F.col("i") <= F.col("j")).select("i", "j", rounded(F.col("x") + F.col("y"), 8).alias("x"))


BANDS = [(0, 0, 1000), (1, 1000, 1300), (2, 1300, 1700), (3, 1700, 1000000)]


@query("q_price_bands", f"SELECT CAST(band AS INTEGER) AS band, count(*) AS n, round(sum(p_retailprice), 2) AS total FROM part JOIN (VALUES {', '.join(map(str, BANDS))}) b(band, low, high) ON p_retailprice >= low AND p_retailprice < high GROUP BY band")
def price_bands(s, d):
    bands = s.createDataFrame([(b, float(lo), float(hi)) for b, lo, hi in BANDS], "band int, low double, high double")
    hit = (F.col("p_retailprice") >= F.col("low")) & (F.col("p_retailprice") < F.col("high"))
    return table(s, d, "part").select("p_retailprice").join(F.broadcast(bands), hit).groupBy("band").agg(F.count("*").alias("n"), F.round(F.sum("p_retailprice"), 2).alias("total"))


@query("q_empty_rows", "SELECT CAST(n_nationkey AS BIGINT) AS i FROM nation WHERE n_nationkey NOT IN (SELECT s_nationkey FROM supplier WHERE s_nationkey IS NOT NULL)")
def empty_rows(s, d):
    """Nations without a supplier: their columns of the flow matrix are empty."""
    sellers = table(s, d, "supplier").select(F.col("s_nationkey").alias("n_nationkey"))
    return table(s, d, "nation").join(sellers, "n_nationkey", "left_anti").select(F.col("n_nationkey").cast("long").alias("i"))


@query("q_used_rows", "SELECT CAST(n_nationkey AS BIGINT) AS i FROM nation WHERE n_nationkey IN (SELECT s_nationkey FROM supplier)")
def used_rows(s, d):
    sellers = table(s, d, "supplier").select(F.col("s_nationkey").alias("n_nationkey"))
    return table(s, d, "nation").join(sellers, "n_nationkey", "left_semi").select(F.col("n_nationkey").cast("long").alias("i"))


@query("q_event_asof", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_purchase FROM events")
def event_asof(s, d):
    """For each event the last purchase of the same user before it."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return table(s, d, "events").select("event_id", last.alias("last_purchase"))


@query("q_event_interval", "SELECT a.event_id, count(b.event_id) AS n FROM events a LEFT JOIN events b ON a.user_id = b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 24 HOUR GROUP BY a.event_id")
def event_interval(s, d):
    """Events of the same user in the day before each event, by a window over time instead of a range join."""
    w = Window.partitionBy("user_id").orderBy(streams.micros("ts")).rangeBetween(-86_400_000_000, -1)
    return table(s, d, "events").select("event_id", F.count("event_id").over(w).alias("n"))


@query("q_event_weights", "SELECT event_type, count(*) AS n, round(sum(CAST(json_extract_string(props, '$.k') AS DOUBLE)), 6) AS weight FROM events GROUP BY event_type")
def event_weights(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum(F.get_json_object("props", "$.k").cast("double")), 6).alias("weight"))


@query("q_monthly_gram", "SELECT strftime(date_trunc('month', ts), '%Y-%m-%d') AS month, count(*) AS g00, round(sum(value), 4) AS g01, round(sum(value * value), 4) AS g11 FROM events GROUP BY 1")
def monthly_gram(s, d):
    """Cells of Z'Z for Z = (1, value), month by month."""
    month = F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("month")
    return table(s, d, "events").groupBy(month).agg(F.count("*").alias("g00"), F.round(F.sum("value"), 4).alias("g01"), F.round(F.sum(F.col("value") * F.col("value")), 4).alias("g11"))


@query("q_distinct_keys", "SELECT count(DISTINCT l_orderkey) AS orders, count(DISTINCT l_suppkey) AS suppliers, (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem)) AS pairs FROM lineitem")
def distinct_keys(s, d):
    lines = table(s, d, "lineitem")
    return lines.agg(F.countDistinct("l_orderkey").alias("orders"), F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_orderkey", "l_suppkey").alias("pairs"))


@query("q_statistics", "SELECT count(*) AS n, round(avg(l_extendedprice), 4) AS mean, round(stddev_samp(l_extendedprice), 4) AS sd, round(covar_samp(l_quantity, l_extendedprice), 3) AS cov, round(corr(l_quantity, l_extendedprice), 8) AS r FROM lineitem")
def statistics(s, d):
    q, p = F.col("l_quantity"), F.col("l_extendedprice")
    return table(s, d, "lineitem").agg(F.count("*").alias("n"), F.round(F.avg(p), 4).alias("mean"), F.round(F.stddev_samp(p), 4).alias("sd"), F.round(F.covar_samp(q, p), 3).alias("cov"), F.round(F.corr(q, p), 8).alias("r"))


GROUPED = "SELECT r_name AS region, n_name AS nation, grouping(r_name) * 2 + grouping(n_name) AS level, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY {g}"


def _revenue(s, d):
    orders = table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"), F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    nations = table(s, d, "nation").join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("c_nationkey"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"))
    return orders.join(table(s, d, "customer").select("c_custkey", "c_nationkey"), "c_custkey").join(nations, "c_nationkey")




def _summed(grouped):
    return grouped.agg(F.grouping_id().cast("long").alias("level"), F.sum("cents").alias("cents"))


query("q_flow_rollup", GROUPED.format(g="ROLLUP (r_name, n_name)"))(lambda s, d: _summed(_revenue(s, d).rollup("region", "nation")))
query("q_flow_cube", GROUPED.format(g="CUBE (r_name, n_name)"))(lambda s, d: _summed(_revenue(s, d).cube("region", "nation")))


@query("q_flow_grouping_sets", GROUPED.format(g="GROUPING SETS ((n_name), (r_name), ())"))
def grouping_sets(s, d):
    view = f"revenue_{uuid.uuid4().hex}"
    _revenue(s, d).createOrReplaceTempView(view)
    return s.sql(f"SELECT region, nation, CAST(grouping(region) * 2 + grouping(nation) AS BIGINT) AS level, sum(cents) AS cents FROM {view} GROUP BY GROUPING SETS ((nation), (region), ())")


@query("q_markov_pivot", "WITH s AS (SELECT event_type AS a, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events) SELECT a AS event_type, count(*) FILTER (b = 'click') AS click, count(*) FILTER (b = 'purchase') AS purchase, count(*) FILTER (b = 'view') AS view FROM s WHERE b IS NOT NULL GROUP BY a")
def markov_pivot(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    steps = table(s, d, "events").select("event_type", F.lead("event_type").over(w).alias("next")).filter("next is not null")
    return steps.groupBy("event_type").pivot("next", ["click", "purchase", "view"]).count().na.fill(0)


@query("q_set_ops", "(SELECT c_nationkey AS i, 'both' AS kind FROM customer INTERSECT SELECT s_nationkey, 'both' FROM supplier) UNION ALL (SELECT c_nationkey AS i, 'buyers' AS kind FROM customer EXCEPT SELECT s_nationkey, 'buyers' FROM supplier)")
def set_ops(s, d):
    buyers, sellers = table(s, d, "customer").select(F.col("c_nationkey").alias("i")), table(s, d, "supplier").select(F.col("s_nationkey").alias("i"))
    both = buyers.intersect(sellers).withColumn("kind", F.lit("both"))
    return both.unionByName(buyers.subtract(sellers).withColumn("kind", F.lit("buyers")))


# One join, by each of the physical ways.

JOIN_SQL = "SELECT c_mktsegment, count(*) AS n, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM orders JOIN customer ON c_custkey = o_custkey GROUP BY c_mktsegment"
for hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"q_join_{hint}", JOIN_SQL)
    def joined(s, d, hint=hint):
        customers = table(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment").hint(hint)
        orders = table(s, d, "orders").select("o_custkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
        return orders.join(customers, "o_custkey").groupBy("c_mktsegment").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))


# Streams; each drains what is there and answers as the batch would.


def _drained(s, stream, mode="complete"):
    return streams.drained(stream, f"stream_{uuid.uuid4().hex}", mode)


TS = lambda c: F.date_format(streams.plain(c), "yyyy-MM-dd HH:mm:ss").alias(c)


@query("q_stream_tumbling_counts", "SELECT strftime(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def tumbling(s, d):
    out = _drained(s, streams.tumbling_counts(streams.event_stream(s, f"{d}/events.parquet")))
    return out.select(TS("start"), "event_type", "n")


@query("q_stream_sliding_counts", "SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM (SELECT event_type, time_bucket(INTERVAL 12 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 12 HOUR AS start FROM events, range(2) r(k)) GROUP BY 1, 2")
def sliding(s, d):
    out = _drained(s, streams.sliding_counts(streams.event_stream(s, f"{d}/events.parquet")))
    return out.select(TS("start"), "event_type", "n")


@query(
    "q_stream_session_counts",
    """WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
 b AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM a)
 SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, strftime(max(ts) + INTERVAL 6 HOUR, '%Y-%m-%d %H:%M:%S') AS stop, count(*) AS n FROM b GROUP BY user_id, k""",
)
def sessions(s, d):
    out = _drained(s, streams.session_counts(streams.event_stream(s, f"{d}/events.parquet")))
    return out.select("user_id", TS("start"), TS("stop"), "n")


@query("q_stream_markov_final", O.cells(O.TRANSITIONS, 8))
def stream_markov(s, d):
    """Transition shares from the stateful stream of steps."""
    steps = _drained(s, streams.transition_stream(streams.event_stream(s, f"{d}/events.parquet")), "append")
    counts = steps.groupBy("event_type", "next").agg(F.count("*").alias("c"))
    k = matrices.event_numbers(s, d)
    first, second = k.select("event_type", F.col("k").alias("i")), k.select(F.col("event_type").alias("next"), F.col("k").alias("j"))
    full = first.crossJoin(second).join(counts, ["event_type", "next"], "left").select("i", "j", F.coalesce("c", F.lit(0)).alias("c"))
    row = F.sum("c").over(Window.partitionBy("i"))
    return shown(full.select("i", "j", F.when(row > 0, F.col("c") / row).otherwise(0.0).alias("x")), 8)


@query("q_stream_gram", "SELECT strftime(time_bucket(INTERVAL 7 DAY, ts, TIMESTAMP '1970-01-01'), '%Y-%m-%d %H:%M:%S') AS start, CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(sum([1.0::DOUBLE, value][i + 1] * [1.0::DOUBLE, value][j + 1]), 4) AS x FROM events, range(2) a(i), range(2) b(j) GROUP BY 1, 2, 3")
def stream_gram(s, d):
    rows = streams.event_stream(s, f"{d}/events.parquet").select("ts", F.lit(1.0).alias("one"), "value")
    out = _drained(s, streams.gram_stream(rows, ["one", "value"], "7 days"))
    return out.select(TS("start"), "i", "j", F.round("x", 4).alias("x"))
