"""Line dedup with DataFrame functions only: windows of three consecutive lines that occurred before are removed.

Lines are the parts of a text between \\n; blank lines (only white space `[\\x20\\x09-\\x0D]`) are kept where they are and are
skipped by the windows. Of each window of three lines, the first occurrence in the order of (doc_id, MD5 of the text,
position) stays; the lines of every later occurrence go, overlapping ones merged into one set of positions. A window is known
by 128 bits of two seeded XXH64 values over its lines.

One aggregate finds the repeated windows with their counts and first places. A window met more often than HOT times, and in
more than 1 of MOST_HOT occurrences, is hot: there are at most MOST_HOT such, so that they are broadcast and their occurrences aren't
dealt by window at all. The others are joined.

Null and empty texts and texts of fewer than three lines with words have no window and stay as they are (null stays null).
Rows of one doc_id and different texts are told apart by the MD5; of rows equal in both, one counts as the first and the others
lose every line that lies in a window. Null ids come first in the order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, table, unnamed

LINES = 3
#: Occurrences from which a window may be hot, and the most hot windows that there can be.
HOT, MOST_HOT = 256, 10_000
BLANK = r"^[\x20\x09-\x0D]*$"


def _windows(lines: Column, width: int) -> Column:
    """Array of (h0, h1, positions) for the runs of width lines with words; positions are those in the text, from 0."""
    numbered = F.filter(F.transform(lines, lambda line, i: F.struct(line.alias("line"), i.alias("at"))), lambda x: ~x["line"].rlike(BLANK))
    run = lambda all_, i, field: [all_[(i + k).cast("int")][field] for k in range(width)]
    return F.transform(
        F.array(numbered),
        lambda kept: F.transform(
            F.when(F.size(kept) >= width, F.sequence(F.lit(0), F.size(kept) - width)).otherwise(F.array().cast("array<int>")),
            lambda i: F.struct(F.xxhash64(*run(kept, i, "line")).alias("h0"), F.xxhash64(F.lit("second"), *run(kept, i, "line")).alias("h1"), F.array(*run(kept, i, "at")).alias("at")),
        ),
    )[0]


def _identity(text: str, doc_id: str) -> list[Column]:
    """What a row is known by: its id and 120 bits of its text's MD5 as two longs that aren't null, which SQL can work out too."""
    digest = F.md5(F.coalesce(F.col(text), F.lit("")))
    return [F.col(doc_id).alias("id"), *[F.conv(F.substring(digest, 1 + 15 * k, 15), 16, 10).cast("long").alias(f"c{k}") for k in (0, 1)]]


def repeated_lines(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = LINES, hot: int = HOT) -> DataFrame:
    """(doc, lines): for each document (id, c0, c1) that has any, the positions of its lines to remove, ascending."""
    each = docs.select(F.struct(*_identity(text, doc_id)).alias("doc"), _windows(F.split(F.col(text), "\n", -1), width).alias("ws"))
    # Beside the explode the digest would be worked out for every window; an inner explode would put a filter on the windows before it, which works them out twice more.
    found = each.select("doc", F.explode_outer("ws").alias("w")).filter("w is not null").select("doc", "w.h0", "w.h1", "w.at")
    often = cut(found.groupBy("h0", "h1").agg(F.count("*").alias("n"), F.min(F.struct("doc", "at")).alias("first")).filter("n > 1"))
    bound = max(hot, (often.agg(F.sum("n")).first()[0] or 0) // MOST_HOT)
    common = often.filter(F.col("n") > bound).select(F.col("h0").alias("g0"), F.col("h1").alias("g1"), F.col("first").alias("hot_first"))
    told = found.join(F.broadcast(common), (F.col("h0") == F.col("g0")) & (F.col("h1") == F.col("g1")), "left")
    # What is settled by the broadcast is dealt by document, where it meets nothing.
    settled = F.col("hot_first").isNotNull()
    told = told.select("doc", "at", "hot_first", F.when(settled, F.xxhash64("doc", "at")).otherwise(F.col("h0")).alias("h0"), F.when(settled, F.lit(0)).otherwise(F.col("h1")).alias("h1"))
    rare = often.filter(F.col("n") <= bound).select("h0", "h1", "first")
    later = told.join(rare, ["h0", "h1"], "left").filter(F.struct("doc", "at") > F.coalesce("hot_first", "first"))
    return later.select("doc", F.explode("at").alias("line")).groupBy("doc").agg(F.array_sort(F.collect_set("line")).alias("lines"))


def deduplicated(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = LINES, hot: int = HOT) -> DataFrame:
    """docs, each text without its repeated lines, with removed_lines (how many) behind its columns, in place of one of that name."""
    plain, name = unnamed(docs)
    words = name[text]
    row = lambda id_, c0, c1: [F.xxhash64(F.lit(seed), c0, c1, id_) for seed in ("one", "two")]
    gone = repeated_lines(plain, words, name[doc_id], width, hot).select(*[k.alias(f"r{i}") for i, k in enumerate(row(F.col("doc.id"), F.col("doc.c0"), F.col("doc.c1")))], "lines")
    own = plain.select("*", *_identity(words, name[doc_id])[1:])
    own = own.select(*plain.columns, *[k.alias(f"r{i}") for i, k in enumerate(row(F.col(name[doc_id]), F.col("c0"), F.col("c1")))])
    # Equal rows are numbered by the partitioning that the join needs anyhow.
    both = own.withColumn("nth", F.row_number().over(Window.partitionBy("r0", "r1").orderBy(F.lit(0)))).join(gone, ["r0", "r1"], "left")
    split = F.split(F.col(words), "\n", -1)
    full = lambda lines: F.filter(F.transform(lines, lambda line, i: F.when(~line.rlike(BLANK), i)), lambda i: i.isNotNull())
    every = F.transform(F.array(full(split)), lambda at: F.when(F.size(at) >= width, at))[0]
    off = F.when(F.col("nth") == 1, F.col("lines")).otherwise(every)
    told = both.select(*plain.columns, off.alias("off"))
    stay = lambda lines: F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("off"))  # noqa: E731  by hashing, in linear time
    left = F.transform(F.array(split), lambda lines: F.array_join(F.transform(stay(lines), lambda i: lines[i]), "\n"))[0]
    text_left = F.when(F.col("off").isNull(), F.col(words)).otherwise(left)
    count = F.coalesce(F.greatest(F.size("off"), F.lit(0)), F.lit(0))
    kept = [c for c in docs.columns if c.lower() != "removed_lines"]
    return told.select(*[(text_left if c == text else F.col(name[c])).alias(c) for c in kept], count.alias("removed_lines"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = deduplicated(docs)
    return found.select("doc_id", F.col("removed_lines").cast("long").alias("n_removed"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


OP4_SQL = r"""
WITH d AS (SELECT doc_id, text, row_number() OVER () AS rid, substr(md5(coalesce(text, '')), 1, 30) AS c FROM documents),
l AS (SELECT rid, i - 1 AS spot, line FROM (SELECT rid, unnest(string_split(text, chr(10))) AS line, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS i FROM d WHERE text IS NOT NULL)),
c AS (SELECT rid, spot, line, row_number() OVER (PARTITION BY rid ORDER BY spot) AS k FROM l WHERE NOT regexp_full_match(line, '[\x20\x09-\x0D]*')),
w AS (SELECT a.rid, a.spot AS a0, b.spot AS a1, d.spot AS a2, a.line || chr(10) || b.line || chr(10) || d.line AS s
      FROM c a JOIN c b ON b.rid = a.rid AND b.k = a.k + 1 JOIN c d ON d.rid = a.rid AND d.k = a.k + 2),
r AS (SELECT w.*, row_number() OVER (PARTITION BY s ORDER BY d.doc_id NULLS FIRST, d.c, d.rid, a0) AS nth FROM w JOIN d USING (rid)),
g AS (SELECT DISTINCT rid, unnest([a0, a1, a2]) AS spot FROM r WHERE nth > 1),
k AS (SELECT l.rid, string_agg(l.line, chr(10) ORDER BY l.spot) AS kept FROM l ANTI JOIN g USING (rid, spot) GROUP BY l.rid),
n AS (SELECT rid, count(*) AS n FROM g GROUP BY rid)
SELECT d.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256
FROM d LEFT JOIN k USING (rid) LEFT JOIN n USING (rid)
"""
