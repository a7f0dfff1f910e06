"""The relational operators around the engine, as small queries on the given tables: each with SQL that must agree."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.sources.tables import load

QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {}


def _query(sql: str):
    def keep(f: Callable) -> Callable:
        QUERIES[f.__name__.removeprefix("q_")] = (f, sql)
        return f

    return keep


def _same(name: str, sql: str, *tables: str) -> None:
    """A query whose text both systems run."""

    def run(s: SparkSession, d: str) -> DataFrame:
        for t in tables:
            load(s, d, t).createOrReplaceTempView(t)
        return s.sql(sql)

    QUERIES[name] = (run, sql)


@_query("SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem WHERE l_quantity >= 49")
def q_scan_pruned(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_quantity").where("l_quantity >= 49").drop("l_quantity")


_same("filter_between", "SELECT p_partkey, p_size FROM part WHERE p_size BETWEEN 10 AND 12 AND p_brand LIKE 'Brand#%' AND p_type IS NOT NULL", "part")
_same("filter_in_case", "SELECT event_id, CASE WHEN event_type IN ('click', 'view') THEN 'seen' ELSE 'other' END AS kind FROM events WHERE user_id IN (1, 2, 3)", "events")


@_query("SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_nationkey = 3")
def q_join_broadcast(s: SparkSession, d: str) -> DataFrame:
    c = load(s, d, "customer", "c_custkey", "c_nationkey").where("c_nationkey = 3")
    return load(s, d, "orders", "o_orderkey", "o_custkey").join(c.hint("broadcast"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")


@_query("SELECT l_orderkey, l_linenumber, o_custkey FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def q_join_smj(s: SparkSession, d: str) -> DataFrame:
    o = load(s, d, "orders", "o_orderkey", "o_custkey")
    return load(s, d, "lineitem", "l_orderkey", "l_linenumber").join(o.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "o_custkey")


@_query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def q_join_semi(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "customer", "c_custkey").join(load(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


@_query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def q_join_anti(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "customer", "c_custkey").join(load(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@_query("""WITH a AS (SELECT l_partkey AS v, min(l_quantity)::BIGINT AS x FROM lineitem WHERE l_suppkey % 2 = 0 GROUP BY 1), b AS (SELECT l_partkey AS v, min(l_quantity)::BIGINT AS y FROM lineitem WHERE l_suppkey % 2 = 1 GROUP BY 1)
SELECT coalesce(a.v, b.v) AS v, least(coalesce(x, 999), coalesce(y, 999)) AS best FROM a FULL JOIN b ON a.v = b.v""")
def q_join_full_state(s: SparkSession, d: str) -> DataFrame:
    li = load(s, d, "lineitem", "l_partkey", "l_suppkey", "l_quantity")
    side = lambda odd, to: li.where(F.col("l_suppkey") % 2 == odd).groupBy(F.col("l_partkey").alias("v")).agg(F.min("l_quantity").cast("long").alias(to))
    return side(0, "x").join(side(1, "y"), "v", "full").select("v", F.least(F.coalesce("x", F.lit(999).cast("long")), F.coalesce("y", F.lit(999).cast("long"))).alias("best"))


@_query("SELECT a.n_nationkey AS a, b.r_regionkey AS b FROM nation a CROSS JOIN region b WHERE a.n_regionkey <> b.r_regionkey")
def q_join_cross_pairs(s: SparkSession, d: str) -> DataFrame:
    # Two tables of fixed size.
    pairs = load(s, d, "nation", "n_nationkey", "n_regionkey").crossJoin(load(s, d, "region", "r_regionkey"))
    return pairs.where("n_regionkey <> r_regionkey").select(F.col("n_nationkey").alias("a"), F.col("r_regionkey").alias("b"))


@_query("""WITH e AS (SELECT event_id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM events)
SELECT a.user_id, a.event_id AS x, b.event_id AS y FROM e a JOIN e b ON a.user_id = b.user_id AND b.r > a.r AND b.r <= a.r + 2""")
def q_join_range_window(s: SparkSession, d: str) -> DataFrame:
    e = load(s, d, "events", "event_id", "user_id", "ts").withColumn("r", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    a, b = e.alias("a"), e.alias("b")
    near = (F.col("b.r") > F.col("a.r")) & (F.col("b.r") <= F.col("a.r") + 2)
    return a.join(b, (F.col("a.user_id") == F.col("b.user_id")) & near).select(F.col("a.user_id"), F.col("a.event_id").alias("x"), F.col("b.event_id").alias("y"))


@_query("""SELECT o_orderkey, (SELECT max(e.event_id) FROM events e WHERE e.user_id = o.o_custkey % 150 AND e.ts = (SELECT max(f.ts) FROM events f WHERE f.user_id = o.o_custkey % 150 AND f.ts <= o.o_orderdate)) AS event_id FROM orders o""")
def q_join_asof_events(s: SparkSession, d: str) -> DataFrame:
    """The latest earlier event: both kinds of rows in one order, the last event carried along."""
    o = load(s, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select(F.pmod("o_custkey", F.lit(150)).alias("user"), F.col("o_orderdate").cast("timestamp").alias("t"), F.lit(1).alias("kind"), "o_orderkey", F.lit(None).cast("long").alias("event_id"))
    e = load(s, d, "events", "event_id", "user_id", "ts").select(F.col("user_id").cast("long").alias("user"), F.col("ts").cast("timestamp").alias("t"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("o_orderkey"), "event_id")
    w = Window.partitionBy("user").orderBy("t", "kind", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return o.unionByName(e).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w)).where("kind = 1").select("o_orderkey", "event_id")


@_query("SELECT a.event_id AS x, b.event_id AS y FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND epoch_us(b.ts) <= epoch_us(a.ts) + 3600000000")
def q_join_interval_events(s: SparkSession, d: str) -> DataFrame:
    """Within an hour: hours as keys, each row also under the hour before, the rest as a condition."""
    e = load(s, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = F.floor(F.col("us") / 3_600_000_000)
    a = e.select("user_id", F.col("event_id").alias("x"), F.col("us").alias("ua"), hour.alias("h"))
    b = e.select("user_id", F.col("event_id").alias("y"), F.col("us").alias("ub"), F.explode(F.array(hour, hour - 1)).alias("h"))
    return a.join(b, ["user_id", "h"]).where("x <> y AND ub >= ua AND ub <= ua + 3600000000").select("x", "y")


@_query("""WITH e AS (SELECT DISTINCT n_nationkey AS a, c_mktsegment AS b FROM customer JOIN nation ON c_nationkey = n_nationkey) SELECT x.a AS u, y.a AS v, count(*) AS shared FROM e x JOIN e y ON x.b = y.b AND x.a < y.a GROUP BY 1, 2""")
def q_self_join_shared(s: SparkSession, d: str) -> DataFrame:
    e = load(s, d, "customer", "c_nationkey", "c_mktsegment").distinct()
    x, y = e.alias("x"), e.alias("y")
    return x.join(y, (F.col("x.c_mktsegment") == F.col("y.c_mktsegment")) & (F.col("x.c_nationkey") < F.col("y.c_nationkey"))).groupBy(F.col("x.c_nationkey").alias("u"), F.col("y.c_nationkey").alias("v")).agg(F.count("*").alias("shared"))


_same("agg_hash", "SELECT l_suppkey, count(*) AS n, CAST(sum(l_quantity) AS BIGINT) AS q, min(l_partkey) AS lo, max(l_partkey) AS hi FROM lineitem GROUP BY l_suppkey", "lineitem")
_same("agg_rollup", "SELECT n_regionkey, c_nationkey, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, c_nationkey)", "customer", "nation")
_same("agg_cube", "SELECT c_mktsegment, c_nationkey % 5 AS g, count(*) AS n FROM customer GROUP BY CUBE (c_mktsegment, c_nationkey % 5)", "customer")
_same("agg_gsets", "SELECT p_brand, p_size % 4 AS g, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_size % 4), ())", "part")
_same("agg_minby", "SELECT l_suppkey, min(l_quantity) AS least, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY l_suppkey", "lineitem")
_same("reach_counts", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY l_suppkey", "lineitem")
_same("win_rank", "SELECT p_partkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS nt FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)".replace("row_number() OVER w", "row_number() OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey)"), "part")
_same("win_prefix", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS before FROM orders", "orders")
_same("win_range", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS near FROM part", "part")
_same("topk_per_group", "SELECT c_nationkey, c_custkey FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) t WHERE r <= 3", "customer")
_same("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", "customer", "supplier")
_same("set_intersect", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 40 INTERSECT SELECT l_partkey FROM lineitem WHERE l_quantity < 3", "lineitem")
_same("set_except", "SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem WHERE l_quantity > 45", "part", "lineitem")
_same("fn_math", "SELECT p_partkey, ceil(log2(p_size + 1)) AS bits, round(sqrt(p_size), 6) AS root, greatest(p_size, 10) AS least_ten FROM part".replace("ceil(log2(p_size + 1))", "CAST(ceil(log2(p_size + 1)) AS BIGINT)"), "part")


@_query("SELECT l_partkey AS src, list(DISTINCT l_suppkey ORDER BY l_suppkey) AS d FROM lineitem GROUP BY l_partkey".replace("list(DISTINCT l_suppkey ORDER BY l_suppkey) AS d", "array_to_string(list_sort(list(DISTINCT l_suppkey)), ',') AS near"))
def q_adjacency_lists(s: SparkSession, d: str) -> DataFrame:
    li = load(s, d, "lineitem", "l_partkey", "l_suppkey").distinct()
    return li.groupBy(F.col("l_partkey").alias("src")).agg(F.array_join(F.array_sort(F.collect_list("l_suppkey")), ",").alias("near"))


@_query("SELECT c_nationkey, count(*) FILTER (c_mktsegment = 'BUILDING') AS building, count(*) FILTER (c_mktsegment = 'MACHINERY') AS machinery FROM customer GROUP BY c_nationkey")
def q_agg_pivot(s: SparkSession, d: str) -> DataFrame:
    out = load(s, d, "customer", "c_nationkey", "c_mktsegment").groupBy("c_nationkey").pivot("c_mktsegment", ["BUILDING", "MACHINERY"]).count()
    return out.select("c_nationkey", F.coalesce("BUILDING", F.lit(0).cast("long")).alias("building"), F.coalesce("MACHINERY", F.lit(0).cast("long")).alias("machinery"))


@_query("SELECT floor(l_quantity / 5)::BIGINT AS bin, count(*) AS n FROM lineitem GROUP BY 1")
def q_dist_histogram(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem", "l_quantity").groupBy(F.floor(F.col("l_quantity") / 5).alias("bin")).agg(F.count("*").alias("n"))


@_query("SELECT p_partkey, p_size FROM part ORDER BY p_size DESC, p_partkey LIMIT 50")
def q_topk_global(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "part", "p_partkey", "p_size").orderBy(F.desc("p_size"), "p_partkey").limit(50)


@_query("SELECT event_id, json_extract(props, '$.k')::BIGINT AS k FROM events WHERE props IS NOT NULL")
def q_fn_json(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "events", "event_id", "props").where("props IS NOT NULL").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@_query("SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1")
def q_fn_time(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "orders", "o_orderdate").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count("*").alias("n"))


@_query("SELECT vec_id, round(list_sum([x * x FOR x IN embedding::DOUBLE[]]), 4) AS norm2, len([x FOR x IN embedding IF x > 0])::INTEGER AS positive FROM embeddings")
def q_fn_array(s: SparkSession, d: str) -> DataFrame:
    norm = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return load(s, d, "embeddings", "vec_id", "embedding").select("vec_id", F.round(norm, 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


@_query("""WITH l AS (SELECT l_partkey AS v, l_suppkey AS m, min(l_quantity)::BIGINT AS d FROM lineitem WHERE l_suppkey <= 3 GROUP BY 1, 2) SELECT a.v AS a, b.v AS b, min(a.d + b.d) AS upper FROM l a JOIN l b ON a.m = b.m AND b.v = a.v + 1 GROUP BY 1, 2""")
def q_fn_label_map(s: SparkSession, d: str) -> DataFrame:
    """Label queries without a join on landmarks: labels folded to maps."""
    li = load(s, d, "lineitem", "l_partkey", "l_suppkey", "l_quantity").where("l_suppkey <= 3").groupBy("l_partkey", "l_suppkey").agg(F.min("l_quantity").cast("long").alias("d"))
    maps = li.groupBy(F.col("l_partkey").alias("v")).agg(F.map_from_entries(F.collect_list(F.struct("l_suppkey", "d"))).alias("labels"))
    a, b = maps.select(F.col("v").alias("a"), F.col("labels").alias("la")), maps.select(F.col("v").alias("b"), F.col("labels").alias("lb"))
    both = a.join(b, F.col("b") == F.col("a") + 1)
    sums = F.filter(F.map_values(F.map_zip_with("la", "lb", lambda k, x, y: x + y)), lambda x: x.isNotNull())
    return both.select("a", "b", F.array_min(sums).alias("upper")).where("upper IS NOT NULL")


@_query("""WITH o AS (SELECT l_suppkey, l_partkey, sum(l_quantity)::BIGINT AS q FROM lineitem GROUP BY 1, 2),
p AS (SELECT l_suppkey, row_number() OVER w AS size, sum(q) OVER w AS volume, sum(q) OVER (PARTITION BY l_suppkey) AS total FROM o WINDOW w AS (PARTITION BY l_suppkey ORDER BY q DESC, l_partkey ROWS UNBOUNDED PRECEDING))
SELECT l_suppkey, min(size * 1000000 // least(volume, total - volume))::BIGINT AS best FROM p WHERE volume < total GROUP BY l_suppkey""")
def q_udaf_sweep(s: SparkSession, d: str) -> DataFrame:
    """The least ratio of size to volume, of the prefixes by falling quantity: a grouped aggregate over Arrow batches."""
    o = load(s, d, "lineitem", "l_suppkey", "l_partkey", "l_quantity").groupBy("l_suppkey", "l_partkey").agg(F.sum("l_quantity").cast("long").alias("q"))

    def sweep(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["q", "l_partkey"], ascending=[False, True])
        volume = rows["q"].cumsum().to_numpy()
        small = np.minimum(volume, volume[-1] - volume)
        fine = small > 0
        best = ((np.arange(1, len(rows) + 1) * 1_000_000)[fine] // small[fine]).min() if fine.any() else None
        return pd.DataFrame({"l_suppkey": rows["l_suppkey"].iloc[:1].to_numpy(), "best": [best]})

    return o.groupBy("l_suppkey").applyInPandas(sweep, "l_suppkey long, best long").where("best IS NOT NULL")


@_query("SELECT p_partkey, p_size * 3 + 1 AS priority FROM part")
def q_udf_priority(s: SparkSession, d: str) -> DataFrame:
    @F.pandas_udf("int")
    def priority(x: pd.Series) -> pd.Series:
        return x * 3 + 1

    return load(s, d, "part", "p_partkey", "p_size").select("p_partkey", priority("p_size").alias("priority"))


# Joins that the engine's own plans lean on


@_query("SELECT l_orderkey, l_linenumber, s_nationkey FROM lineitem JOIN supplier ON l_suppkey = s_suppkey")
def q_join_shuffle_hash(s: SparkSession, d: str) -> DataFrame:
    side = load(s, d, "supplier", "s_suppkey", "s_nationkey").hint("shuffle_hash")
    return load(s, d, "lineitem", "l_orderkey", "l_linenumber", "l_suppkey").join(side, F.col("l_suppkey") == F.col("s_suppkey")).select("l_orderkey", "l_linenumber", "s_nationkey")


@_query("""WITH e AS (SELECT DISTINCT l_suppkey AS a, l_partkey AS b FROM lineitem WHERE l_suppkey <= 30),
p AS (SELECT x.a AS u, y.a AS v FROM e x JOIN e y ON x.b = y.b AND x.a < y.a GROUP BY 1, 2 HAVING count(*) >= 2)
SELECT x.u AS a, x.v AS b, y.v AS c FROM p x JOIN p y ON x.v = y.u JOIN p z ON z.u = x.u AND z.v = y.v""")
def q_triangles(s: SparkSession, d: str) -> DataFrame:
    """Triples of suppliers that pairwise share at least two parts: every edge runs from the smaller id, so a triangle is found once."""
    e = load(s, d, "lineitem", "l_suppkey", "l_partkey").where("l_suppkey <= 30").distinct()
    x, y = e.select(F.col("l_suppkey").alias("u"), "l_partkey"), e.select(F.col("l_suppkey").alias("v"), "l_partkey")
    p = x.join(y, "l_partkey").where("u < v").groupBy("u", "v").agg(F.count("*").alias("n")).where("n >= 2").select("u", "v")
    wedge = p.select(F.col("u").alias("a"), F.col("v").alias("b")).join(p.select(F.col("u").alias("b"), F.col("v").alias("c")), "b")
    return wedge.join(p.select(F.col("u").alias("a"), F.col("v").alias("c")), ["a", "c"], "left_semi").select("a", "b", "c")


@_query("""WITH r AS (SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS k FROM orders),
e AS (SELECT least(a.k, b.k) AS lo, greatest(a.k, b.k) AS hi FROM (SELECT o_orderkey, o_custkey, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS nxt FROM orders) o JOIN r a ON a.o_orderkey = o.o_orderkey JOIN r b ON b.o_orderkey = o.nxt),
c AS (SELECT k FROM r WHERE k % 500 = 0)
SELECT c.k, count(*) AS crossing FROM c JOIN e ON e.lo <= c.k AND c.k < e.hi GROUP BY c.k""")
def q_join_range_sweep(s: SparkSession, d: str) -> DataFrame:
    """Edges across every 500th cut of a ranking: an edge is joined by the bins of 500 ranks that it spans, so the range is an equality."""
    from manyq.operators.partition import global_rank

    o = load(s, d, "orders", "o_orderkey", "o_custkey", "o_totalprice")
    r = global_rank(o.select("o_orderkey", "o_totalprice"), F.col("o_totalprice"), F.col("o_orderkey")).select("o_orderkey", (F.col("rank") + 1).alias("k"))
    nxt = o.withColumn("nxt", F.lead("o_orderkey").over(Window.partitionBy("o_custkey").orderBy("o_orderkey"))).where("nxt IS NOT NULL").select("o_orderkey", "nxt")
    e = nxt.join(r.withColumnRenamed("k", "a"), "o_orderkey").join(r.select(F.col("o_orderkey").alias("nxt"), F.col("k").alias("b")), "nxt").select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi"))
    spanned = e.where(F.ceil(F.col("lo") / 500) <= F.floor((F.col("hi") - 1) / 500)).select(F.explode(F.sequence(F.ceil(F.col("lo") / 500), F.floor((F.col("hi") - 1) / 500))).alias("bin"))
    return spanned.groupBy((F.col("bin") * 500).alias("k")).agg(F.count("*").alias("crossing"))


@_query("""SELECT n.n_nationkey, t.c_custkey FROM nation n, LATERAL (SELECT c_custkey FROM customer c WHERE c.c_nationkey = n.n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 2) t""")
def q_join_lateral(s: SparkSession, d: str) -> DataFrame:
    n, c = load(s, d, "nation", "n_nationkey"), load(s, d, "customer", "c_custkey", "c_nationkey", "c_acctbal")
    top = c.where(F.col("c_nationkey") == F.col("n_nationkey").outer()).orderBy(F.desc("c_acctbal"), "c_custkey").limit(2).select("c_custkey")
    return n.lateralJoin(top).select("n_nationkey", "c_custkey")


@_query("""WITH x AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS s FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
t AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY s DESC, dst) AS r FROM x) SELECT src, dst FROM t WHERE r <= 8""")
def q_knn_edges(s: SparkSession, d: str) -> DataFrame:
    """A stated set of query vectors against all, a block of queries at a time: only each block's best go on."""
    e = load(s, d, "embeddings", "vec_id", "embedding")
    q = e.where("vec_id % 50 = 0").select(F.col("vec_id").alias("src"), F.col("embedding").alias("x"))
    dot = F.round(F.aggregate(F.zip_with("x", "embedding", lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda a, b: a + b), 9)
    pairs = e.join(q.hint("broadcast"), F.col("vec_id") != F.col("src")).select("src", F.col("vec_id").alias("dst"), dot.alias("s"))  # a fiftieth of the ids, by statement
    return pairs.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("s"), "dst"))).where("r <= 8").select("src", "dst")


# Orders, sets, quantiles, times

_same("win_percent", "SELECT p_partkey, round(percent_rank() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS pr, round(cume_dist() OVER (PARTITION BY p_brand ORDER BY p_size), 6) AS cd FROM part", "part")
_same("set_intersect_all", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 40 INTERSECT ALL SELECT l_partkey FROM lineitem WHERE l_quantity < 20", "lineitem")
_same("set_except_all", "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity > 25 EXCEPT ALL SELECT l_suppkey FROM lineitem WHERE l_quantity < 10", "lineitem")
_same("set_union_all", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier", "customer", "supplier")


@_query("SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC, o_orderkey) - 1 AS place FROM orders")
def q_sort_global(s: SparkSession, d: str) -> DataFrame:
    """Places of a global order without one task that sees all rows."""
    from manyq.operators.partition import global_rank

    return global_rank(load(s, d, "orders", "o_orderkey", "o_totalprice"), -F.col("o_totalprice"), F.col("o_orderkey")).select("o_orderkey", F.col("rank").alias("place"))


@_query("SELECT l_suppkey, quantile_cont(l_quantity, 0.5) AS median, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY l_suppkey")
def q_agg_percentile(s: SparkSession, d: str) -> DataFrame:
    return load(s, d, "lineitem", "l_suppkey", "l_quantity").groupBy("l_suppkey").agg(F.percentile("l_quantity", 0.5).alias("median"), F.percentile("l_quantity", 0.9).alias("p90"))


@_query("""WITH x AS (SELECT l_suppkey % 4 AS g, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1) SELECT g, n, true AS sketch_near, true AS approx_near FROM x""")
def q_agg_sketches(s: SparkSession, d: str) -> DataFrame:
    """Distinct counts exactly, by HyperLogLog++, and by a sketch merged from two halves."""
    li = load(s, d, "lineitem", "l_suppkey", "l_partkey", "l_linenumber").withColumn("g", F.col("l_suppkey") % 4)
    exact = li.groupBy("g").agg(F.count_distinct("l_partkey").alias("n"), F.approx_count_distinct("l_partkey", 0.02).alias("a"))
    halves = li.groupBy("g", F.col("l_linenumber") % 2).agg(F.hll_sketch_agg("l_partkey", 12).alias("h")).groupBy("g").agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("k"))
    near = lambda c: F.abs(F.col(c) - F.col("n")) <= 0.08 * F.col("n")
    return exact.join(halves, "g").select("g", "n", near("k").alias("sketch_near"), near("a").alias("approx_near"))


@_query("SELECT event_id, date_trunc('hour', ts)::TIMESTAMP AS hour, (epoch_us(ts) // 86400000000)::BIGINT AS day, ((epoch_us(ts) + 5400000000) // 3600000000)::BIGINT AS later FROM events")
def q_fn_interval(s: SparkSession, d: str) -> DataFrame:
    e = load(s, d, "events", "event_id", "ts")
    return e.select("event_id", F.date_trunc("hour", "ts").alias("hour"), F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 86_400_000_000).alias("day"), F.floor(F.unix_micros((F.col("ts") + F.expr("INTERVAL 90 MINUTES")).cast("timestamp")) / 3_600_000_000).alias("later"))
