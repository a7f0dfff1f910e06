"""Graphs made from the given tables, each as DataFrame and as SQL: edges (src, dst, w) both ways, vertices (id, deg, ord)."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from manyq.functions import ids
from manyq.functions.ids import vertex
from manyq.sources.tables import epoch, load


@dataclass
class Graph:
    """Directed edges with weights from pairs of vertices. ord is the order in which neighbourhoods are kept together by the chunk partitioner."""

    pairs: DataFrame  # x, y
    orders: DataFrame | None = None  # id, ord
    directed: bool = False
    unit: bool = False
    name: str = "graph"
    _cache: dict = field(default_factory=dict)

    @cached_property
    def links(self) -> DataFrame:
        """(src, dst), distinct, no loops."""
        return symmetrise(self.pairs) if not self.directed else self.pairs.where("x <> y").select(F.col("x").alias("src"), F.col("y").alias("dst")).distinct()

    @cached_property
    def n_vertices(self) -> int:
        return self.links.select(F.col("src").alias("id")).union(self.links.select("dst")).distinct().count()

    @cached_property
    def edges(self) -> DataFrame:
        return self.links.withColumn("w", F.lit(1).cast("long") if self.unit else ids.weight(F.col("src"), F.col("dst"), self.n_vertices))

    @cached_property
    def vertices(self) -> DataFrame:
        out = self.links.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("deg"))
        if self.directed:
            out = out.join(self.links.select(F.col("dst").alias("id")).distinct(), "id", "full").select("id", F.coalesce("deg", F.lit(0).cast("long")).alias("deg"))
        if self.orders is None:
            return out.withColumn("ord", F.col("id"))
        return out.join(self.orders, "id", "left").select("id", "deg", F.coalesce("ord", "id").alias("ord"))


def settled(g: Graph) -> Graph:
    """g with its links and vertices written once, so that plans, weights and sources do not derive them from the tables again."""
    if not g._cache.get("settled"):
        g.__dict__["links"] = epoch(g.links, "links")
        g.__dict__.pop("vertices", None)
        g.__dict__["vertices"] = epoch(g.vertices, "vertices")
        if "edges" in g.__dict__ and not g._cache.get("own_edges"):
            g.__dict__.pop("edges")
        g.__dict__.setdefault("n_vertices", g.vertices.count())
        g._cache["settled"] = True
    return g


def symmetrise(pairs: DataFrame) -> DataFrame:
    """Both directions of (x, y), once each, without loops; copies are found in one direction, so half the rows are exchanged."""
    one = pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).where("a <> b").distinct()
    way = lambda src, dst: F.struct(F.col(src).alias("src"), F.col(dst).alias("dst"))
    return one.select(F.inline(F.array(way("a", "b"), way("b", "a"))))


def reached(g: Graph, sources: DataFrame, most_sent: int = 2_000_000) -> Graph:
    """The part of g that can be reached from sources (query_id, src): its vertices with all their links, degrees and weights as in g.

    What only follows links from the sources finds the same there as in g. Every step reads all links once, so this is for
    graphs of few steps. A step's new vertices are sent to all executors while they are at most most_sent, else exchanged.
    """
    settled(g)
    fresh = epoch(sources.select(F.col("src").alias("id")).distinct(), "reached")
    seen, known, new = fresh, 0, fresh.count()
    sent = lambda ids, n: F.broadcast(ids) if n <= most_sent else ids
    while new and known + new < g.n_vertices:
        known += new
        found = g.links.join(sent(fresh.withColumnRenamed("id", "src"), new), "src", "left_semi").select(F.col("dst").alias("id")).distinct()
        fresh = epoch(found.join(sent(seen, known), "id", "left_anti"), "reached")
        seen, new = seen.unionByName(fresh), fresh.count()
    if known + new >= g.n_vertices:
        return g
    out = Graph(g.pairs, g.orders, g.directed, g.unit, f"{g.name}-reached")
    own = sent(seen, known)
    links = epoch(g.links.join(own.withColumnRenamed("id", "src"), "src", "left_semi"), "links")
    edges = links.withColumn("w", F.lit(1).cast("long") if g.unit else ids.weight(F.col("src"), F.col("dst"), g.n_vertices))
    out.__dict__.update(links=links, edges=edges, vertices=epoch(g.vertices.join(own, "id", "left_semi"), "vertices"), n_vertices=known)
    out._cache.update(settled=True, own_edges=True)
    return out


def event_grid(spark: SparkSession, sf_dir: str) -> Graph:
    """Road-like: a user's events in a row, every fourth tied to the next user's event of that rank."""
    by_user = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, sf_dir, "events", "event_id", "user_id", "ts").withColumn("k", F.row_number().over(by_user) - 1)
    e = e.select(vertex(ids.EVENT, F.col("event_id")).alias("id"), F.col("user_id").cast("long").alias("user"), "k")
    chain = e.withColumn("y", F.lead("id").over(Window.partitionBy("user").orderBy("k"))).where("y IS NOT NULL").select(F.col("id").alias("x"), "y")
    right = e.select(F.col("id").alias("y"), (F.col("user") - 1).alias("user"), "k")
    rung = e.where("k % 4 = 1").join(right, ["user", "k"]).select(F.col("id").alias("x"), "y")
    return Graph(chain.unionByName(rung), e.select("id", (F.col("user") * 1_000_000 + F.col("k")).cast("long").alias("ord")), name="event_grid")


def supply(spark: SparkSession, sf_dir: str) -> Graph:
    """Dense: parts and their suppliers."""
    li = load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey")
    return Graph(li.select(vertex(ids.PART, F.col("l_partkey")).alias("x"), vertex(ids.SUPPLIER, F.col("l_suppkey")).alias("y")).distinct(), name="supply")


def copurchase(spark: SparkSession, sf_dir: str) -> Graph:
    """Dense: parts bought in one order."""
    a = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").select("l_orderkey", vertex(ids.PART, F.col("l_partkey")).alias("x")).distinct()
    return Graph(a.join(a.select("l_orderkey", F.col("x").alias("y")), "l_orderkey").where("x < y").select("x", "y").distinct(), name="copurchase")


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Social: customers and the suppliers they bought from."""
    li = load(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey")
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    both = li.join(o, li["l_orderkey"] == o["o_orderkey"])
    return Graph(both.select(vertex(ids.CUSTOMER, F.col("o_custkey")).alias("x"), vertex(ids.SUPPLIER, F.col("l_suppkey")).alias("y")), name="trade")


def hyperlink(spark: SparkSession, sf_dir: str) -> Graph:
    """Web: pages and the targets of their links; several components."""
    found = load(spark, sf_dir, "pages", "page_id", "html").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]+)"'), F.lit(1))).alias("token")).distinct()
    # Targets are numbered in their order: by ranges of their first bytes, as a number.
    from manyq.operators.partition import global_rank

    start = F.conv(F.rpad(F.hex(F.substring(F.col("token").cast("binary"), 1, 6)), 12, "0"), 16, 10).cast("double")
    token = global_rank(found.select("token").distinct(), start, F.col("token")).withColumn("rank", F.col("rank") + 1)
    return Graph(found.join(token, "token").select(vertex(ids.PAGE, F.col("page_id")).alias("x"), vertex(ids.TOKEN, F.col("rank")).alias("y")), name="hyperlink")


def order_timeline(spark: SparkSession, sf_dir: str, directed: bool = False) -> Graph:
    """Citation-like: an order to the customer's next, and to the day's next; directed it has no cycles."""
    o = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    by_customer = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    by_day = Window.partitionBy("o_orderdate").orderBy("o_orderkey")
    pairs = o.select("o_orderkey", F.lead("o_orderkey").over(by_customer).alias("y")).unionByName(o.select("o_orderkey", F.lead("o_orderkey").over(by_day).alias("y")))
    pairs = pairs.where("y IS NOT NULL").select(vertex(ids.ORDER, F.col("o_orderkey")).alias("x"), vertex(ids.ORDER, F.col("y")).alias("y"))
    return Graph(pairs.distinct(), directed=directed, name="order_timeline")


def geo_tree(spark: SparkSession, sf_dir: str) -> Graph:
    """Trees: regions, nations, their customers and suppliers."""
    n = load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    c, s = load(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    pairs = n.select(vertex(ids.REGION, F.col("n_regionkey")).alias("x"), vertex(ids.NATION, F.col("n_nationkey")).alias("y"))
    pairs = pairs.unionByName(c.select(vertex(ids.NATION, F.col("c_nationkey")).alias("x"), vertex(ids.CUSTOMER, F.col("c_custkey")).alias("y")))
    return Graph(pairs.unionByName(s.select(vertex(ids.NATION, F.col("s_nationkey")).alias("x"), vertex(ids.SUPPLIER, F.col("s_suppkey")).alias("y"))), name="geo_tree")


def _runs(parts: str, k: int):
    """All runs of k elements of an array column, each joined by blanks."""
    return F.transform(F.sequence(F.lit(1), F.size(parts) - k + 1), lambda i: F.array_join(F.slice(parts, i, k), " "))


def citation(spark: SparkSession, sf_dir: str, words: int = 6) -> Graph:
    """Documents and the benchmark passages they hold: joined on a passage's words, then compared whole.

    The first and the last piece of a passage may meet other characters in a document, so keys are made of the pieces
    between; passages with fewer than `words` of these have shorter keys, and those with none are compared with all documents.
    """
    pieces = lambda c: F.split(c, "[ \n]+")
    b = load(spark, sf_dir, "benchmark", "item_id", "text").select("item_id", F.col("text").alias("passage")).where("item_id IS NOT NULL AND passage IS NOT NULL")
    inner = b.withColumn("inner", F.slice(pieces("passage"), 2, F.greatest(F.size(pieces("passage")) - 2, F.lit(0))))
    keyed = inner.select("item_id", F.least(F.size("inner"), F.lit(words)).alias("k"), F.array_join(F.slice("inner", 1, words), " ").alias("key"))
    d = load(spark, sf_dir, "documents", "doc_id", "text").where("doc_id IS NOT NULL")
    split = d.select("doc_id", pieces("text").alias("parts"))
    near = d.select("doc_id").limit(0).join(b.select("item_id"))
    for (k,) in keyed.select("k").where("k > 0").distinct().collect():  # at most `words` lengths
        own = split.where(F.size("parts") >= k).select("doc_id", F.explode(F.array_distinct(_runs("parts", k))).alias("key"))
        near = near.unionByName(own.join(keyed.where(F.col("k") == k), "key").select("doc_id", "item_id"))
    hit = d.join(near.distinct(), "doc_id").join(b, "item_id").where(F.contains("text", "passage")).select("doc_id", "item_id")
    bare = b.join(keyed.where("k = 0").select("item_id"), "item_id", "left_semi")
    hit = hit.unionByName(d.join(bare, F.contains("text", "passage")).select("doc_id", "item_id"))
    return Graph(hit.select(vertex(ids.DOCUMENT, F.col("doc_id")).alias("x"), vertex(ids.ITEM, F.col("item_id")).alias("y")).distinct(), name="citation")


BUILDERS = {f.__name__: f for f in (event_grid, supply, copurchase, trade, hyperlink, order_timeline, geo_tree, citation)}

S = ids.SPACE
PAIRS_SQL = {
    "event_grid": f"""
ev AS (SELECT {ids.EVENT * S} + event_id AS id, user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS k FROM events),
pairs AS (SELECT a.id AS x, b.id AS y FROM ev a JOIN ev b ON b.user_id = a.user_id AND b.k = a.k + 1
  UNION SELECT a.id, b.id FROM ev a JOIN ev b ON b.user_id = a.user_id + 1 AND b.k = a.k WHERE a.k % 4 = 1)""",
    "supply": f"pairs AS (SELECT DISTINCT {ids.PART * S} + l_partkey AS x, {ids.SUPPLIER * S} + l_suppkey AS y FROM lineitem)",
    "copurchase": f"pairs AS (SELECT DISTINCT {ids.PART * S} + a.l_partkey AS x, {ids.PART * S} + b.l_partkey AS y FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey)",
    "trade": f"pairs AS (SELECT DISTINCT {ids.CUSTOMER * S} + o_custkey AS x, {ids.SUPPLIER * S} + l_suppkey AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey)",
    "hyperlink": f"""
found AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="/([^"]+)"', 1)) AS token FROM pages),
ranked AS (SELECT page_id, dense_rank() OVER (ORDER BY encode(token)) AS r FROM found),
pairs AS (SELECT {ids.PAGE * S} + page_id AS x, {ids.TOKEN * S} + r AS y FROM ranked)""",
    "order_timeline": f"""
nexts AS (SELECT o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS b FROM orders
  UNION SELECT o_orderkey, lead(o_orderkey) OVER (PARTITION BY o_orderdate ORDER BY o_orderkey) FROM orders),
pairs AS (SELECT {ids.ORDER * S} + a AS x, {ids.ORDER * S} + b AS y FROM nexts WHERE b IS NOT NULL)""",
    "geo_tree": f"""
pairs AS (SELECT {ids.REGION * S} + n_regionkey AS x, {ids.NATION * S} + n_nationkey AS y FROM nation
  UNION ALL SELECT {ids.NATION * S} + c_nationkey, {ids.CUSTOMER * S} + c_custkey FROM customer
  UNION ALL SELECT {ids.NATION * S} + s_nationkey, {ids.SUPPLIER * S} + s_suppkey FROM supplier)""",
    "citation": f"pairs AS (SELECT {ids.DOCUMENT * S} + doc_id AS x, {ids.ITEM * S} + item_id AS y FROM documents d JOIN benchmark b ON contains(d.text, b.text))",
}


def graph_sql(name: str, unit: bool = False, directed: bool = False) -> str:
    """Common tables: pairs, e (src, dst, w), v (id, deg)."""
    both = "SELECT x AS src, y AS dst FROM pairs" + ("" if directed else " UNION SELECT y, x FROM pairs")
    w = "1" if unit else f"1 + (least(src % {S}, dst % {S}) * 7919 + greatest(src % {S}, dst % {S}) * 104729) % (SELECT greatest(1, ceil(log2(greatest(2, n)))::BIGINT - 1) FROM nv)"
    return f"""{PAIRS_SQL[name]},
l AS MATERIALIZED (SELECT DISTINCT src::BIGINT AS src, dst::BIGINT AS dst FROM ({both}) WHERE src <> dst),
nv AS MATERIALIZED (SELECT count(*) AS n FROM (SELECT src FROM l UNION SELECT dst FROM l)),
e AS MATERIALIZED (SELECT src, dst, ({w})::BIGINT AS w FROM l),
v AS MATERIALIZED (SELECT id, sum(d)::BIGINT AS deg FROM (SELECT src AS id, 1 AS d FROM l UNION ALL SELECT dst, 0 FROM l) GROUP BY id)"""
