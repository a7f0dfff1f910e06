from pyspark.sql import functions as F

from manyq import sqlapi
from manyq.functions import ids
from manyq.operators.blocks import blocked
from manyq.plans.kernels import Relax
from manyq.sources import datasource, graphs, tables
from manyq.sources.graphs import Graph
from manyq.streaming import requests, windows


def test_edges_round_trip(spark, tmp_path):
    edges = spark.createDataFrame([(1, 2, 3), (1, 4, 1), (2, 1, 3)], "src long, dst long, w long")
    for fmt in ("csv", "json", "orc", "parquet", "text"):
        tables.write_edges(edges, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, tables.read_edges(spark, str(tmp_path / fmt), fmt).collect())) == sorted(map(tuple, edges.collect()))


def test_bucketed_blocks_prune(spark):
    g = Graph(spark.createDataFrame([(i, i + 1) for i in range(20)], "x long, y long"))
    bg = blocked(g, parts=4)
    spark.sql("DROP TABLE IF EXISTS blocks_t")
    tables.save_blocked(bg.blocks, "blocks_t", 4)
    some = tables.load_blocked(spark, "blocks_t", [1])
    assert some.count() == 1 and "PushedFilters: [In(part_id" in some._jdf.queryExecution().toString() or "EqualTo(part_id" in some._jdf.queryExecution().toString()
    spark.sql("DROP TABLE blocks_t")


def test_scan_reads_named_columns(spark):
    plan = tables.load(spark, "/root/testdata/sf0.001", "lineitem", "l_partkey", "l_suppkey").where("l_partkey < 5")._jdf.queryExecution().toString()
    assert "ReadSchema: struct<l_partkey:bigint,l_suppkey:bigint>" in plan and "LessThan(l_partkey,5)" in plan


def test_synthetic_source(spark):
    datasource.register(spark)
    read = lambda **o: spark.read.format("manyq_graph").options(**o).load()
    assert read(kind="grid", n=5).count() == 40
    assert read(kind="ring", n=7).count() == 7
    assert read(kind="star", n=9).count() == 8


def test_table_functions(spark):
    sqlapi.register(spark)
    spark.createDataFrame([(1, 2, 5), (2, 3, 1), (1, 3, 9)], "src long, dst long, w long").createOrReplaceTempView("e")
    got = spark.sql("SELECT v, dist FROM graph_sssp(TABLE(e) WITH SINGLE PARTITION, 1)").collect()
    assert sorted(map(tuple, got)) == [(1, 0), (2, 5), (3, 6)]


def test_request_stream_matches_batch(spark, tmp_path):
    g = Graph(spark.createDataFrame([(i, i + 1) for i in range(6)], "x long, y long"), unit=True)
    bg = blocked(g, parts=2)
    spark.createDataFrame([(0,), (3,)], "src long").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("src long").parquet(str(tmp_path / "in"))
    requests.serve_requests(stream, bg, Relax(True), str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out")).where("src = 3").select("v", F.col("num").cast("int")).collect()
    assert sorted(map(tuple, got)) == [(v, abs(v - 3)) for v in range(7)]


def test_windows_on_a_stream(spark, tmp_path):
    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))
    events.write.parquet(str(tmp_path / "ev"))
    stream = windows.tumbling(spark.readStream.schema(events.schema).parquet(str(tmp_path / "ev")))
    q = stream.writeStream.outputMode("complete").format("memory").queryName("w").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert sorted(map(str, spark.sql("SELECT * FROM w").collect())) == sorted(map(str, windows.tumbling(events).collect()))


def _held(spark, sf_dir):
    docs, items = (spark.read.parquet(f"{sf_dir}/{name}.parquet") for name in ("documents", "benchmark"))
    both = docs.select("doc_id", "text").crossJoin(F.broadcast(items.select("item_id", F.col("text").alias("passage"))))
    rows = both.where(F.contains("text", "passage")).select((F.lit(ids.DOCUMENT * ids.SPACE) + F.col("doc_id")).alias("x"), (F.lit(ids.ITEM * ids.SPACE) + F.col("item_id")).alias("y"))
    return {tuple(r) for r in rows.distinct().collect()}


def test_citation_finds_every_passage(spark, tmp_path):
    """Against contains: on the given table, and on passages that are short or meet other characters at their edges."""
    texts = ['He said "one two three\nfour five six seven" twice', "one two", "(one) two,  three\nfour five six seven eight", "ab\n\nc de", "", None, "one two three four five six seven"]
    passages = ["one two three\nfour five six seven", "two three\nfour five six sev", "one", "two", "e t", "b\n\nc d", " two", "\nfour five ", "", None, "three four five", "two,  three\nfour five six seven eight"]
    for name, key, rows in (("documents", "doc_id", texts), ("benchmark", "item_id", passages)):
        spark.createDataFrame(list(enumerate(rows)), f"{key} long, text string").write.parquet(str(tmp_path / f"{name}.parquet"))
    for sf_dir in (str(tmp_path), "/root/testdata/sf0.1"):
        want = _held(spark, sf_dir)
        assert want and {tuple(r) for r in graphs.citation(spark, sf_dir).pairs.collect()} == want
