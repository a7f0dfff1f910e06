import math
import random

from pyspark.sql import functions as F

from manyq.llm import nearest


def vectors(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>")


def test_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, [0.5, 0.5]), (2, [0.5, 0.5]), (3, None), (4, []), (5, [0.0, 0.0]), (6, [math.nan, 1.0]), (7, [math.inf, 1.0]), (8, [None, 1.0]), (9, [1.0, 2.0, 3.0]), (None, [1.0, 1.0]), (20, [-1.0, 0.2]), (2, [0.5, 0.5])]
    got = nearest.search(vectors(spark, rows), F.col("vec_id") % 20 == 0, k=3).orderBy("query_id", "rank").collect()
    assert [(r["query_id"], r["rank"], r["vec_id"]) for r in got] == [(0, 1, 1), (0, 2, 2), (0, 3, 20), (20, 1, 1), (20, 2, 2), (20, 3, 0)]
    assert nearest.search(vectors(spark, rows[3:5]), F.col("vec_id") % 20 == 0).count() == 0


def test_recall_and_ties(spark):
    rng = random.Random(4)
    rows = [(i, [rng.gauss(0, 1) for _ in range(16)]) for i in range(1200)] + [(i, [0.25] * 16) for i in range(1200, 1500)]
    df = vectors(spark, rows).cache()
    query = F.col("vec_id") % 50 == 0
    got = nearest.search(df, query, k=10, trees=6, leaf_rows=200)
    want = {(r["query_id"], r["vec_id"]) for r in nearest.exact(df, query, 10).collect()}
    found = {(r["query_id"], r["vec_id"]) for r in got.collect()}
    assert len(found & want) / len(want) >= 0.9
    same = [r["vec_id"] for r in got.where("query_id = 1250").orderBy("rank").collect()]
    assert len(same) == 10 and all(a < b for a, b in zip(same, same[1:], strict=False) if a >= 1200 and b >= 1200)


def test_registered_search_against_the_full_scan(spark):
    """The query's own settings at sf0.1: recall, and distinct rows looked at."""
    sf = "/root/testdata/sf0.1"
    got = nearest.op7_nearest(spark, sf).collect()
    want = {(r["query_id"], r["vec_id"]) for r in nearest.exact(spark.read.parquet(f"{sf}/embeddings.parquet"), F.col("vec_id") % 20 == 0).collect()}
    assert len({(r["query_id"], r["vec_id"]) for r in got} & want) / len(want) >= 0.9
    looked = {r["query_id"]: r["looked"] for r in got}
    assert 0.5 * 2000 < max(looked.values()) < 0.85 * 2000 and sum(looked.values()) / len(looked) < 0.8 * 2000
    assert nearest.search(vectors(spark, []), F.col("vec_id") % 20 == 0).count() == 0


def test_pipeline_stages(spark):
    import corpus_pipeline as c

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    schema, before = docs.schema, docs.count()
    for name, stage in c.STAGES[:-1]:
        docs = c.materialise(stage(spark, docs, sf), name)
        assert docs.schema == schema and 0.8 * before <= docs.count() <= before, name
    pieces = c.STAGES[-1][1](spark, docs, sf)
    assert pieces.where("start = 0").count() == docs.count() == c.run(spark, sf).where("start = 0").count()


def test_pipeline_rows_against_brute_force(spark, tmp_path):
    """Toxicity, line dedup and near dedup with the stages' own settings, on real rows."""
    import duckdb
    import numpy as np

    import corpus_pipeline as c
    from manyq.llm import line_dedup, near_dedup, toxicity

    sf, stages = "/root/testdata/sf0.001", dict(c.STAGES)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    machine = toxicity.learn(docs, spark.read.parquet(f"{sf}/labels.parquet"))

    def margin(text):
        terms = toxicity.term_lists([(text or "").encode()])[0]
        x = machine.values[terms].astype(float)
        v = x[:, None] * machine.vectors[terms]
        return machine.bias + x @ machine.weights[terms] + np.triu(v @ v.T, 1).sum()

    before = docs.collect()
    want = {r["doc_id"] for r in before if 1 / (1 + math.exp(-margin(r["text"]))) < toxicity.THRESHOLD}
    docs = c.materialise(stages["toxicity"](spark, docs, sf), "t-toxicity")
    assert {r["doc_id"] for r in docs.collect()} == want and 0 < len(want) < len(before)

    def brute(frame, name, sql):
        frame.toPandas().to_parquet(str(tmp_path / name))
        con = duckdb.connect()
        con.execute(f"CREATE VIEW given AS SELECT * FROM '{tmp_path / name}'")
        return con.execute(sql).fetchall()

    kept = dict(brute(docs, "a.parquet", "WITH " + line_dedup.LINES_SQL.format(name="x", docs="given") + " SELECT doc_id, kept FROM x_out"))
    docs = c.materialise(stages["line_dedup"](spark, docs, sf), "t-lines")
    assert {r["doc_id"]: r["text"] for r in docs.collect()} == kept
    # Few near copies are left after the lines; the stage also has to agree on the documents as given.
    given = spark.read.parquet(f"{sf}/documents.parquet")
    for name, frame in (("b.parquet", docs), ("c.parquet", given)):
        least = brute(frame, name, "WITH RECURSIVE " + near_dedup.groups_sql("given", 5, 80, "x") + " SELECT doc_id FROM x_least WHERE doc_id = component_id")
        left = {r["doc_id"] for r in stages["near_dedup"](spark, frame, sf).collect()}
        assert left == {r[0] for r in least}
    assert len(left) < given.count()
