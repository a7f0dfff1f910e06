"""Small graphs with known answers; undirected, unit weights."""

from manyq.operators.blocks import BlockedGraph, blocked
from manyq.sources.graphs import Graph

YIELDING = ("A-B B-C C-H H-E E-D E-F B-D", {0: "ABCEH", 1: "DF"})
TWO_QUERIES = ("A-B A-C B-D D-E E-F F-G G-H I-J J-K K-L J-B L-M M-N N-O O-H", {0: "ABCD", 1: "EFGH", 2: "IJKL", 3: "MNO"})
SCHEDULES = ("A-F A-J A-K B-F C-F C-I D-H D-L E-K E-L F-I F-J G-L H-K H-L I-K J-L", {0: "ABC", 1: "DEF", 2: "GHI", 3: "JKL"})


def build(spark, edges: str, parts: dict[int, str], name: str = "fixture") -> BlockedGraph:
    pairs = [tuple(map(ord, e.split("-"))) for e in edges.split()]
    g = Graph(spark.createDataFrame(pairs, "x long, y long"), unit=True, name=name)
    plan = [(ord(v), p) for p, own in parts.items() for v in own]
    return blocked(g, spark.createDataFrame(plan, "id long, part_id int"))


def sources(spark, names: str):
    return spark.createDataFrame([(i, ord(v)) for i, v in enumerate(names)], "query_id int, src long")


def lengths(result) -> dict[int, str]:
    out: dict[int, list] = {}
    for r in result.state.collect():
        out.setdefault(r["query_id"], []).append((chr(r["v"]), int(r["num"])))
    return {q: " ".join(f"{v}{d}" for v, d in sorted(x)) for q, x in out.items()}
