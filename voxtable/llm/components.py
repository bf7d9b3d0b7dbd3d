"""Connected components of an edge table, by contraction.

Each round every node joins the neighbour (or itself) of lowest priority in that round's seeded order, edges are
relabelled, loops and repeats go. Random priorities shrink paths and stars alike, so rounds grow with the logarithm of
the nodes. All state is in written tables; the driver sees only whether edges are left. A forest whose parents are known needs no contraction: its
paths are halved.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from voxtable.llm.common import cut


def component_roots(edges: DataFrame) -> DataFrame:
    """edges (a, b) of longs -> (node, root), one row for each node of an edge; root is some node of its component."""
    edges = cut(edges.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct())
    rounds: list[DataFrame] = []
    while not edges.isEmpty():
        both = edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        order = lambda c: F.struct(F.xxhash64(F.lit(len(rounds)), c).alias("h"), c.alias("n"))
        joined = both.groupBy("a").agg(F.min(order(F.col("b"))).alias("lowest"))
        joined = cut(joined.select(F.col("a").alias("node"), F.least(F.col("lowest"), order(F.col("a")))["n"].alias("to")))
        edges = (
            edges.join(joined.select(F.col("node").alias("a"), F.col("to").alias("x")), "a")
            .join(joined.select(F.col("node").alias("b"), F.col("to").alias("y")), "b")
            .filter("x <> y")
            .select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
            .distinct()
        )
        edges = cut(edges)
        rounds.append(joined)
    if not rounds:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    labels = rounds[0].select("node", F.col("to").alias("root"))
    for n, moved in enumerate(rounds[1:]):
        labels = labels.join(moved.withColumnRenamed("node", "root"), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
        if n % 4 == 3:
            labels = cut(labels)
    return cut(labels)


def forest_roots(parents: DataFrame) -> DataFrame:
    """parents (a, b) of longs, each b once and a < b -> (node, root), one row for each node; paths halve with every round."""
    ups = cut(parents.select(F.col("b").alias("node"), F.col("a").alias("root"), F.lit(True).alias("moved")))
    tops = ups.select(F.col("root").alias("node")).distinct().join(ups, "node", "left_anti").withColumn("root", F.col("node"))
    out = tops.select("node", "root")
    while not ups.filter("moved").isEmpty():
        above = ups.select(F.col("node").alias("root"), F.col("root").alias("next"))
        ups = cut(ups.join(above, "root", "left").select("node", F.coalesce("next", "root").alias("root"), F.col("next").isNotNull().alias("moved")))
    return out.unionAll(ups.select("node", "root"))
