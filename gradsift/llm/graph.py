"""Connected components of an edge table, without a graph on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradsift.llm.staging import Stage


def components(edges: DataFrame, stage: Stage, src: str = "a", dst: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, comp): comp is the smallest node reachable. Nodes without an edge are left out.

    Alternating star steps: each node's neighbours are tied to the smallest of them, first
    the larger ones and then the smaller ones, until nothing changes. A round is two
    aggregations with map-side minima and two joins on the node, which Spark can split where
    one node has very many edges.
    """
    now = stage.put(
        edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).where("u <> v").distinct()
    )
    before = None
    for _ in range(max_rounds):
        state = now.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("u", "v"))).first()
        if tuple(state) == before or not state[0]:
            break
        before = tuple(state)
        # large star: the larger neighbours of a node go to the least of it and its neighbours
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        # small star: a node and its smaller neighbours go to the least of them
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        new = stage.put(small)
        stage.drop(now)
        now = new
    else:
        raise RuntimeError("the components did not settle")
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct()
    return now.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("comp")).unionByName(roots)
