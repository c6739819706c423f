"""Connected components of an edge table by randomised contraction.

Each round every node moves to the closed neighbour with the least random priority, edges are renamed to the new
names and loops vanish. The image of a round shrinks by a constant factor in expectation, whatever the graph's shape
(paths, stars, cliques), so the number of rounds is logarithmic. All per-node work is a map-side combined minimum,
hence a hub with millions of neighbours never meets in one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsim.scratch import Scratch


def connected_components(edges: DataFrame, src: str = "a", dst: str = "b", max_rounds: int = 64) -> DataFrame:
    """``(node BIGINT, component BIGINT)`` for every node that has an edge; component = least node id in it.

    Null endpoints and loops are ignored, repeated edges count once. An empty edge table gives an empty result.
    """
    spark = edges.sparkSession
    scratch = Scratch(spark, "components")
    live = edges.select(F.col(src).cast("long").alias("a"), F.col(dst).cast("long").alias("b"))
    live = live.filter("a IS NOT NULL AND b IS NOT NULL AND a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    live = scratch.save(live, "edges0")
    layers: list[DataFrame] = []
    for k in range(max_rounds):
        if live.isEmpty():
            break
        rank = lambda c, k=k: F.struct(F.xxhash64(F.col(c), F.lit(k)).alias("p"), F.col(c).alias("n"))
        both = live.select(F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("e")).select("e.a", "e.b")
        best = both.groupBy("a").agg(F.min(rank("b")).alias("m"))
        layer = scratch.save(best.select(F.col("a").alias("old"), F.least("m", rank("a"))["n"].alias("new")), f"layer{k}")
        layers.append(layer)
        left = layer.select(F.col("old").alias("a"), F.col("new").alias("na"))
        right = layer.select(F.col("old").alias("b"), F.col("new").alias("nb"))
        moved = live.join(left, "a").join(right, "b").filter("na <> nb").select(F.least("na", "nb").alias("a"), F.greatest("na", "nb").alias("b")).distinct()
        live = scratch.save(moved, f"edges{k + 1}")
        scratch.drop(f"edges{k}")
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    if not layers:
        return spark.createDataFrame([], "node long, component long")
    names = layers[0].select(F.col("old").alias("node"), F.col("new").alias("label"))
    for layer in layers[1:]:
        names = names.join(layer.withColumnRenamed("old", "label"), "label", "left").select("node", F.coalesce("new", "label").alias("label"))
    names = scratch.save(names, "names")
    least = names.groupBy("label").agg(F.min("node").alias("component"))
    least = least.withColumn("component", F.least("component", "label"))
    return names.join(least, "label").select("node", "component")
