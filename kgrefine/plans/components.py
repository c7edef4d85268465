"""Connected components by alternating star contractions over DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import forget, written


def _mins(both: DataFrame) -> DataFrame:
    return both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))


def _large_star(edges: DataFrame, hub_rows: int | None) -> DataFrame:
    both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    if hub_rows is None:
        joined = both.join(_mins(both), "u")
    else:
        # a hub's edges are dealt out by the other end, and its minimum goes to each of the parts
        degrees = written(both.groupBy("u").agg(F.min("v").alias("m"), F.ceil(F.count("*") / hub_rows).cast("int").alias("parts")), "cc")
        hubs = degrees.where("parts > 1").select("u", "parts")
        hubs = F.broadcast(hubs) if hubs.count() <= 1_000_000 else hubs
        dealt = both.join(hubs, "u", "left").withColumn("part", F.pmod(F.xxhash64("v"), F.coalesce("parts", F.lit(1))).cast("int"))
        least = degrees.select("u", F.least("u", "m").alias("m"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"))
        joined = dealt.join(least, ["u", "part"])
    return joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = _mins(down)
    moved = down.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.unionByName(least.select("u", F.col("m").alias("v")))


def connected_components(edges: DataFrame, left: str = "u", right: str = "v", max_rounds: int = 50, hub_rows: int = 200_000) -> DataFrame:
    """Rows (node, component) for every node with an edge to another node; component is the smallest node reached.

    Large-star and small-star rounds move every edge towards the smallest neighbour, so the number of
    rounds grows with the logarithm of the longest path. The minimum of a node's neighbours is a
    partial aggregate joined back on the node, never a collected list. With over ``hub_rows`` edges in all
    there can be hubs; a node of more is then joined in parts of that size, so a hub with a third of all
    edges is many tasks. Each round is written to the shared folder. Null ends and self loops are left
    out; an empty edge table gives an empty result.
    """
    now = written(
        edges.select(F.col(left).cast("long").alias("u"), F.col(right).cast("long").alias("v"))
        .where("u is not null and v is not null and u <> v").distinct(), "cc")
    before, edges_left = None, now.count()
    for _ in range(max_rounds):
        step = written(_small_star(_large_star(now, hub_rows if edges_left > hub_rows else None)).where("u <> v").distinct(), "cc")
        mark = step.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        forget(now)
        now = step
        if mark == before or mark[0] == 0:
            break
        before, edges_left = mark, mark[0]
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    ends = now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return ends.unionByName(roots)
