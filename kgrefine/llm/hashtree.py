"""Sharding by a hierarchical weighted hash tree. DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.plans.scratch import written

#: A tree is a list of (region, rack, shard, weight) leaves.
Tree = list[tuple[int, int, int, float]]


def balanced_tree(shards: int, per_rack: int = 4, racks: int = 2) -> Tree:
    """Equal leaves numbered from 0, filled rack by rack and region by region."""
    return [(s // (per_rack * racks), s // per_rack, s, 1.0) for s in range(shards)]


def grown(tree: Tree, weight: float = 1.0) -> Tree:
    """One more shard, in a region of its own: rows that the root's draw moves have only the new leaf to fall to."""
    region, rack, shard = (max((leaf[i] for leaf in tree), default=-1) + 1 for i in range(3))
    return [*tree, (region, rack, shard, weight)]


def _choose(children: Column, level: str, seed: int, key: Column) -> Column:
    """The child with the smallest exponential draw; a draw depends on the key, the child and its weight alone."""

    def draw(c: Column) -> Column:
        bits = F.xxhash64(F.lit(seed), F.lit(level), c["id"], key).bitwiseAND(F.lit(2**53 - 1))
        return F.struct((-F.ln((bits + 0.5) / float(2**53)) / c["weight"]).alias("draw"), c["id"].alias("id"))

    return F.array_min(F.transform(children, draw))["id"]


def descend(key: Column, tree: Tree, seed: int = 7) -> Column:
    """The leaf shard of ``key``: at region, rack and shard level the child with the best weighted draw.

    A child wins in proportion to the weight below it. When a leaf's weight changes, draws change only
    for its own rack and region, so keys move only into or out of those; all other choices stay.
    """
    levels: list[dict] = [{}, {}, {}]
    for region, rack, shard, weight in tree:
        if weight > 0:
            for at, (parent, child) in enumerate(((0, region), (region, rack), (rack, shard))):
                group = levels[at].setdefault(parent, {})
                group[child] = group.get(child, 0.0) + weight

    def table(level: dict) -> Column:
        kids = lambda g: F.array(*[F.struct(F.lit(i).alias("id"), F.lit(float(w)).alias("weight")) for i, w in sorted(g.items())])
        return F.create_map(*[x for parent, g in sorted(level.items()) for x in (F.lit(parent), kids(g))])

    def step(at: Column, name: str, level: dict) -> Column:
        return F.element_at(F.transform(F.array(F.element_at(table(level), at)), lambda kids: _choose(kids, name, seed, key)), 1)

    at = F.lit(0)
    for name, level in zip(("region", "rack", "shard"), levels, strict=True):
        at = step(at, name, level)
    return at


def shard_documents(docs: DataFrame, tree: Tree, more: Tree | None = None, id_col: str = "doc_id", text_col: str = "text", seed: int = 7,
                    rows_per_bucket: int = 50_000) -> DataFrame:
    """(doc_id, size, text_crc32, shard, slot, grown_shard): each row's leaf, its gapless place there, and its leaf in ``more``.

    The key is the id alone, so shards depend on ids and the tree. ``size`` is the text's UTF-8 bytes
    plus 16. Slots come from two levels: shards are cut into hash buckets of about ``rows_per_bucket`` rows,
    rows are numbered in their bucket and buckets are offset by the sums before them, so that no task
    orders a whole shard. A null id is a key of its own; null text counts as empty; repeated rows get a
    slot each and the same shard; an empty table gives none. Further columns are not carried.
    """
    text = F.coalesce(text_col, F.lit(""))
    key = F.coalesce(F.col(id_col).cast("string"), F.lit("null"))
    rows = docs.select(F.col(id_col).alias("doc_id"), (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text).alias("text_crc32"),
                       descend(key, tree, seed).cast("int").alias("shard"),
                       (descend(key, more, seed) if more else F.lit(None)).cast("int").alias("grown_shard"), F.monotonically_increasing_id().alias("row"))
    rows = written(rows, "shards")
    buckets = max(1, math.ceil(rows.count() / rows_per_bucket))
    rows = rows.withColumn("bucket", F.pmod(F.xxhash64("row"), F.lit(buckets)).cast("int"))
    counts = rows.groupBy("shard", "bucket").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    counts = counts.select("shard", "bucket", before.alias("before"))
    inside = F.row_number().over(Window.partitionBy("shard", "bucket").orderBy("row")) - 1
    return rows.withColumn("inside", inside).join(counts, ["shard", "bucket"]).select(
        "doc_id", "size", "text_crc32", "shard", (F.col("before") + F.col("inside")).cast("long").alias("slot"), "grown_shard")
