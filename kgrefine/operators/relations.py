"""Relation deduplication: union, ordered fold and first-wins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEY = ["doc_id", "src", "dst", "rel_type"]


def show_quals(quals: Column) -> Column:
    """A qualifier map as sorted ``key=value;`` text."""
    return F.array_join(F.transform(F.array_sort(F.map_entries(quals)), lambda e: F.concat(e["key"], F.lit("="), e["value"], F.lit(";"))), "")


def dedup_relations(rels: DataFrame, mode: str = "union") -> DataFrame:
    """(doc_id, src, dst, rel_type, quals, n_merged, alternatives): one row for each relation.

    ``union`` keeps every qualifier key: of several values of a key the one of the smallest ``ord`` is
    primary and all stand in ``alternatives``. It is commutative: relations that stand once pass as they
    are, the qualifiers of the others are exploded and summed with partial aggregates. ``fold`` walks the copies in the order of ``ord``: equal sizes
    unite, otherwise the larger set stays. ``first`` keeps the qualifiers of the smallest ``ord``.
    """
    if mode == "union":
        # counts alone are hashed; only relations with copies meet in the wider aggregates
        copied = rels.groupBy(*KEY).agg(F.count("*").alias("n")).where("n > 1").select(*KEY)
        same = lambda a, b: [F.col(f"{a}.{k}").eqNullSafe(F.col(f"{b}.{k}")) for k in KEY]
        none = F.lit(None).cast("string")
        once = rels.alias("r").join(copied.alias("c"), same("r", "c"), "left_anti").select(*KEY, F.coalesce("quals", F.create_map().cast("map<string,string>")).alias("quals"), F.lit(1).cast("long").alias("n_merged"),
                                                                                          F.create_map().cast("map<string,array<string>>").alias("alternatives"))
        rels = rels.alias("r").join(copied.alias("c"), same("r", "c"), "left_semi")
        # a null key beside a row's own counts the rows, so one scan gives both
        blank = F.struct(none.alias("k"), none.alias("v"))
        entries = F.concat(F.transform(F.map_entries("quals"), lambda e: F.struct(e["key"].alias("k"), e["value"].alias("v"))), F.array(blank))
        each = rels.select(*KEY, "ord", F.inline(F.coalesce(entries, F.array(blank))))
        by_key = each.groupBy(*KEY, "k").agg(F.min(F.struct("ord", "v")).alias("m"), F.collect_set("v").alias("vs"), F.count("*").alias("n"))
        quals = F.map_from_entries(F.array_sort(F.collect_list(F.when(F.col("k").isNotNull(), F.struct("k", F.col("m.v"))))))
        alts = F.map_from_entries(F.array_sort(F.collect_list(F.when(F.size("vs") > 1, F.struct(F.col("k"), F.array_sort("vs"))))))
        return by_key.groupBy(*KEY).agg(quals.alias("quals"), F.max(F.when(F.col("k").isNull(), F.col("n"))).alias("n_merged"), alts.alias("alternatives")).unionByName(once)
    none = F.lit(None).cast("map<string,array<string>>").alias("alternatives")
    if mode == "first":
        return rels.groupBy(*KEY).agg(F.min_by("quals", "ord").alias("quals"), F.count("*").alias("n_merged")).select("*", none)
    if mode != "fold":
        raise ValueError(mode)
    ordered = F.array_sort(F.collect_list(F.struct("ord", F.map_entries("quals").alias("q"))))

    def step(acc: Column, x: Column) -> Column:
        new = F.filter(x["q"], lambda e: ~F.exists(acc, lambda a: a["key"] == e["key"]))
        both = F.concat(acc, new)
        return F.when(F.size(x["q"]) == F.size(acc), both).when(F.size(x["q"]) > F.size(acc), x["q"]).otherwise(acc)

    start = F.array().cast("array<struct<key:string,value:string>>")
    rows = rels.groupBy(*KEY).agg(ordered.alias("o"), F.count("*").alias("n_merged"))
    return rows.select(*KEY, F.map_from_entries(F.aggregate("o", start, step)).alias("quals"), "n_merged", none)
