"""Spreadsheets by one plan: inspect a few rows, plan once, execute as one projection."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def inspect_table(df: DataFrame, n: int = 10) -> dict:
    """Headers, types and about ``n`` rows of a sheet."""
    return {"columns": dict(df.dtypes), "rows": [r.asDict() for r in df.limit(n).collect()]}


def plan_table(profile: dict, provider=None, entity_type: str = "ROW") -> dict:
    """One plan for a template: value kinds, name column, relations, split and fill columns, rows to drop.

    ``provider(profile) -> plan`` is called once; the rule planner reads kinds from the sampled values.
    """
    if provider is not None:
        return provider(profile)

    def kind(col: str, declared: str) -> str:
        if declared in ("int", "bigint", "long"):
            return "int"
        if declared in ("double", "float") or declared.startswith("decimal"):
            return "float"
        seen = [str(r[col]) for r in profile["rows"] if r[col] is not None]
        if seen and sum(bool(re.fullmatch(r"\d{4}-\d{2}-\d{2}", s)) for s in seen) * 2 > len(seen):
            return "date"
        if seen and all(re.fullmatch(r"-?\d+", s) for s in seen):
            return "int"
        return "string"

    cols = profile["columns"]
    return {"entity_type": entity_type, "name_column": next(iter(cols), None), "columns": {c: kind(c, t) for c, t in cols.items()}, "relations": [], "split": {}, "fill": [], "drop_where": None}


def coerce(col: Column, kind: str) -> Column:
    """A value of the planned kind, null where it does not parse."""
    text = F.trim(col.cast("string"))
    if kind == "int":
        return F.when(text.rlike(r"^-?\d{1,18}$"), text.try_cast("long"))
    if kind == "float":
        return text.try_cast("double")
    if kind == "date":
        return F.when(text.rlike(r"^\d{4}-\d{2}-\d{2}$"), text.try_cast("date"))
    return text


def execute_plan(df: DataFrame, plan: dict, order_col: str | None = None, group_col: str | None = None) -> DataFrame:
    """The sheet's rows with planned kinds, as one projection.

    ``drop_where`` (SQL) drops totals and the like; ``fill`` columns take the last value above within
    ``group_col`` in the order of ``order_col`` (merged cells); ``split`` maps columns to separators and
    gives a row for each value. ``<column>__bad`` marks dates that did not parse.
    """
    rows = df.where(f"not coalesce(({plan['drop_where']}), false)") if plan.get("drop_where") else df
    for c in plan.get("fill", []):
        w = Window.partitionBy(*([group_col] if group_col else [])).orderBy(order_col).rowsBetween(Window.unboundedPreceding, 0)
        rows = rows.withColumn(c, F.last(c, ignorenulls=True).over(w))
    for c, sep in plan.get("split", {}).items():
        rows = rows.withColumn(c, F.explode_outer(F.split(F.col(c), rf"\s*{re.escape(sep)}\s*")))
    out = [coerce(F.col(c), k).alias(c) for c, k in plan["columns"].items()]
    bad = [(F.col(c).isNotNull() & coerce(F.col(c), k).isNull()).alias(f"{c}__bad") for c, k in plan["columns"].items() if k == "date"]
    return rows.select(*out, *bad)


def map_records(records: DataFrame, plan: dict, id_col: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(entities, relations, warnings): a row's entity, its planned relations, and a count of unparsable dates for each column."""
    name = F.col(plan["name_column"]).cast("string")
    props = F.map_filter(F.create_map(*[x for c in plan["columns"] for x in (F.lit(c), F.col(c).cast("string"))]), lambda k, v: v.isNotNull())
    ents = records.select(F.col(id_col).cast("string").alias("ent_id"), F.lit(plan["entity_type"]).alias("type"), name.alias("name"), props.alias("props"))
    rels = None
    for r in plan.get("relations", []):
        part = records.where(F.col(r["column"]).isNotNull()).select(F.col(id_col).cast("string").alias("src"), F.concat(F.lit(r["target_type"] + ":"), F.col(r["column"]).cast("string")).alias("dst"), F.lit(r["rel_type"]).alias("rel_type"))
        rels = part if rels is None else rels.unionByName(part)
    if rels is None:
        rels = records.select(F.lit("").alias("src"), F.lit("").alias("dst"), F.lit("").alias("rel_type")).where("false")
    flags = [c for c in records.columns if c.endswith("__bad")]
    if not flags:
        return ents, rels, records.select(F.lit("").alias("column"), F.lit(0).cast("long").alias("unparsed")).where("false")
    counts = records.agg(*[F.count_if(F.col(c)).alias(c) for c in flags])
    warn = counts.select(F.explode(F.array(*[F.struct(F.lit(c.removesuffix("__bad")).alias("column"), F.col(c).alias("unparsed")) for c in flags])).alias("w")).select("w.*")
    return ents, rels, warn
