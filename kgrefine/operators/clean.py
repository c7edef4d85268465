"""Finalisation of entities and relations: labels, loops, types, titles, merge, ids, dangling references.

Entities are rows (doc_id, ent_id, type, name, ...); relations are rows (doc_id, src, dst, rel_type, ...).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT

#: Misspelt relation types and their corrections (own list, extend by parameter).
TYPOS = {"SURVEILED": "SURVEILLED", "OCURRED_IN": "OCCURRED_IN", "RECIEVED": "RECEIVED"}

#: Strong indicator words of types other than person (own list).
INDICATORS = {"ORGANIZATION": ("ministry", "company", "committee", "agency", "inc", "corp"), "LOCATION": ("street", "river", "island", "harbour", "city"),
              "EVENT": ("conference", "summit", "exercise")}

PREFIXES = {"PERSON": "p", "ORGANIZATION": "o", "LOCATION": "l", "EVENT": "e"}


def canon_rel_type(label: Column, typos: dict[str, str] = TYPOS) -> Column:
    """Upper snake form of a relation label, known misspellings corrected; null stays null."""
    snake = F.upper(F.regexp_replace(F.trim(label), r"[\s\-]+", "_"))
    fixed = snake
    for wrong, right in typos.items():
        fixed = F.when(snake == wrong, right).otherwise(fixed)
    return fixed


def drop_self_loops(rels: DataFrame) -> DataFrame:
    """Relations whose ends differ; those with a null end stay for the dangling check."""
    return rels.where("not (src <=> dst)")


def fix_entity_type(ents: DataFrame, indicators: dict[str, tuple[str, ...]] = INDICATORS) -> DataFrame:
    """Persons whose name holds a strong indicator word take that word's type; ``retyped`` says which."""
    tokens = F.split(F.lower("name"), r"[^a-z]+")
    new = F.lit(None).cast("string")
    for kind, words in reversed(indicators.items()):
        new = F.when(F.arrays_overlap(tokens, F.array(*[F.lit(w) for w in words])), kind).otherwise(new)
    change = (F.col("type") == "PERSON") & new.isNotNull()
    return ents.withColumn("retyped", F.coalesce(change, F.lit(False))).withColumn("type", F.when(change, new).otherwise(F.col("type")))


def core_name(name: Column, most: int = DEFAULT.title_token_chars, attested: Column | None = None) -> Column:
    """The name without leading title-like tokens, never fewer than two tokens.

    Structural mode strips every leading alphabetic token (a final stop allowed) of at most ``most``
    letters while more than two are left. ``attested``, an array column of lower-case tokens, strips
    only tokens found in it.
    """
    tokens = F.split(F.trim(F.regexp_replace(name, r"\s+", " ")), " ")

    def titled(t: Column) -> Column:
        shape = t.rlike(r"^\p{L}+\.?$") & (F.length(F.regexp_replace(t, r"\.", "")) <= most)
        return shape if attested is None else shape & F.array_contains(attested, F.lower(F.regexp_replace(t, r"\.", "")))

    # the first place whose token stays; the last two always stay
    front = F.slice(tokens, 1, F.greatest(F.size(tokens) - 2, F.lit(0)))
    n = F.aggregate(front, F.struct(F.lit(0).alias("n"), F.lit(True).alias("go")),
                    lambda a, t: F.struct((a["n"] + F.when(a["go"] & titled(t), 1).otherwise(0)).alias("n"), (a["go"] & titled(t)).alias("go")), lambda a: a["n"])
    return F.array_join(F.slice(tokens, n + 1, F.size(tokens)), " ")


def attested_titles(names: DataFrame, name_col: str = "name", least: int = 3) -> DataFrame:
    """(token): tokens that stand before at least ``least`` distinct two-word names which also occur on their own."""
    rows = names.select(F.split(F.trim(name_col), r"\s+").alias("t"), F.lower(F.trim(name_col)).alias("whole")).distinct()
    long = rows.where(F.size("t") == 3).select(F.lower(F.regexp_replace(F.col("t")[0], r"\.", "")).alias("token"), F.lower(F.array_join(F.slice("t", 2, 2), " ")).alias("core"))
    return long.join(rows.select(F.col("whole").alias("core")), "core", "left_semi").groupBy("token").agg(F.countDistinct("core").alias("n")).where(F.col("n") >= least).select("token")


def merge_entities(ents: DataFrame, key: str = "core", order_col: str = "ent_id", core: Column | None = None) -> tuple[DataFrame, DataFrame]:
    """(merged, id_map): entities of a document with one type and one key become one.

    ``key`` is ``core`` (title-free name) or ``verbatim``. The shortest name of a group is its name, the
    others its aliases; the smallest id is its id. Grouping is by document, type and key, so a group holds the
    mentions of one name in one document. ``id_map`` has (doc_id, ent_id, merged_id).
    """
    base = (core if core is not None else core_name(F.col("name"))) if key == "core" else F.col("name")
    rows = ents.withColumn("__key", F.lower(base)).withColumn("__base", base)
    group = ["doc_id", "type", "__key"]
    merged = rows.groupBy(*group).agg(F.min(order_col).alias("ent_id"), F.min(F.struct(F.length("__base"), F.col("__base"))).alias("__b"),
                                      F.array_sort(F.collect_set("name")).alias("names"), F.count("*").alias("mentions"))
    merged = merged.withColumn("name", F.col("__b.__base"))
    ids = rows.join(merged.select(*group, F.col("ent_id").alias("merged_id")), group).select("doc_id", "ent_id", "merged_id")
    aliases = F.array_except("names", F.array("name"))
    return merged.select("doc_id", "ent_id", "type", "name", aliases.alias("aliases"), "mentions"), ids


def remap(rels: DataFrame, ids: DataFrame) -> DataFrame:
    """Relations with both ends renamed by (doc_id, ent_id, merged_id); ends that are not in the map stay."""
    a = ids.select("doc_id", F.col("ent_id").alias("src"), F.col("merged_id").alias("__s"))
    b = ids.select("doc_id", F.col("ent_id").alias("dst"), F.col("merged_id").alias("__d"))
    out = rels.join(a, ["doc_id", "src"], "left").join(b, ["doc_id", "dst"], "left")
    return out.withColumn("src", F.coalesce("__s", "src")).withColumn("dst", F.coalesce("__d", "dst")).select(*rels.columns)


def renumber(ents: DataFrame, width: int = 3, prefixes: dict[str, str] = PREFIXES, order_col: str = "ent_id") -> tuple[DataFrame, DataFrame]:
    """(entities, id_map) with ids prefix_number by type within the document, in the order of ``order_col``."""
    prefix = F.coalesce(*[F.when(F.col("type") == k, v) for k, v in prefixes.items()], F.lit("x"))
    rows = ents.withColumn("__p", prefix)
    n = F.dense_rank().over(Window.partitionBy("doc_id", "__p").orderBy(order_col))
    rows = rows.withColumn("new_id", F.concat("__p", F.lit("_"), F.lpad(n.cast("string"), width, "0") if width else n.cast("string")))
    return rows.drop("ent_id", "__p").withColumnRenamed("new_id", "ent_id"), rows.select("doc_id", "ent_id", F.col("new_id").alias("merged_id"))


def drop_dangling(rels: DataFrame, ents: DataFrame) -> DataFrame:
    """Relations both ends of which are entities of the same document."""
    ids = ents.select("doc_id", "ent_id").distinct()
    return (rels.join(ids.withColumnRenamed("ent_id", "src"), ["doc_id", "src"], "left_semi").join(ids.withColumnRenamed("ent_id", "dst"), ["doc_id", "dst"], "left_semi"))


#: Steps of ``finalize``, each of which may be left out.
FIXES = ("labels", "loops", "types", "titles", "ids", "dangling")


def clean_entities(ents: DataFrame, fixes: tuple[str, ...] = FIXES, cut=lambda df: df, known: dict | None = None) -> tuple[DataFrame, dict[str, DataFrame]]:
    """Entities after those of the named steps that act on them, and the maps of ids by step.

    Relations have no part in these steps, so chains that begin alike may share a ``known`` table of what
    each beginning gave; it must be used with one table of entities only.
    """
    known, done, maps = {} if known is None else known, (), {}
    for name in ("types", "titles", "ids"):
        if name not in fixes:
            continue
        done = (*done, name)
        if done not in known:
            known[done] = (fix_entity_type(ents).drop("retyped"), None) if name == "types" else tuple(map(cut, merge_entities(ents) if name == "titles" else renumber(ents)))
        ents, ids = known[done]
        if ids is not None:
            maps[name] = ids
    return ents, maps


def finalize(ents: DataFrame, rels: DataFrame, fixes: tuple[str, ...] = FIXES, cut=lambda df: df, known: dict | None = None) -> tuple[DataFrame, DataFrame]:
    """Entities and relations after the named steps, always in the order of ``FIXES``; loops go before and after the merge.

    ``cut`` may store what several later steps read (merged entities and the maps of ids), so that the merge runs once;
    ``known`` is as in ``clean_entities``.
    """
    if "labels" in fixes:
        rels = rels.withColumn("rel_type", canon_rel_type(F.col("rel_type")))
    if "loops" in fixes:
        rels = drop_self_loops(rels)
    ents, maps = clean_entities(ents, fixes, cut, known)
    if "titles" in maps:
        rels = remap(rels, maps["titles"])
        rels = drop_self_loops(rels) if "loops" in fixes else rels
    if "ids" in maps:
        rels = remap(rels, maps["ids"])
    if "dangling" in fixes:
        rels = drop_dangling(rels, ents)
    return ents, rels


def quality_table(ents: DataFrame, rels: DataFrame) -> DataFrame:
    """One row of defect counts: entities, persons, relations, self loops, dangling, type variants, id shapes."""
    e = ents.agg(F.count("*").alias("entities"), F.count_if(F.col("type") == "PERSON").alias("persons"),
                 F.countDistinct(F.regexp_replace("ent_id", "[0-9]+", "9")).alias("id_shapes"))
    ids = ents.select("doc_id", "ent_id").distinct()
    r = rels.agg(F.count("*").alias("relations"), F.count_if(F.col("src") == F.col("dst")).alias("self_loops"), F.countDistinct("rel_type").alias("type_variants"))
    lost = rels.select("doc_id", F.explode(F.array_distinct(F.array("src", "dst"))).alias("ent_id")).join(ids, ["doc_id", "ent_id"], "left_anti").agg(F.count("*").alias("dangling_ends"))
    return e.crossJoin(r).crossJoin(lost)
