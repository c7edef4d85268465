"""Relationship quality gates that force a second extraction pass, and the catalogues of that pass."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT


def skip_by_count(rels: DataFrame, least: int = DEFAULT.gate_relations) -> DataFrame:
    """The baseline, (doc_id, n_rels, skip): a document with enough relations needs no second pass."""
    return rels.groupBy("doc_id").agg(F.count("*").alias("n_rels")).withColumn("skip", F.col("n_rels") >= least)


def quality_gate(ents: DataFrame, rels: DataFrame, least: int = DEFAULT.gate_relations, persons: int = DEFAULT.gate_persons, person_rels: int = DEFAULT.gate_person_relations,
                 share: float = DEFAULT.gate_share, types: int = DEFAULT.gate_types, financial: str = "FINANCIAL", reporting: str = "REPORTED_TO",
                 labels: str = "(?i)(fund|budget|approv)") -> DataFrame:
    """(doc_id, n_rels, force, reasons, second_pass) for every document with entities.

    Checks: ``financial_links`` (financial and other entities, no relation across), ``financial_labels``
    (financial entities, no label like ``labels``), ``person_diversity`` (``persons`` or more persons, fewer
    than ``person_rels`` relations of persons other than reporting) and ``concentration`` (one type over
    ``share`` of the relations and fewer than ``types`` types). Each is an aggregate by document; a forced
    document is not skipped however many relations it has.
    """
    kinds = ents.select("doc_id", "ent_id", "type").distinct()
    per_doc = kinds.groupBy("doc_id").agg(F.count_if(F.col("type") == financial).alias("n_fin"), F.count_if(F.col("type") != financial).alias("n_other"),
                                          F.count_if(F.col("type") == "PERSON").alias("n_person"))
    s = kinds.select("doc_id", F.col("ent_id").alias("src"), F.col("type").alias("s_type"))
    d = kinds.select("doc_id", F.col("ent_id").alias("dst"), F.col("type").alias("d_type"))
    typed = rels.select("doc_id", "src", "dst", "rel_type").join(s, ["doc_id", "src"], "left").join(d, ["doc_id", "dst"], "left")
    across = F.coalesce((F.col("s_type") == financial) != (F.col("d_type") == financial), F.lit(False))
    person = F.coalesce((F.col("s_type") == "PERSON") | (F.col("d_type") == "PERSON"), F.lit(False))
    by_type = typed.groupBy("doc_id", "rel_type").agg(F.count("*").alias("n"), F.count_if(across).alias("n_across"), F.count_if(person & (F.col("rel_type") != reporting)).alias("n_prel"))
    stats = by_type.groupBy("doc_id").agg(F.sum("n").alias("n_rels"), F.max("n").alias("top"), F.count("*").alias("n_types"), F.sum("n_across").alias("n_across"),
                                          F.sum("n_prel").alias("n_prel"), F.count_if(F.col("rel_type").rlike(labels)).alias("n_labels"))
    rows = per_doc.join(stats, "doc_id", "left").na.fill(0)
    tests = {"financial_links": "n_fin > 0 and n_other > 0 and n_across = 0", "financial_labels": "n_fin > 0 and n_labels = 0",
             "person_diversity": f"n_person >= {persons} and n_prel < {person_rels}", "concentration": f"n_rels > 0 and top > {share} * n_rels and n_types < {types}"}
    reasons = F.array_compact(F.array(*[F.when(F.expr(t), F.lit(k)) for k, t in tests.items()]))
    rows = rows.select("doc_id", F.col("n_rels").cast("long").alias("n_rels"), reasons.alias("reasons")).withColumn("force", F.size("reasons") > 0)
    return rows.withColumn("second_pass", F.col("force") | (F.col("n_rels") < least))


def fallback_catalog(ents: DataFrame, top: int = DEFAULT.fallback_entities, score_col: str = "mentions") -> DataFrame:
    """The ``top`` entities of each document by score."""
    w = Window.partitionBy("doc_id").orderBy(F.desc(score_col), "ent_id")
    return ents.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= top)


def evidence_window(docs: DataFrame, most: int = DEFAULT.fallback_chars, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text): what of a text stands beside the fallback catalogue in a prompt; 0 means no limit."""
    from .chunks import limit_text

    return docs.select(F.col(id_col).alias("doc_id"), limit_text(F.col(text_col), most).alias("text"))


def batch_catalog(ents: DataFrame, size: int = DEFAULT.batch_entities, batches: int = DEFAULT.batch_count) -> DataFrame:
    """Adds ``batch_no``; entities past the last batch have null, so that they can be counted."""
    n = F.floor((F.row_number().over(Window.partitionBy("doc_id").orderBy("ent_id")) - 1) / size).cast("int")
    return ents.withColumn("batch_no", n).withColumn("batch_no", F.when(F.col("batch_no") < batches, F.col("batch_no")))


def coverage_warnings(ents: DataFrame, rels: DataFrame, ratio: float = 0.2, least: int = 10) -> DataFrame:
    """(doc_id, n_ents, n_rels, warning): documents of at least ``least`` entities with fewer than ``ratio`` relations for each."""
    e = ents.groupBy("doc_id").agg(F.count("*").alias("n_ents"))
    r = rels.groupBy("doc_id").agg(F.count("*").alias("n_rels"))
    rows = e.join(r, "doc_id", "left").na.fill(0, ["n_rels"])
    return rows.withColumn("warning", (F.col("n_ents") >= least) & (F.col("n_rels") < ratio * F.col("n_ents")))


def relation_concentration(rels: DataFrame) -> DataFrame:
    """(doc_id, edges, types, top_type_edges, top_share): two aggregates, by (document, type) and by document."""
    by_type = rels.groupBy("doc_id", "rel_type").agg(F.count("*").alias("n"))
    rows = by_type.groupBy("doc_id").agg(F.sum("n").alias("edges"), F.count("*").alias("types"), F.max("n").alias("top_type_edges"))
    return rows.withColumn("top_share", F.round(F.col("top_type_edges") / F.col("edges"), 6))


def detect_grid(rels: DataFrame, min_edges: int = 20, min_fill: float = 0.9) -> DataFrame:
    """(doc_id, rel_type, edges, n_src, n_dst, fill, grid): one predicate over nearly all pairs of several sources and targets."""
    e = rels.select("doc_id", "rel_type", "src", "dst").distinct()
    rows = e.groupBy("doc_id", "rel_type").agg(F.count("*").alias("edges"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"))
    rows = rows.withColumn("fill", F.round(F.col("edges") / (F.col("n_src") * F.col("n_dst")), 6))
    return rows.withColumn("grid", (F.col("edges") >= min_edges) & (F.col("fill") >= min_fill) & (F.col("n_src") > 1) & (F.col("n_dst") > 1))
