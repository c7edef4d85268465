"""Conformance of relations and types to the ontology: snap, fold, orient, flag, validate."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT

from .clean import canon_rel_type


def singular(label: Column) -> Column:
    """A label without wrapper suffixes and plural endings."""
    bare = F.regexp_replace(F.trim(label), r"(?i)[_ ](type|class|entity|relation)$", "")
    return F.when(bare.rlike("(?i)ies$"), F.regexp_replace(bare, "(?i)ies$", "y")).when(bare.rlike("(?i)ss$"), bare).otherwise(F.regexp_replace(bare, "(?i)s$", ""))


def snap_predicates(rels: DataFrame, vocab: DataFrame, label_vecs: DataFrame | None = None, vocab_vecs: DataFrame | None = None, floor: float = DEFAULT.snap_floor,
                    most_bytes: int = 64 << 20) -> DataFrame:
    """Adds ``canon`` and ``tier`` (exact, singular, vector, novel). ``vocab`` has (label).

    Only distinct labels are looked at; the vector tier, for the residue, takes the best vocabulary
    label at or over ``floor`` by cosine of (label, vec), the last in order of equal ones. The vocabulary's
    vectors go out as one matrix of at most ``most_bytes``; a larger vocabulary is met part by part. The
    map is joined back.
    """
    labels = rels.select(F.col("rel_type").alias("raw")).where("raw is not null").distinct().withColumn("canon0", F.lower(canon_rel_type(F.col("raw"))))
    words = vocab.select(F.col("label").alias("v")).distinct()
    exact = words.select(F.lower(canon_rel_type(F.col("v"))).alias("canon0"), F.col("v").alias("v_exact")).groupBy("canon0").agg(F.min("v_exact").alias("v_exact"))
    single = words.select(singular(F.lower(canon_rel_type(F.col("v")))).alias("s"), F.col("v").alias("v_single")).groupBy("s").agg(F.min("v_single").alias("v_single"))
    rows = labels.join(exact, "canon0", "left").withColumn("s", singular(F.col("canon0"))).join(single, "s", "left").withColumn("v_vec", F.lit(None).cast("string"))
    if label_vecs is not None and vocab_vecs is not None:
        rest = rows.where("v_exact is null and v_single is null").select("raw").join(label_vecs.select(F.col("label").alias("raw"), "vec"), "raw")
        near = _nearest(rest, vocab_vecs, floor, most_bytes)
        best = near.groupBy("raw").agg(F.max(F.struct("cos", "v")).alias("m")).select("raw", F.col("m.v").alias("v_vec"))
        rows = rows.drop("v_vec").join(best, "raw", "left")
    tier = F.when(F.col("v_exact").isNotNull(), "exact").when(F.col("v_single").isNotNull(), "singular").when(F.col("v_vec").isNotNull(), "vector").otherwise("novel")
    names = rows.select(F.col("raw").alias("rel_type"), F.coalesce("v_exact", "v_single", "v_vec", "raw").alias("canon"), tier.alias("tier"))
    return rels.join(names, "rel_type", "left")


def _nearest(rest: DataFrame, vocab_vecs: DataFrame, floor: float, most_bytes: int) -> DataFrame:
    """(raw, v, cos): for each (raw, vec) the best vocabulary label at or over ``floor`` of every part of the vocabulary."""
    words = vocab_vecs.select("label", F.col("vec").cast("array<double>").alias("vec")).where("label is not null and vec is not null")
    size, width = words.agg(F.count("*"), F.max(F.size("vec"))).first()
    parts = max(1, -(-size * (width or 1) * 8 // most_bytes))
    spark, out = rest.sparkSession, None
    for part in range(parts):
        rows = words.where(F.pmod(F.xxhash64("label"), F.lit(parts)) == part).orderBy("label").collect()  # at most about most_bytes
        shared = spark.sparkContext.broadcast(([r[0] for r in rows], np.array([r[1] for r in rows], dtype=np.float64).reshape(len(rows), -1)))

        def go(batches, shared=shared):
            names, mat = shared.value
            for b in batches:
                if not b.num_rows or not names:
                    continue
                x = np.array(b.column(1).to_pylist(), dtype=np.float64)
                cos = (x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-300)) @ (mat / np.maximum(np.linalg.norm(mat, axis=1, keepdims=True), 1e-300)).T
                at = cos.shape[1] - 1 - np.argmax(cos[:, ::-1], axis=1)
                best = cos[np.arange(len(at)), at]
                ok = np.flatnonzero(best >= floor - 1e-12)
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(ok)), pa.array([names[i] for i in at[ok]], pa.string()), pa.array(best[ok])], ["raw", "v", "cos"])

        near = rest.select("raw", F.col("vec").cast("array<double>").alias("vec")).mapInArrow(go, "raw string, v string, cos double")
        out = near if out is None else out.unionByName(near)
    return out


def unknown_predicates(snapped: DataFrame) -> DataFrame:
    """(rel_type, n) of novel labels, for review."""
    return snapped.where("tier = 'novel'").groupBy("rel_type").agg(F.count("*").alias("n"))


#: Upward predicate of downward and inverse labels: the ends are swapped.
INVERSES = {"has_subordinate": "subordinate_to", "commands": "subordinate_to", "has_subordinate_formation": "subordinate_to"}


def fold_inverse(rels: DataFrame, inverses: dict[str, str] = INVERSES) -> DataFrame:
    """Inverse labels become their upward predicate with the ends swapped."""
    label = F.lower(canon_rel_type(F.col("rel_type")))
    up = F.coalesce(*[F.when(label == k, v) for k, v in inverses.items()])
    return rels.withColumn("__up", up).withColumns({"src": F.when(F.col("__up").isNotNull(), F.col("dst")).otherwise(F.col("src")),
                                                    "dst": F.when(F.col("__up").isNotNull(), F.col("src")).otherwise(F.col("dst")),
                                                    "rel_type": F.coalesce("__up", "rel_type")}).drop("__up")


#: Rank words, highest level first.
TIERS = (("corps", "command"), ("division",), ("brigade",), ("regiment", "battalion"))


def rank_of(name: Column, tiers: tuple[tuple[str, ...], ...] = TIERS) -> Column:
    """4 for the highest level down to 1; null without a rank word."""
    low = F.lower(name)
    return F.coalesce(*[F.when(low.rlike(r"(^|[^a-z])(" + "|".join(words) + r")($|[^a-z])"), len(tiers) - i) for i, words in enumerate(tiers)])


def orient_by_rank(rels: DataFrame, ents: DataFrame, predicate: str = "subordinate_to", org: str = "ORGANIZATION") -> DataFrame:
    """Swaps the ends of ``predicate`` edges between organisations whose source outranks the target; equal or unknown ranks stay."""
    e = ents.select("doc_id", "ent_id", "type", rank_of(F.col("name")).alias("r"))
    rows = (rels.join(e.select("doc_id", F.col("ent_id").alias("src"), F.col("type").alias("st"), F.col("r").alias("sr")), ["doc_id", "src"], "left")
            .join(e.select("doc_id", F.col("ent_id").alias("dst"), F.col("type").alias("dt"), F.col("r").alias("dr")), ["doc_id", "dst"], "left"))
    swap = F.coalesce((F.col("rel_type") == predicate) & (F.col("st") == org) & (F.col("dt") == org) & (F.col("sr") > F.col("dr")), F.lit(False))
    rows = rows.withColumn("__swap", swap)
    return rows.withColumns({"src": F.when(F.col("__swap"), F.col("dst")).otherwise(F.col("src")), "dst": F.when(F.col("__swap"), F.col("src")).otherwise(F.col("dst"))}).select(*rels.columns)


def conform(rels: DataFrame, ents: DataFrame, vocab: DataFrame, **vecs) -> DataFrame:
    """Snap, fold, orient, in this order, so that later keys see canonical types and directions."""
    snapped = snap_predicates(rels, vocab, **vecs).withColumn("rel_type", F.col("canon")).drop("canon", "tier")
    return orient_by_rank(fold_inverse(snapped), ents)


def flag_novel(df: DataFrame, vocab: DataFrame, col: str) -> DataFrame:
    """Adds ``novel``: the label, without plural and wrapper suffixes, is not in the vocabulary (label)."""
    known = vocab.select(singular(F.lower("label")).alias("__k")).distinct().withColumn("__known", F.lit(True))
    return df.withColumn("__k", singular(F.lower(F.col(col)))).join(known, "__k", "left").withColumn("novel", F.col("__known").isNull()).drop("__k", "__known")


def proposed_extensions(flagged: DataFrame, col: str) -> DataFrame:
    return flagged.where("novel").groupBy(singular(F.lower(F.col(col))).alias("label")).agg(F.count("*").alias("n"))


def promote(vocab: DataFrame, approved: DataFrame) -> DataFrame:
    """The vocabulary with approved labels; its version hash changes, so cached slices miss."""
    return vocab.select("label").unionByName(approved.select("label")).distinct()


def tag_types(ents: DataFrame, classes: DataFrame) -> DataFrame:
    """Adds ``class_id`` by exact, singular or alternative label; ``classes`` has (class_id, label, alt_labels)."""
    names = classes.select("class_id", F.explode(F.concat(F.array("label"), F.coalesce("alt_labels", F.array().cast("array<string>")))).alias("l"))
    keys = names.groupBy(singular(F.lower("l")).alias("__k")).agg(F.min("class_id").alias("class_id"))
    return ents.withColumn("__k", singular(F.lower("type"))).join(keys, "__k", "left").drop("__k")


def validate_domain_range(rels: DataFrame, ents: DataFrame, predicates: DataFrame, reach: DataFrame) -> DataFrame:
    """Adds ``valid``: both ends' types lie at or under the predicate's domain and range; unknown predicates are null."""
    t = ents.select("doc_id", "ent_id", F.col("type").alias("t"))
    rows = rels.join(t.select("doc_id", F.col("ent_id").alias("src"), F.col("t").alias("st")), ["doc_id", "src"], "left").join(t.select("doc_id", F.col("ent_id").alias("dst"), F.col("t").alias("dt")), ["doc_id", "dst"], "left")
    rows = rows.join(predicates.select(F.col("pred_id").alias("rel_type"), "domain", "range"), "rel_type", "left")
    up = reach.select("child", "ancestor", F.lit(True).alias("ok")).distinct()
    rows = rows.join(up.select(F.col("child").alias("st"), F.col("ancestor").alias("domain"), F.col("ok").alias("s_ok")), ["st", "domain"], "left")
    rows = rows.join(up.select(F.col("child").alias("dt"), F.col("ancestor").alias("range"), F.col("ok").alias("d_ok")), ["dt", "range"], "left")
    valid = F.when(F.col("domain").isNotNull(), F.coalesce("s_ok", F.lit(False)) & F.coalesce("d_ok", F.lit(False)))
    return rows.withColumn("valid", valid).select(*rels.columns, "valid")
