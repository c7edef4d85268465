"""Cost and accuracy measures."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, F.round(a / b, 6)).otherwise(F.lit(0.0))


def set_f1(found: DataFrame, gold: DataFrame, keys: list[str]) -> DataFrame:
    """(tp, fp, fn, precision, recall, f1) of two sets of key tuples: spans, pairs or triples by the choice of keys."""
    f = found.select(*keys).distinct().withColumn("__f", F.lit(1))
    g = gold.select(*keys).distinct().withColumn("__g", F.lit(1))
    rows = f.join(g, keys, "full").agg(F.count_if(F.col("__f").isNotNull() & F.col("__g").isNotNull()).alias("tp"), F.count_if(F.col("__g").isNull()).alias("fp"), F.count_if(F.col("__f").isNull()).alias("fn"))
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return rows.withColumns({"precision": _ratio(tp, tp + fp), "recall": _ratio(tp, tp + fn), "f1": _ratio(2 * tp, 2 * tp + fp + fn)})


def bag_tokens(df: DataFrame, id_col: str, text_col: str, out: str) -> DataFrame:
    t = F.explode(F.split(F.lower(F.coalesce(text_col, F.lit(""))), r"\s+")).alias("token")
    return df.select(F.col(id_col).alias("id"), t).where("token <> ''").groupBy("id", "token").agg(F.count("*").alias(out))


def token_f1(found: DataFrame, gold: DataFrame, id_col: str = "id", text_col: str = "text") -> DataFrame:
    """(id, overlap, n_found, n_gold, f1): overlap of token bags of each page."""
    both = bag_tokens(found, id_col, text_col, "n").join(bag_tokens(gold, id_col, text_col, "m"), ["id", "token"], "full").na.fill(0)
    rows = both.groupBy("id").agg(F.sum(F.least("n", "m")).alias("overlap"), F.sum("n").alias("n_found"), F.sum("m").alias("n_gold"))
    return rows.withColumn("f1", _ratio(2 * F.col("overlap"), F.col("n_found") + F.col("n_gold")))


def word_distance(a: list[str], b: list[str]) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prev, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prev, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prev + (x != y))
    return row[-1]


def wer(found: Column, gold: Column) -> Column:
    """Word edits over gold words, in order."""
    def go(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array([word_distance((x or "").split(), (y or "").split()) / max(1, len((y or "").split())) for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.float64())

    return F.arrow_udf(go, "double")(found, gold)


def cer(found: Column, gold: Column) -> Column:
    return F.levenshtein(found, gold) / F.greatest(F.length(gold), F.lit(1))


def conformance(emitted: DataFrame, vocab: DataFrame, source: DataFrame, gold: DataFrame | None = None) -> DataFrame:
    """(n, conform_pct, hallucination_pct, mapping_pct) of emitted (doc_id, name, type): types in the vocabulary, names absent from the source text (and gold), types equal to gold."""
    rows = emitted.join(vocab.select(F.lower("label").alias("__t"), F.lit(1).alias("__ok")).distinct(), F.lower("type") == F.col("__t"), "left").join(source.select("doc_id", F.lower("text").alias("__text")), "doc_id", "left")
    absent = ~F.coalesce(F.contains(F.col("__text"), F.lower("name")), F.lit(False))
    mapped = F.lit(None).cast("boolean")
    if gold is not None:
        rows = rows.join(gold.select("doc_id", "name", F.col("type").alias("__gold")).distinct(), ["doc_id", "name"], "left")
        absent, mapped = absent & F.col("__gold").isNull(), F.lower("type") == F.lower("__gold")
    n = F.count("*")
    return rows.agg(n.alias("n"), F.round(100 * F.count_if(F.col("__ok") == 1) / n, 4).alias("conform_pct"), F.round(100 * F.count_if(absent) / n, 4).alias("hallucination_pct"), F.round(100 * F.count_if(mapped) / n, 4).alias("mapping_pct"))


def gold_recall(found: DataFrame, gold: DataFrame, key: str = "name") -> DataFrame:
    """(n_gold, hits, recall): gold names that were found."""
    f = found.select(F.lower(key).alias("k")).distinct().withColumn("__hit", F.lit(1))
    rows = gold.select(F.lower(key).alias("k")).distinct().join(f, "k", "left").agg(F.count("*").alias("n_gold"), F.count_if(F.col("__hit") == 1).alias("hits"))
    return rows.withColumn("recall", _ratio(F.col("hits"), F.col("n_gold")))


def hallucinated(found: DataFrame, gold: DataFrame, key: str = "name") -> DataFrame:
    """(n, hallucinated, rate): emitted names outside gold."""
    g = gold.select(F.lower(key).alias("k")).distinct().withColumn("__g", F.lit(1))
    rows = found.select(F.lower(key).alias("k")).join(g, "k", "left").agg(F.count("*").alias("n"), F.count_if(F.col("__g").isNull()).alias("hallucinated"))
    return rows.withColumn("rate", _ratio(F.col("hallucinated"), F.col("n")))


def false_merges(clusters: DataFrame, gold: DataFrame) -> DataFrame:
    """(clusters, false_clusters, false_pairs): clusters (ent_id, canonical_id) that hold several gold ids (ent_id, gold_id), and the pairs they join wrongly."""
    per = clusters.join(gold, "ent_id").groupBy("canonical_id", "gold_id").agg(F.count("*").alias("n"))
    rows = per.groupBy("canonical_id").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("sq"), F.count("*").alias("golds"))
    wrong = (F.col("n") * F.col("n") - F.col("sq")) / 2
    return rows.agg(F.count("*").alias("clusters"), F.count_if(F.col("golds") > 1).alias("false_clusters"), F.coalesce(F.sum(wrong), F.lit(0.0)).cast("long").alias("false_pairs"))


def alias_counts(ents: DataFrame) -> DataFrame:
    """(entities, aliases_per_entity)."""
    return ents.agg(F.count("*").alias("entities"), F.round(F.avg(F.size("aliases")), 6).alias("aliases_per_entity"))


def blocking_quality(pairs: DataFrame, gold_pairs: DataFrame, n: int) -> DataFrame:
    """(candidates, gold, kept, completeness, reduction) of candidate pairs over n entities."""
    g = gold_pairs.select("left_id", "right_id").distinct().withColumn("__g", F.lit(1))
    rows = pairs.select("left_id", "right_id").distinct().withColumn("__p", F.lit(1)).join(g, ["left_id", "right_id"], "full")
    rows = rows.agg(F.count_if(F.col("__p") == 1).alias("candidates"), F.count_if(F.col("__g") == 1).alias("gold"), F.count_if((F.col("__p") == 1) & (F.col("__g") == 1)).alias("kept"))
    return rows.withColumn("completeness", _ratio(F.col("kept"), F.col("gold"))).withColumn("reduction", F.round(1 - F.col("candidates") / (n * (n - 1) / 2), 6))


def accuracy_dimensions(pairs: DataFrame) -> DataFrame:
    """(dimension, pct) and their mean for (dimension, ok) checks against a gold document."""
    each = pairs.groupBy("dimension").agg(F.round(100 * F.avg(F.col("ok").cast("double")), 4).alias("pct"))
    return each.unionByName(each.agg(F.round(F.avg("pct"), 4).alias("pct")).select(F.lit("mean").alias("dimension"), "pct"))


def route_confusion(routed: DataFrame, legacy: DataFrame) -> DataFrame:
    """(route, legacy, docs, pages_lost, pages_wasted): pages to be read by vision in documents sent to text, and text pages sent to vision, by the legacy guess."""
    rows = routed.join(legacy, "doc_id")
    return rows.groupBy("route", "legacy").agg(F.count("*").alias("docs"), F.sum(F.when(F.col("legacy") == "text", F.col("n_ocr")).otherwise(0)).alias("pages_lost"),
                                               F.sum(F.when(F.col("legacy") == "ocr", F.col("n_text")).otherwise(0)).alias("pages_wasted"))


def simulate_workers(durations: list[float], k: int) -> dict[str, float]:
    """Makespan and mean wait of jobs taken in order by k workers (a small list)."""
    import heapq

    free, waits = [0.0] * k, 0.0
    for d in durations:
        t = heapq.heappop(free)
        waits += t
        heapq.heappush(free, t + d)
    return {"workers": k, "makespan": max(free), "mean_wait": waits / max(1, len(durations))}
