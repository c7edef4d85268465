"""Cross-document entity resolution: render, embed, block, score, decide, cluster, collect."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT
from kgrefine.functions import strings as S
from kgrefine.plans.components import connected_components

from .ontology import dot


def render_entity(ents: DataFrame) -> DataFrame:
    """Adds ``rendered``: name, type, sorted properties and aliases as one text."""
    props = F.array_join(F.transform(F.array_sort(F.map_entries("props")), lambda e: F.concat(e["key"], F.lit("="), e["value"])), "; ") if "props" in ents.columns else F.lit("")
    aliases = F.array_join(F.array_sort("aliases"), ", ") if "aliases" in ents.columns else F.lit("")
    return ents.withColumn("rendered", F.concat_ws(" | ", "name", "type", props, aliases))


def embed_hash(text: Column, dim: int = 64) -> Column:
    """A unit vector drawn from the text's hash: equal texts are equal, all others about orthogonal. JVM only."""
    raw = F.transform(F.sequence(F.lit(1), F.lit(dim)), lambda i: F.xxhash64(text, i).cast("double") / float(2**63))
    return F.transform(F.array(raw), lambda v: F.transform(v, lambda x: x / F.sqrt(dot(v, v))))[0]


def embed_ngrams(df: DataFrame, text_col: str, out: str = "vec", dim: int = 64, n: int = 3) -> DataFrame:
    """An offline stand-in for a semantic embedder: hashed character n-grams, signed and normalised, in Arrow batches."""
    from zlib import crc32

    def go(a: pa.Array) -> pa.Array:
        rows = []
        for t in a.to_pylist():
            v = np.zeros(dim)
            s = f" {(t or '').lower()} "
            for i in range(max(1, len(s) - n + 1)):
                h = crc32(s[i : i + n].encode())
                v[h % dim] += 1 if h >> 16 & 1 else -1
            rows.append((v / (np.linalg.norm(v) or 1)).tolist())
        return pa.array(rows, pa.list_(pa.float64()))

    return df.withColumn(out, F.arrow_udf(go, "array<double>")(F.col(text_col)))


def embed_batches(df: DataFrame, call, text_col: str = "text", out: str = "vec", batch: int = DEFAULT.embed_batch) -> DataFrame:
    """Back-fill through ``call(list of texts) -> list of vectors or None``: batches of ``batch``; members of a failed call, or without a vector, are tried alone.

    Parallel calls are tasks: set the number of partitions for the number in flight.
    """
    cols = df.columns
    at = cols.index(text_col)

    def one(text):
        try:
            return call([text])[0]
        except Exception:  # noqa: BLE001  the provider's errors are its own
            return None

    def go(batches):
        for b in batches:
            texts, got = b.column(at).to_pylist(), []
            for i in range(0, len(texts), batch):
                part = texts[i : i + batch]
                try:
                    vecs = list(call(part))
                except Exception:  # noqa: BLE001
                    vecs = [None] * len(part)
                got += [v if v is not None else one(t) for t, v in zip(part, vecs, strict=True)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got, pa.list_(pa.float64()))], [*b.schema.names, out])

    from pyspark.sql import types as T

    return df.mapInArrow(go, T.StructType([*df.schema.fields, T.StructField(out, T.ArrayType(T.DoubleType()))]))


def block_vector(vecs: DataFrame, k: int = DEFAULT.neighbours, method: str = "exact", slab: int = 8192, tables: int = 8, bits: int | None = None, seed: int = 5, bucket_rows: int = 16, probes: int = 4) -> DataFrame:
    """(left_id, right_id, cos): pairs of a row with one of its k nearest by cosine, left_id < right_id.

    ``exact`` meets packed slabs of rows with each other, keeps k of each tile and merges by a window
    limit. ``lsh`` compares rows that share a bucket of signed random projections in one of ``tables``;
    ``bits`` defaults to as many (at least 12) as leave about ``bucket_rows`` rows to a bucket, so pairs
    grow with the rows and not with their square. ``ivf`` puts each row into the nearest of the cells that
    k-means finds on a sample of about 20,000 rows, and compares it with the rows of its ``probes`` nearest.
    """
    rows = vecs.select(F.col("vec_id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec")).where("vec is not null")
    if method == "lsh":
        bits = bits or max(12, math.ceil(math.log2(max(1, rows.count() / bucket_rows))))
        planes = np.random.default_rng(seed).normal(size=(tables * bits, vecs.select(F.max(F.size("vec"))).first()[0] or 1))

        def keys(batches):
            for b in batches:
                x = np.array(b.column(1).to_pylist(), dtype=np.float64)
                side = (x @ planes.T > 0).reshape(len(x), tables, bits) if len(x) else np.zeros((0, tables, bits), bool)
                key = (side * (1 << np.arange(bits))).sum(axis=2) + (np.arange(tables) << bits)
                n = np.repeat(np.arange(len(x)), tables)
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(n)), pa.array(key.ravel().astype(np.int64))], ["id", "key"])

        put = rows.mapInArrow(keys, "id long, key long")
        asks = put
    elif method == "ivf":
        put, asks = _cells(rows, seed, probes)
    if method in ("lsh", "ivf"):
        met = asks.withColumnRenamed("id", "a").join(put.withColumnRenamed("id", "b"), "key").where("a <> b").select("a", "b").distinct()
        cos = met.join(rows.select(F.col("id").alias("a"), F.col("vec").alias("x")), "a").join(rows.select(F.col("id").alias("b"), F.col("vec").alias("y")), "b")
        near = cos.select("a", "b", (dot(F.col("x"), F.col("y")) / F.sqrt(dot(F.col("x"), F.col("x")) * dot(F.col("y"), F.col("y")))).alias("cos"))
    else:
        n = max(1, math.ceil(rows.count() / slab))
        put = rows.withColumn("s", F.pmod(F.xxhash64("id"), F.lit(n)).cast("int"))
        every = F.sequence(F.lit(0), F.lit(n - 1))
        left = put.select("id", "vec", "s", F.explode(every).alias("o"))
        right = put.select(F.col("id").alias("id2"), F.col("vec").alias("vec2"), F.explode(every).alias("s2"), F.col("s").alias("o2"))

        def tile(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
            if x.empty or y.empty:
                return pd.DataFrame({"a": pd.Series(dtype="int64"), "b": pd.Series(dtype="int64"), "cos": pd.Series(dtype="float64")})
            unit = lambda m: m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)
            a, b = unit(np.stack(x["vec"].to_numpy())), unit(np.stack(y["vec2"].to_numpy()))
            xi, yi, out = x["id"].to_numpy(), y["id2"].to_numpy(), []
            for at in range(0, len(a), 512):
                cos = a[at : at + 512] @ b.T
                cos[xi[at : at + 512, None] == yi[None, :]] = -2
                take = np.argsort(-cos, axis=1, kind="stable")[:, :k]
                out.append(pd.DataFrame({"a": np.repeat(xi[at : at + 512], take.shape[1]), "b": yi[take].ravel(), "cos": np.take_along_axis(cos, take, 1).ravel()}))
            return pd.concat(out)

        near = left.groupBy("s", "o").cogroup(right.groupBy("s2", "o2")).applyInPandas(tile, "a long, b long, cos double").where("cos > -2")
    top = near.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("cos"), "b"))).where(F.col("r") <= k)
    return top.groupBy(F.least("a", "b").alias("left_id"), F.greatest("a", "b").alias("right_id")).agg(F.max("cos").alias("cos"))


def _cells(rows: DataFrame, seed: int, probes: int, sample_rows: int = 20_000, cell_rows: int = 64, most_cells: int = 65_536) -> tuple[DataFrame, DataFrame]:
    """((id, key) of each row's cell, (id, key) of its ``probes`` nearest cells), by k-means on unit vectors of a bounded sample."""
    n = rows.count()
    chance = F.shiftrightunsigned(F.xxhash64("id", F.lit(seed)), 11) / float(2**53)
    sample = np.array([r["vec"] for r in rows.where(chance < sample_rows / max(n, 1)).orderBy("id").limit(2 * sample_rows).collect()], dtype=np.float64)
    unit = lambda m: m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300)
    count = int(min(max(1, math.ceil(n / cell_rows)), most_cells, max(1, len(sample))))
    centres = unit(sample[np.random.default_rng(seed).permutation(len(sample))[:count]]) if len(sample) else np.zeros((0, 1))
    for _ in range(8):
        at = (unit(sample) @ centres.T).argmax(axis=1) if len(sample) else np.zeros(0, dtype=int)
        total = np.zeros_like(centres)
        np.add.at(total, at, unit(sample) if len(sample) else sample)
        centres = np.where(np.linalg.norm(total, axis=1, keepdims=True) > 0, unit(total), centres)
    shared = rows.sparkSession.sparkContext.broadcast(centres)

    def nearest(k):
        def go(batches):
            for b in batches:
                if b.num_rows:
                    order = np.argsort(-(np.array(b.column(1).to_pylist(), dtype=np.float64) @ shared.value.T), axis=1, kind="stable")[:, :k]
                    who = np.repeat(np.arange(len(order)), order.shape[1])
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(who)), pa.array(order.ravel().astype(np.int64))], ["id", "key"])

        return rows.mapInArrow(go, "id long, key long")

    return nearest(1), nearest(probes)


def block_phonetic(ents: DataFrame) -> DataFrame:
    """(left_id, right_id): entities (ent_id, name) whose sorted phonetic token codes are equal; codes are worked out once for each distinct name."""
    codes = ents.select("name").distinct().select("name", F.array_join(F.array_sort(S.phonetic(F.col("name"))), "-").alias("code"))
    keyed = ents.select("ent_id", "name").join(codes, "name").select("ent_id", "code")
    return keyed.withColumnRenamed("ent_id", "left_id").join(keyed.withColumnRenamed("ent_id", "right_id"), "code").where("left_id < right_id").select("left_id", "right_id")


def block_all(ents: DataFrame, scope: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """(left_id, right_id): every pair of one scope, the baseline that blocks are measured against; a scope is a document, never the table."""
    a, b = (ents.select(*scope, F.col("ent_id").alias(i)) for i in ("left_id", "right_id"))
    return a.join(b, list(scope)).where("left_id < right_id").select("left_id", "right_id")


def block_union(**blocks: DataFrame) -> DataFrame:
    """(left_id, right_id, sources): distinct pairs of all blocks with the sorted names of those that hold them."""
    every = None
    for name, b in blocks.items():
        b = b.select("left_id", "right_id", F.lit(name).alias("src"))
        every = b if every is None else every.unionByName(b)
    return every.groupBy("left_id", "right_id").agg(F.array_sort(F.collect_set("src")).alias("sources"))


#: Attributes two different values of which make two entities different.
DISCRIMINATORS = ("dob", "nationality", "gender", "passport_no", "employee_no")


def hard_conflict(a: Column, b: Column, keys: tuple[str, ...] = DISCRIMINATORS) -> Column:
    """Whether two property maps hold different values of a discriminator, case folded; null never conflicts."""
    return F.coalesce(F.exists(F.array(*[F.lit(k) for k in keys]), lambda k: F.coalesce(F.lower(a[k]) != F.lower(b[k]), F.lit(False))), F.lit(False))


def property_score(a: Column, b: Column) -> Column:
    """(agreeing - 2 * conflicting) / shared properties, held to [0, 1]."""
    shared = F.array_intersect(F.map_keys(a), F.map_keys(b))
    agree = F.size(F.filter(shared, lambda k: F.lower(a[k]) == F.lower(b[k])))
    clash = F.size(F.filter(shared, lambda k: F.lower(a[k]) != F.lower(b[k])))
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), (agree - 2 * clash) / F.greatest(F.size(shared), F.lit(1))))


#: Fixed values.
RESOLVE_WEIGHTS = {"name": 0.25, "cosine": 0.20, "properties": 0.15, "phonetic": 0.10, "types": 0.10, "aliases": 0.10, "proximity": 0.10}
TYPE_FAMILIES = {"INDIVIDUAL": "PERSON", "OFFICER": "PERSON", "AGENCY": "ORGANIZATION", "PLACE": "LOCATION"}


def score_pairs(pairs: DataFrame, ents: DataFrame, weights: dict[str, float] = RESOLVE_WEIGHTS, type_families: dict[str, str] = TYPE_FAMILIES, keys: tuple[str, ...] = DISCRIMINATORS) -> DataFrame:
    """Adds ``score``, the seven signals and ``conflict`` to (left_id, right_id, ...).

    ``ents``: ent_id, name, type, vec, aliases, props, doc_id, chunk_no. Pairs in hard conflict keep their
    row but no kernel runs on them.
    """
    cols = ("name", "type", "vec", "aliases", "props", "doc_id", "chunk_no")
    side = lambda s, i: ents.select(F.col("ent_id").alias(i), *[F.col(c).alias(f"{c}_{s}") for c in cols])
    rows = pairs.join(side("a", "left_id"), "left_id").join(side("b", "right_id"), "right_id").withColumn("conflict", hard_conflict(F.col("props_a"), F.col("props_b"), keys))
    open_ = rows.where("not conflict")
    x, y = S.norm_name(F.col("name_a")), S.norm_name(F.col("name_b"))
    names = open_.select(x.alias("a"), y.alias("b")).distinct().withColumn("name", S.jaro_winkler(F.col("a"), F.col("b")))
    names = names.withColumn("p1", S.phonetic(F.col("a"))).withColumn("p2", S.phonetic(F.col("a"), True)).withColumn("q1", S.phonetic(F.col("b"))).withColumn("q2", S.phonetic(F.col("b"), True))
    names = names.select("a", "b", "name", S.phonetic_overlap(F.col("p1"), F.col("p2"), F.col("q1"), F.col("q2")).alias("phonetic"))
    family = lambda t: F.coalesce(*[F.when(t == k, v) for k, v in type_families.items()], t)
    rows = rows.withColumn("a", x).withColumn("b", y).join(names, ["a", "b"], "left")
    cos = F.greatest(F.lit(0.0), dot(F.col("vec_a"), F.col("vec_b")))
    meet, both = F.size(F.array_intersect("aliases_a", "aliases_b")), F.size(F.array_union("aliases_a", "aliases_b"))
    near = F.when(F.col("doc_id_a") == F.col("doc_id_b"), F.when(F.col("chunk_no_a") == F.col("chunk_no_b"), 1.0).when(F.abs(F.col("chunk_no_a") - F.col("chunk_no_b")) == 1, 0.5).otherwise(0.25)).otherwise(0.0)
    rows = rows.withColumns({"cosine": cos, "aliases": F.when(meet > 0, 1.0).otherwise(meet / F.greatest(both, F.lit(1))), "properties": property_score(F.col("props_a"), F.col("props_b")),
                             "types": F.when(family(F.col("type_a")) == family(F.col("type_b")), 1.0).otherwise(0.0), "proximity": near})
    score = sum((F.coalesce(F.col(k), F.lit(0.0)) * w for k, w in weights.items()), F.lit(0.0))
    return rows.withColumn("score", F.when(F.col("conflict"), F.lit(0.0)).otherwise(score)).select(*pairs.columns, "score", *weights, "conflict", "name_a", "name_b")


CODENAME = r"^[\"'“][^\"'”]+[\"'”]$|^[A-Z]{3,}$|^(?i:operation) |(?i:codename)"


def decide_resolution(scored: DataFrame, auto: float = DEFAULT.resolve_auto, review: float = DEFAULT.resolve_review, codename: float = DEFAULT.resolve_codename, pattern: str = CODENAME) -> DataFrame:
    """Adds ``action``: a conflict is distinct whatever the score; then auto, review, codename candidate, distinct."""
    coded = F.col("name_a").rlike(pattern) | F.col("name_b").rlike(pattern)
    action = F.when(F.col("conflict"), "distinct").when(F.col("score") >= auto, "auto_merge").when(F.col("score") >= review, "manual_review").when((F.col("score") >= codename) & coded, "codename_candidate").otherwise("distinct")
    return scored.withColumn("action", action)


def clusters(merged: DataFrame, ents: DataFrame, keys: tuple[str, ...] = DISCRIMINATORS) -> DataFrame:
    """(ent_id, canonical_id) of auto-merged pairs (left_id, right_id, score), no cluster with two values of a discriminator.

    Components first; only those with a conflict are taken apart: their edges are admitted again in
    falling score, skipping any that would join two values. A group is one conflicting component. An
    entity whose edges are all skipped is its own cluster; ``with_partner`` leaves it out.
    """
    comp = connected_components(merged, "left_id", "right_id").withColumnRenamed("node", "ent_id")
    props = ents.select(F.col("ent_id").cast("long").alias("ent_id"), "props")
    known = comp.join(props, "ent_id")
    clash = F.lit(False)
    aggs = [F.count_distinct(F.lower(F.col("props")[k])).alias(f"k{i}") for i, k in enumerate(keys)]
    for i in range(len(keys)):
        clash = clash | (F.col(f"k{i}") > 1)
    bad = known.groupBy("component").agg(*aggs).where(clash).select("component")
    fine = comp.join(bad, "component", "left_anti").select("ent_id", F.col("component").alias("canonical_id"))
    values = F.array(*[F.lower(F.col("props")[k]) for k in keys])
    nodes = known.join(bad, "component", "left_semi").select("component", "ent_id", values.alias("vals"))
    edges = merged.select(F.col("left_id").cast("long").alias("ent_id"), F.col("right_id").cast("long").alias("right_id"), "score").join(comp, "ent_id").join(bad, "component", "left_semi").select(
        F.col("component").alias("component2"), F.col("ent_id").alias("left_id"), "right_id", "score")

    def admit(n: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        root = {i: i for i in n["ent_id"]}
        held = {i: list(v) for i, v in zip(n["ent_id"], n["vals"], strict=True)}

        def find(i):
            while root[i] != i:
                i = root[i]
            return i

        for left, right in e.sort_values(["score", "left_id", "right_id"], ascending=[False, True, True])[["left_id", "right_id"]].itertuples(index=False):
            a, b = find(left), find(right)
            if a != b and not any(x is not None and y is not None and x != y for x, y in zip(held[a], held[b], strict=True)):
                a, b = min(a, b), max(a, b)
                root[b] = a
                held[a] = [y if x is None else x for x, y in zip(held[a], held[b], strict=True)]
        return pd.DataFrame({"ent_id": list(root), "canonical_id": [find(i) for i in root]}).astype("int64")

    split = nodes.groupBy("component").cogroup(edges.groupBy("component2")).applyInPandas(admit, "ent_id long, canonical_id long")
    return fine.unionByName(split)


def with_partner(canon: DataFrame) -> DataFrame:
    """Rows of (ent_id, canonical_id) whose cluster has two members or more: an entity whose merges were all refused has none."""
    several = canon.where("ent_id <> canonical_id").select("canonical_id").distinct()
    return canon.join(several, "canonical_id", "left_semi").select("ent_id", "canonical_id")


def collect_resolution(ents: DataFrame, canon: DataFrame, decided: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(merged entities, id map of all entities, decisions, review queue)."""
    ids = ents.select(F.col("ent_id").cast("long").alias("ent_id"), "name").join(canon, "ent_id", "left").select("ent_id", "name", F.coalesce("canonical_id", "ent_id").alias("canonical_id"))
    merged = ids.groupBy("canonical_id").agg(F.array_sort(F.collect_set("name")).alias("names"), F.count("*").alias("members"))
    decisions = decided.select("left_id", "right_id", "score", "action", "conflict")
    return merged, ids.select("ent_id", "canonical_id"), decisions, decisions.where("action in ('manual_review', 'codename_candidate')")


def review_queue(rule: DataFrame, embedded: DataFrame) -> DataFrame:
    """(left_id, right_id, layer): one queue of both layers; a pair of both is the rule layer's."""
    both = rule.select("left_id", "right_id", F.lit(1).alias("n")).unionByName(embedded.select("left_id", "right_id", F.lit(2).alias("n")))
    return both.groupBy("left_id", "right_id").agg(F.min("n").alias("n")).select("left_id", "right_id", F.when(F.col("n") == 1, "rule").otherwise("embedding").alias("layer"))


class ResolutionStore:
    """Entities of earlier runs as Parquet, partitioned by a block key; only new ones meet the stored."""

    def __init__(self, spark, path: str, parts: int = 64):
        self.spark, self.path, self.parts = spark, path, parts

    def read(self) -> DataFrame | None:
        from pyspark.errors import AnalysisException

        try:
            return self.spark.read.parquet(self.path)
        except AnalysisException:
            return None

    def unseen(self, ents: DataFrame) -> DataFrame:
        old = self.read()
        return ents if old is None else ents.join(old.select("ent_id"), "ent_id", "left_anti")

    def upsert(self, ents: DataFrame) -> None:
        block = F.pmod(F.xxhash64(F.array_join(F.array_sort(S.phonetic(F.col("name"))), "-")), F.lit(self.parts)).cast("int")
        self.unseen(ents).withColumn("block", block).repartition("block").write.mode("append").partitionBy("block").parquet(self.path)

    def pairs(self, ents: DataFrame) -> DataFrame:
        """(left_id, right_id): new entities with stored ones of the same phonetic code."""
        old = self.read()
        code = lambda df, i: df.select(F.col("ent_id").alias(i), F.array_join(F.array_sort(S.phonetic(F.col("name"))), "-").alias("code"))
        return code(self.unseen(ents), "left_id").join(code(old, "right_id"), "code").select("left_id", "right_id")
