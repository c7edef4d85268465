"""Intake: heterogeneous messages to one record type, locations, format routing, readers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

RAW = ("struct<_id:struct<`$oid`:string>,id:string,recordId:string,createdAt:string,created_at:string,timestamp:string,filePath:string,file_path:string,mimeType:string,mime_type:string,"
       "title:string,report_text:string,content:string,text:string,seq:long>")

#: Handlers by MIME type, then by extension.
HANDLERS = {"application/pdf": "pdf", "application/vnd.openxmlformats-officedocument.spreadsheetml.sheet": "xlsx", "application/vnd.openxmlformats-officedocument.wordprocessingml.document": "docx",
            "application/vnd.openxmlformats-officedocument.presentationml.presentation": "pptx", "image/png": "image", "image/jpeg": "image", "text/plain": "text", "text/html": "html"}
EXTENSIONS = {"pdf": "pdf", "xlsx": "xlsx", "docx": "docx", "pptx": "pptx", "png": "image", "jpg": "image", "jpeg": "image", "txt": "text", "html": "html", "htm": "html"}


def normalize_records(raw: DataFrame, json_col: str = "value") -> DataFrame:
    """Records from JSON messages with nested or flat ids, camel or snake fields and several content fields; unread messages keep null fields and stay in ``raw``."""
    j = F.from_json(json_col, RAW)
    rows = raw.select(j.alias("j"), F.col(json_col).alias("raw"))
    path = F.coalesce("j.filePath", "j.file_path")
    ts = F.coalesce(*[F.try_to_timestamp(F.col(f"j.{c}")) for c in ("createdAt", "created_at", "timestamp")])
    return rows.select(F.coalesce(F.col("j._id")["$oid"], F.col("j.id"), F.col("j.recordId")).alias("record_id"), F.when(path.isNotNull(), "file").otherwise("inline").alias("kind"), path.alias("path"),
                       F.coalesce("j.mimeType", "j.mime_type").alias("mime"), F.nullif(F.lower(F.regexp_extract(F.coalesce(path, F.lit("")), r"\.([A-Za-z0-9]+)$", 1)), F.lit("")).alias("ext"), F.col("j.title").alias("title"),
                       F.coalesce("j.report_text", "j.content", "j.text").alias("text"), ts.alias("ts"), F.col("j.seq").alias("seq"), "raw")


def resolve_location(records: DataFrame, base: str) -> DataFrame:
    """Adds ``location``: base / MIME sub-directory / path of file records."""
    sub = F.coalesce(F.regexp_replace("mime", "[^a-z0-9]+", "_"), F.lit("unknown"))
    return records.withColumn("location", F.when(F.col("kind") == "file", F.concat_ws("/", F.lit(base.rstrip("/")), sub, "path")))


def route_format(records: DataFrame) -> DataFrame:
    """Adds ``handler`` by MIME type, then extension; inline records are text, the rest unknown."""
    known = lambda col, d: [F.when(F.lower(col) == k, v) for k, v in d.items()]
    return records.withColumn("handler", F.coalesce(*known(F.col("mime"), HANDLERS), *known(F.col("ext"), EXTENSIONS), F.when(F.col("kind") == "inline", "text"), F.lit("unknown")))


def unify(*frames: DataFrame) -> DataFrame:
    """Chunks of all handlers as one table; missing columns are null."""
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f, allowMissingColumns=True)
    return out


def kafka_options(servers: str, topic: str, session_ms: int = 300_000, poll_ms: int = 1_800_000, per_batch: int = 16) -> dict[str, str]:
    """Options of the Kafka source; the source keeps its own offsets, so an eviction only delays a batch."""
    return {"kafka.bootstrap.servers": servers, "subscribe": topic, "kafka.session.timeout.ms": str(session_ms), "kafka.max.poll.interval.ms": str(poll_ms), "maxOffsetsPerTrigger": str(per_batch)}


def read_any(spark: SparkSession, path: str, fmt: str = "parquet", **options) -> DataFrame:
    """Parquet, JSON lines, CSV, text or binaryFile."""
    if fmt not in ("parquet", "json", "csv", "text", "binaryFile", "orc"):
        raise ValueError(fmt)
    return spark.read.format(fmt).options(**options).load(path)


def write_results(results: DataFrame, path: str, fmt: str = "json", partitions: int | None = None, one_file_per_doc: bool = False, id_col: str = "doc_id") -> None:
    """Result envelopes as JSON lines or Parquet. At scale few large files, dealt by a hash of the id; one file for each document only on request."""
    out = results if fmt == "parquet" else results.select(id_col, F.to_json(F.struct("*")).alias("value"))
    if one_file_per_doc:
        out.repartition(id_col).write.mode("overwrite").partitionBy(id_col).format("parquet" if fmt == "parquet" else "text").save(path)
        return
    out = out.repartition(partitions, id_col) if partitions else out
    (out.write.mode("overwrite").parquet(path) if fmt == "parquet" else out.select("value").write.mode("overwrite").text(path))


def result_envelopes(ents: DataFrame, rels: DataFrame, pairs: DataFrame, ids: DataFrame) -> DataFrame:
    """(doc_id, entities, relationships, dedup_candidates): nested results, empty arrays where a document has none; groups are single documents."""
    def nest(df, name):
        cols = sorted(c for c in df.columns if c != "doc_id")
        return df.groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct(*cols))).alias(name))

    out = ids.select("doc_id").distinct()
    for df, name in ((ents, "entities"), (rels, "relationships"), (pairs, "dedup_candidates")):
        n = nest(df, name)
        out = out.join(n, "doc_id", "left").withColumn(name, F.coalesce(name, F.array().cast(dict(n.dtypes)[name])))
    return out


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int, path: str) -> DataFrame:
    """``df`` as a bucketed, sorted external table: later joins and aggregates on ``key`` with tables of as many buckets need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(name)
    return df.sparkSession.table(name)
