"""One query for each operator, over whole tables, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import attribution, blockmax, hashtree, mixing, packing, preference, simhash, sites, toxicity, winnowing


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_blockmax_topk(spark, sf_dir):
    rows = _table(spark, sf_dir, "embeddings").select("vec_id", blockmax.integer_terms(F.col("embedding")).alias("terms"))
    return blockmax.topk_search(rows, rows.where("vec_id % 20 = 0"), k=20)


def op2_preference_format(spark, sf_dir):
    return preference.format_preferences(*preference.regenerated_pairs(_table(spark, sf_dir, "conversations")))


def op3_mix_sources(spark, sf_dir):
    return mixing.mix_sources(_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "source")


def op4_token_attribution(spark, sf_dir):
    return attribution.attribute_tokens(_table(spark, sf_dir, "documents"), rule="start")


def op5_simhash_groups(spark, sf_dir):
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return simhash.simhash_groups(_table(spark, sf_dir, "documents")).select("doc_id", hexed.alias("fingerprint"), "component_id")


def op6_winnowing(spark, sf_dir):
    rows = winnowing.edited_pairs(_table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_chars", "edited_sha256", winnowing.digest(F.col("chosen")).alias("fingerprint"),
                       winnowing.digest(F.col("edited_chosen")).alias("edited_fingerprint"), "near_edited", "near_next")


def op7_hash_tree(spark, sf_dir):
    tree = hashtree.balanced_tree(40)
    rows = hashtree.shard_documents(_table(spark, sf_dir, "documents"), tree, hashtree.grown(tree))
    return rows.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op8_vector_packing(spark, sf_dir):
    return packing.pack_documents(_table(spark, sf_dir, "documents"))


def op9_site_quality(spark, sf_dir):
    return sites.quality_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op10_string_kernel_toxicity(spark, sf_dir):
    return toxicity.toxicity_scores(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    found = [op1_blockmax_topk, op2_preference_format, op3_mix_sources, op4_token_attribution, op5_simhash_groups, op6_winnowing, op7_hash_tree,
             op8_vector_packing, op9_site_quality, op10_string_kernel_toxicity, pipeline]
    return {f.__name__: f for f in found}


OP1_SQL = """
with t as (
  select vec_id, list_transform(embedding, lambda x: cast(floor(64 * cast(x as double)) as bigint)) as terms
  from embeddings
  where embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), s as (
  select q.vec_id as query_id, d.vec_id as vec_id,
         cast(list_sum(list_transform(list_zip(q.terms, d.terms), lambda p: p[1] * p[2])) as bigint) as score
  from t q join t d on d.vec_id <> q.vec_id where q.vec_id % 20 = 0
), r as (
  select query_id, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank, vec_id, score from s
)
select query_id, rank, vec_id, score from r where rank <= 20
"""

OP2_SQL = """
with a as (
  select conv_id as pair_id, turn, role, text, row_number() over (partition by conv_id order by turn, role, text) as pos
  from conversations where conv_id is not null
), b as (
  select *, max(case when role = 'assistant' then pos end) over (partition by pair_id) as last_pos,
         last_value(case when role = 'assistant' then text end ignore nulls) over (partition by pair_id order by pos rows between unbounded preceding and 1 preceding) as earlier,
         lag(text) over (partition by pair_id order by pos) as echo
  from a
), c as (
  select *, case when pos = last_pos then coalesce(earlier, echo) else text end as other from b where pos <= last_pos
), d as (
  select *, min(case when text is distinct from other then pos end) over (partition by pair_id) as cut from c
), e as (
  select pair_id, pos, role, text, case when cut is null or pos < cut then 'prompt' else 'chosen' end as part from d
  union all
  select pair_id, pos, role, other, 'rejected' from d where pos >= cut
), f as (
  select *, '<|' || coalesce(role, '') || '|>' || chr(10) || coalesce(text, '') || chr(10) as rendered from e
)
select pair_id, part, cast(row_number() over w as integer) as seq, role, rendered,
       cast(sum(length(rendered)) over w - length(rendered) as bigint) as char_start, cast(sum(length(rendered)) over w as bigint) as char_end,
       part <> 'prompt' and coalesce(role = 'assistant', false) as loss
from f window w as (partition by pair_id, part order by pos)
"""


def oracle_sql() -> dict:
    return {"op1_blockmax_topk": OP1_SQL, "op2_preference_format": OP2_SQL}
