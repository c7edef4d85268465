"""The relational surface around the methods: one query and its SQL for each kind of operation."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgrefine.sources.views import table as t

QUERIES: dict = {}
SQL: dict[str, str] = {}


def q(sql: str | None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


@q("select l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * (1 - l_discount), 4) as net from lineitem")
def scan_project(s, d):
    return t(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@q("select p_partkey, p_name from part where (p_size between 10 and 30 and p_brand in ('Brand#11', 'Brand#12', 'Brand#23', 'Brand#34')) or p_name like 'hot%' or p_type is null")
def filter_predicates(s, d):
    p = t(s, d, "part")
    return p.where((F.col("p_size").between(10, 30) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23", "Brand#34")) | F.col("p_name").like("hot%") | F.col("p_type").isNull()).select("p_partkey", "p_name")


@q("select n_name, r_name from nation join region on n_regionkey = r_regionkey")
def join_broadcast(s, d):
    # region is an upper-level class table of fixed size
    return t(s, d, "nation").join(F.broadcast(t(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")


@q("select l_orderkey, l_linenumber, l_partkey, o_custkey from lineitem join orders on l_orderkey = o_orderkey where o_orderstatus = 'F'")
def join_sort_merge(s, d):
    o = t(s, d, "orders").where("o_orderstatus = 'F'").hint("merge")
    return t(s, d, "lineitem").join(o, F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "l_partkey", "o_custkey")


@q("select p_brand, count(*) as n, cast(sum(l_quantity) as bigint) as qty from lineitem join part on l_partkey = p_partkey group by p_brand")
def join_shuffle_hash(s, d):
    rows = t(s, d, "lineitem").join(t(s, d, "part").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey"))
    return rows.groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"))


@q("select coalesce(d.doc_id, l.doc_id) as doc_id, d.lang, l.quality, l.toxic from documents d full join labels l on d.doc_id = l.doc_id")
def join_left_full_outer(s, d):
    return t(s, d, "documents").select("doc_id", "lang").join(t(s, d, "labels"), "doc_id", "full").select("doc_id", "lang", "quality", "toxic")


@q("""select doc_id, 'labelled' as side from documents where doc_id in (select doc_id from labels)
union all select doc_id, 'bare' as side from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id)""")
def join_semi_anti(s, d):
    docs, l = t(s, d, "documents").select("doc_id"), t(s, d, "labels").select("doc_id")
    return docs.join(l, "doc_id", "left_semi").withColumn("side", F.lit("labelled")).unionByName(docs.join(l, "doc_id", "left_anti").withColumn("side", F.lit("bare")))


@q("""select c_custkey, band from customer join (values ('low', -1e9, 0.0), ('mid', 0.0, 5000.0), ('high', 5000.0, 1e9)) b(band, lo, hi) on c_acctbal >= lo and c_acctbal < hi""")
def join_theta_range(s, d):
    bands = s.createDataFrame([("low", -1e9, 0.0), ("mid", 0.0, 5000.0), ("high", 5000.0, 1e9)], "band string, lo double, hi double")
    return t(s, d, "customer").join(F.broadcast(bands), (F.col("c_acctbal") >= F.col("lo")) & (F.col("c_acctbal") < F.col("hi"))).select("c_custkey", "band")


@q("""select p.event_id as purchase_id, e.event_id as error_id from events p join events e on p.user_id = e.user_id and e.ts <= p.ts and e.ts >= p.ts - interval 10 minute
where p.event_type = 'purchase' and e.event_type = 'error'""")
def join_interval(s, d):
    e = t(s, d, "events")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("ts").alias("p_ts"), "user_id")
    x = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("ts").alias("e_ts"), "user_id")
    return p.join(x, "user_id").where("e_ts <= p_ts and e_ts >= p_ts - interval 10 minutes").select("purchase_id", "error_id")


@q("""select p.event_id as purchase_id, (select max(s.event_id) from events s where s.event_type = 'signup' and s.user_id = p.user_id and s.ts <= p.ts
and s.ts = (select max(z.ts) from events z where z.event_type = 'signup' and z.user_id = p.user_id and z.ts <= p.ts)) as signup_id from events p where p.event_type = 'purchase'""")
def join_asof(s, d):
    e = t(s, d, "events").where("event_type in ('signup', 'purchase')")
    signup = F.when(F.col("event_type") == "signup", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "signup", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("signup_id", F.last(signup, ignorenulls=True).over(w)).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "signup_id")


@q("select a.p_partkey as left_key, b.p_partkey as right_key from part a join part b on a.p_name = b.p_name and a.p_brand = b.p_brand and a.p_partkey < b.p_partkey")
def join_self_pairs(s, d):
    p = t(s, d, "part").select("p_partkey", "p_name", "p_brand")
    a, b = p.withColumnRenamed("p_partkey", "left_key"), p.withColumnRenamed("p_partkey", "right_key")
    return a.join(b, ["p_name", "p_brand"]).where("left_key < right_key").select("left_key", "right_key")


@q("""select l_suppkey, l_orderkey, l_partkey, cast(rn as integer) as rn from (select *, row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_partkey, l_linenumber) as rn
from lineitem join supplier on l_suppkey = s_suppkey) where rn <= 3""")
def join_lateral_topn(s, d):
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_partkey", "l_linenumber")
    rows = t(s, d, "lineitem").join(t(s, d, "supplier").select("s_suppkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    return rows.withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("l_suppkey", "l_orderkey", "l_partkey", "rn")


@q("select l_returnflag, l_linestatus, count(*) as n, cast(sum(l_quantity) as bigint) as qty, round(avg(l_discount), 6) as disc from lineitem group by all")
def agg_group(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"))


@q("select l_suppkey, count(distinct l_partkey) as parts, count(distinct l_returnflag) as flags from lineitem group by l_suppkey")
def agg_distinct(s, d):
    return t(s, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_returnflag").alias("flags"))


@q(None)
def agg_approx_distinct(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


_GROUPED = "select l_returnflag, l_linestatus, count(*) as n, cast(grouping(l_returnflag) as integer) as g1, cast(grouping(l_linestatus) as integer) as g2 from lineitem group by "


def _grouped(df):
    return df.agg(F.count("*").alias("n"), F.grouping("l_returnflag").cast("int").alias("g1"), F.grouping("l_linestatus").cast("int").alias("g2"))


@q(_GROUPED + "rollup (l_returnflag, l_linestatus)")
def agg_rollup(s, d):
    return _grouped(t(s, d, "lineitem").rollup("l_returnflag", "l_linestatus"))


@q(_GROUPED + "cube (l_returnflag, l_linestatus)")
def agg_cube(s, d):
    return _grouped(t(s, d, "lineitem").cube("l_returnflag", "l_linestatus"))


@q(_GROUPED + "grouping sets ((l_returnflag), (l_linestatus))")
def agg_grouping_sets(s, d):
    c = [F.col("l_returnflag"), F.col("l_linestatus")]
    return _grouped(t(s, d, "lineitem").groupingSets([[c[0]], [c[1]]], *c))


@q("""select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase, count(*) filter (event_type = 'error') as error from events group by user_id""")
def agg_pivot(s, d):
    return t(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "error"]).agg(F.count(F.lit(1))).na.fill(0)


@q("select lang, round(quantile_cont(n_chars, 0.5), 4) as p50, round(quantile_cont(n_chars, 0.9), 4) as p90 from documents group by lang")
def agg_percentile(s, d):
    return t(s, d, "documents").groupBy("lang").agg(F.round(F.percentile("n_chars", 0.5), 4).alias("p50"), F.round(F.percentile("n_chars", 0.9), 4).alias("p90"))


@q("select p_name, array_to_string(list_sort(list(distinct p_brand)), ',') as brands from part group by p_name")
def agg_collect(s, d):
    return t(s, d, "part").groupBy("p_name").agg(F.array_join(F.array_sort(F.collect_set("p_brand")), ",").alias("brands"))


@q("""select l_suppkey, flag from (select l_suppkey, l_returnflag as flag, row_number() over (partition by l_suppkey order by count(*) desc, l_returnflag desc) as rn from lineitem group by l_suppkey, l_returnflag) where rn = 1""")
def agg_argmax(s, d):
    n = t(s, d, "lineitem").groupBy("l_suppkey", "l_returnflag").agg(F.count("*").alias("n"))
    return n.groupBy("l_suppkey").agg(F.max(F.struct("n", "l_returnflag"))["l_returnflag"].alias("flag"))


@q("""select l_suppkey, l_orderkey, l_partkey, l_linenumber, cast(row_number() over w as integer) as rn, cast(rank() over v as integer) as rk, cast(dense_rank() over v as integer) as dr, cast(ntile(4) over w as integer) as nt from lineitem
window w as (partition by l_suppkey order by l_quantity desc, l_orderkey, l_partkey, l_linenumber), v as (partition by l_suppkey order by l_quantity desc)""")
def win_rank(s, d):
    v = Window.partitionBy("l_suppkey").orderBy(F.desc("l_quantity"))
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_quantity"), "l_orderkey", "l_partkey", "l_linenumber")
    return t(s, d, "lineitem").select("l_suppkey", "l_orderkey", "l_partkey", "l_linenumber", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"))


@q("select conv_id, turn, lag(role) over w as before, lead(role) over w as after from conversations window w as (partition by conv_id order by turn)")
def win_lag_lead(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    return t(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"))


@q("select doc_id, source, cast(sum(n_chars // 4) over (partition by source order by n_chars desc, doc_id rows unbounded preceding) as bigint) as used from documents")
def win_running(s, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(s, d, "documents").select("doc_id", "source", F.sum(F.expr("n_chars div 4")).over(w).alias("used"))


@q("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as n from events")
def win_range(s, d):
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return t(s, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


@q("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 50")
def sort_limit(s, d):
    return t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(50).select("o_orderkey", "o_totalprice")


@q("select o_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rn from orders) where rn <= 3")
def topk_per_group(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t(s, d, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("o_custkey", "o_orderkey")


@q("select p_brand as word from part union select event_type from events")
def set_union(s, d):
    return t(s, d, "part").select(F.col("p_brand").alias("word")).union(t(s, d, "events").select("event_type")).distinct()


@q("select l_partkey as k from lineitem where l_returnflag = 'R' intersect select l_partkey from lineitem where l_returnflag = 'A'")
def set_intersect(s, d):
    li = t(s, d, "lineitem")
    return li.where("l_returnflag = 'R'").select(F.col("l_partkey").alias("k")).intersect(li.where("l_returnflag = 'A'").select("l_partkey"))


@q("select p_partkey as k from part except select l_partkey from lineitem where l_quantity > 45")
def set_except(s, d):
    return t(s, d, "part").select(F.col("p_partkey").alias("k")).subtract(t(s, d, "lineitem").where("l_quantity > 45").select("l_partkey"))


@q("select p_partkey, upper(p_name) as up, split_part(p_name, ' ', 2) as noun, replace(p_brand, '#', '-') as brand, regexp_replace(p_type, '[AEIOU]', '', 'g') as bare, cast(levenshtein(p_name, 'cold bolt') as integer) as lev from part")
def fn_string(s, d):
    return t(s, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.split_part("p_name", F.lit(" "), F.lit(2)).alias("noun"), F.regexp_replace("p_brand", "#", "-").alias("brand"),
                                  F.regexp_replace("p_type", "[AEIOU]", "").alias("bare"), F.levenshtein("p_name", F.lit("cold bolt")).alias("lev"))


@q("select o_orderkey, cast(date_trunc('month', o_orderdate) as date) as month, cast(date_diff('day', date '1990-01-01', cast(o_orderdate as date)) as integer) as days, cast(o_orderdate + interval 30 day as date) as due from orders")
def fn_date(s, d):
    day = F.col("o_orderdate").cast("date")
    return t(s, d, "orders").select("o_orderkey", F.trunc(day, "month").alias("month"), F.datediff(day, F.lit("1990-01-01").cast("date")).alias("days"), F.date_add(day, 30).alias("due"))


@q("select l_orderkey, l_linenumber, l_partkey, round(ln(l_extendedprice + 1), 6) as lg, round(sqrt(l_quantity), 6) as sq, greatest(l_tax, l_discount) as mx from lineitem")
def fn_math(s, d):
    return t(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.ln(F.col("l_extendedprice") + 1), 6).alias("lg"), F.round(F.sqrt("l_quantity"), 6).alias("sq"), F.greatest("l_tax", "l_discount").alias("mx"))


@q("select vec_id, len(list_filter(embedding, lambda x: x > 0)) as pos, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 4) as norm2 from embeddings")
def fn_array(s, d):
    sq = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"), F.round(sq, 4).alias("norm2"))


@q("""select event_id, cast(json_extract_string(props, '$.k') as bigint) as k, '{"id":' || event_id || ',"type":"' || event_type || '"}' as doc from events""")
def fn_map_json(s, d):
    k = F.from_json("props", "map<string,bigint>")["k"]
    return t(s, d, "events").select("event_id", k.alias("k"), F.to_json(F.struct(F.col("event_id").alias("id"), F.col("event_type").alias("type"))).alias("doc"))


@q("select p_partkey, round(jaro_winkler_similarity(p_name, 'cold bolt'), 6) as jw from part")
def udf_scalar(s, d):
    from kgrefine.functions.strings import jaro_winkler

    names = t(s, d, "part").select("p_name").distinct().withColumn("jw", F.round(jaro_winkler(F.col("p_name"), F.lit("cold bolt")), 6))
    return t(s, d, "part").select("p_partkey", "p_name").join(names, "p_name").select("p_partkey", "jw")


@q(None)
def udaf_wer(s, d):
    from kgrefine.measures import wer

    c = t(s, d, "conversations")
    w = Window.partitionBy("conv_id").orderBy("turn")
    rows = c.select("conv_id", "turn", "role", "text").withColumn("before", F.lag("text").over(w)).where("before is not null")
    return rows.withColumn("wer", wer(F.col("text"), F.col("before"))).groupBy("role").agg(F.round(F.avg("wer"), 6).alias("wer"), F.count("*").alias("n"))


@q("select doc_id, cast(i as integer) as chunk_no, substring(text, cast(1 + i * 500 as bigint), 500) as chunk from documents, range(0, greatest(1, cast(ceil(length(text) / 500.0) as bigint))) r(i)")
def udtf_chunks(s, d):
    from kgrefine.functions.tables import register

    register(s)
    t(s, d, "documents").select("doc_id", "text").createOrReplaceTempView("kg_documents")
    return s.sql("select doc_id, c.chunk_no, c.chunk from kg_documents, lateral kg_chunks(text, 500) c")


@q("select doc_id from documents where doc_id % 7 = 3")
def sample_stable(s, d):
    return t(s, d, "documents").where("doc_id % 7 = 3").select("doc_id")


@q("select o_orderkey from orders o where o_totalprice > (select 1.5 * avg(o_totalprice) from orders i where i.o_custkey = o.o_custkey)")
def subquery_corr(s, d):
    t(s, d, "orders").createOrReplaceTempView("kg_orders")
    return s.sql("select o_orderkey from kg_orders o where o_totalprice > (select 1.5 * avg(o_totalprice) from kg_orders i where i.o_custkey = o.o_custkey)")


_CTE = """with recursive e as (select 'n' || n_nationkey as child, 'r' || n_regionkey as parent from {n} union all select 'r' || r_regionkey, 'root' from {r}),
c as (select child, parent as ancestor, 1 as hop from e union all select c.child, e.parent, c.hop + 1 from c join e on c.ancestor = e.child)
select child, ancestor, hop from c"""


@q(_CTE.format(n="nation", r="region"))
def cte_recursive(s, d):
    t(s, d, "nation").createOrReplaceTempView("kg_nation")
    t(s, d, "region").createOrReplaceTempView("kg_region")
    return s.sql(_CTE.format(n="kg_nation", r="kg_region"))


@q("select n_nationkey, n_name, cast(n_regionkey as bigint) as n_regionkey from nation")
def io_roundtrip(s, d):
    import uuid

    from kgrefine.plans.scratch import scratch_dir

    base, n = f"{scratch_dir(s)}/io-{uuid.uuid4().hex}", t(s, d, "nation").select("n_nationkey", "n_name", F.col("n_regionkey").cast("long").alias("n_regionkey"))
    n.write.parquet(f"{base}/p")
    a = s.read.parquet(f"{base}/p")
    a.write.json(f"{base}/j")
    b = s.read.schema(n.schema).json(f"{base}/j")
    b.write.option("header", True).csv(f"{base}/c")
    return s.read.schema(n.schema).option("header", True).csv(f"{base}/c")


@q("select o_custkey, count(*) as n, cast(sum(l_quantity) as bigint) as qty from lineitem join orders on l_orderkey = o_orderkey group by 1")
def join_bucketed(s, d):
    """Edges and documents bucketed by document: the join reads both sides as they lie."""
    import uuid

    from kgrefine.plans.scratch import scratch_dir
    from kgrefine.sources.records import write_bucketed

    tag, base = uuid.uuid4().hex, scratch_dir(s)
    a = write_bucketed(t(s, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_quantity"), f"kg_edges_{tag}", "k", 8, f"{base}/edges-{tag}")
    b = write_bucketed(t(s, d, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey"), f"kg_docs_{tag}", "k", 8, f"{base}/docs-{tag}")
    return a.join(b.hint("merge"), "k").groupBy("o_custkey").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("qty"))


# streaming: the batch query is the twin


def _stream(s, d):
    from kgrefine.streaming import intake

    return intake, intake.event_stream(s, d)


@q("select time_bucket(interval 1 hour, ts) as w_start, event_type, count(*) as n from events group by all")
def stream_tumbling(s, d):
    intake, e = _stream(s, d)
    return intake.drain(intake.windowed_counts(e, "1 hour"), "tumbling", "complete").select(F.col("w_start").cast("timestamp_ntz").alias("w_start"), "event_type", "n")


@q("select time_bucket(interval 30 minute, ts) - i * interval 30 minute as w_start, event_type, count(*) as n from events, range(0, 2) r(i) group by all")
def stream_sliding(s, d):
    intake, e = _stream(s, d)
    return intake.drain(intake.windowed_counts(e, "1 hour", "30 minutes"), "sliding", "complete").select(F.col("w_start").cast("timestamp_ntz").alias("w_start"), "event_type", "n")


@q("""with a as (select user_id, ts, lag(ts) over (partition by user_id order by ts) as before from events),
b as (select user_id, ts, sum(case when before is null or ts - before >= interval 30 minute then 1 else 0 end) over (partition by user_id order by ts rows unbounded preceding) as s from a)
select user_id, min(ts) as s_start, count(*) as n from b group by user_id, s""")
def stream_session(s, d):
    intake, e = _stream(s, d)
    return intake.drain(intake.session_counts(e), "session", "complete").select("user_id", F.col("s_start").cast("timestamp_ntz").alias("s_start"), "n")


@q("select event_id, event_type from events")
def stream_dedup(s, d):
    intake, e = _stream(s, d)
    return intake.drain(intake.dedup(e.unionByName(e), "60 days").select("event_id", "event_type"), "dedup")


@q("""select a.event_id as request_id, b.event_id as completion_id, a.user_id from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 10 minute
where a.event_type = 'click' and b.event_type = 'purchase'""")
def stream_stream_join(s, d):
    intake, e = _stream(s, d)
    return intake.drain(intake.request_completion_join(e.where("event_type = 'click'"), e.where("event_type = 'purchase'")), "join")


@q("select event_id as record_id, case when event_type = 'signup' then 'file' else 'inline' end as kind, event_id as seq, cast(json_extract_string(props, '$.k') as bigint) as k, event_type <> 'error' as ok from events")
def stream_normalize(s, d):
    intake, e = _stream(s, d)
    return intake.drain(intake.normalize(e), "normalize")


@q("select cast(user_id % 4 as varchar) as channel, row_number() over (partition by user_id % 4 order by event_id) - 1 as seq, event_type as payload from events")
def stream_stateful(s, d):
    import uuid

    from kgrefine.plans.scratch import scratch_dir
    from kgrefine.streaming.intake import drain
    from kgrefine.streaming.ordered import ordered_sink

    n = F.row_number().over(Window.partitionBy("channel").orderBy("event_id")).cast("long") - 1
    rows = t(s, d, "events").withColumn("channel", (F.col("user_id") % 4).cast("string")).select("channel", n.alias("seq"), F.col("event_type").alias("payload"), "value")
    path = f"{scratch_dir(s)}/ordered-{uuid.uuid4().hex}"
    rows.repartition(4, "value").select("channel", "seq", "payload").write.parquet(path)  # out of order on purpose
    return drain(ordered_sink(s.readStream.schema("channel string, seq long, payload string").parquet(path)), "ordered")


@q("""with e as (select ts, event_type, event_id % 10 = 0 as late, time_bucket(interval 1 hour, ts) as w from events),
m as (select max(ts) filter (not late) - interval 1 hour as before, max(ts) - interval 1 hour as at_end from e)
select strftime(w, '%Y-%m-%d %H:%M') as w_start, event_type, count(*) as n from e, m where (not late or w + interval 1 hour > before) and w + interval 1 hour <= at_end group by all""")
def stream_late_data(s, d):
    """Events in three deliveries: the first half and the second half of the time, then every tenth, held back, most of them behind the watermark of the second: dropped."""
    import uuid

    from kgrefine.plans.scratch import scratch_dir
    from kgrefine.streaming.intake import drain, windowed_counts

    e = t(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    middle = F.lit(e.agg(F.timestamp_micros(F.expr("(min(unix_micros(ts)) + max(unix_micros(ts))) div 2"))).first()[0]).cast("timestamp")
    on_time = F.col("event_id") % 10 != 0
    path = f"{scratch_dir(s)}/late-{uuid.uuid4().hex}"
    for n, now in enumerate((on_time & (F.col("ts") < middle), on_time & (F.col("ts") >= middle), ~on_time)):
        e.where(now).select("ts", "event_type").write.parquet(f"{path}/in/p{n}")
        stream = s.readStream.schema("ts timestamp, event_type string").option("recursiveFileLookup", True).parquet(f"{path}/in")
        out = drain(windowed_counts(stream, "1 hour", delay="1 hour"), "late", base=f"{path}/run")  # a delivery is one batch
    return out.select(F.date_format("w_start", "yyyy-MM-dd HH:mm").alias("w_start"), "event_type", "n")
