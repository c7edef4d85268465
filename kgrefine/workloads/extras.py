"""Workloads of the smaller methods: catalogues, conformance tiers, transcripts, contexts, queues, provider calls, options."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgrefine import measures as M
from kgrefine.functions import strings as S
from kgrefine.operators import chunks, clean, conform, extract, gates, names, ontology, pages, resolve, tabular
from kgrefine.sources import records, views
from kgrefine.sources.views import table as t

from .methods import _T, ALIASES, CHUNKS, EXPANDED, TREE, V1, V3, V6, V8, DOT, _hits, _tree

QUERIES: dict = {}
SQL: dict[str, str] = {}


def q(sql: str | None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


_PARTS = "select p_partkey % 5 as doc_id, p_partkey as ent_id, p_size as mentions from part"


@q(f"select doc_id, ent_id, cast(rn as integer) as rank from (select *, row_number() over (partition by doc_id order by mentions desc, ent_id) as rn from ({_PARTS})) where rn <= 20")
def fallback_catalog(s, d):
    e = t(s, d, "part").select((F.col("p_partkey") % 5).alias("doc_id"), F.col("p_partkey").alias("ent_id"), F.col("p_size").alias("mentions"))
    return gates.fallback_catalog(e).select("doc_id", "ent_id", "rank")


@q(f"select doc_id, case when (rn - 1) // 30 < 8 then cast((rn - 1) // 30 as integer) end as batch_no, count(*) as n from (select *, row_number() over (partition by doc_id order by ent_id) as rn from ({_PARTS})) group by all")
def batch_catalog(s, d):
    e = t(s, d, "part").select((F.col("p_partkey") % 5).alias("doc_id"), F.col("p_partkey").alias("ent_id"))
    return gates.batch_catalog(e, 30).groupBy("doc_id", "batch_no").agg(F.count("*").alias("n"))


@q("select o_custkey % 300 as doc_id, count(*) as n_rels, count(*) >= 50 as skip from orders group by 1")
def skip_by_count(s, d):
    return gates.skip_by_count(t(s, d, "orders").withColumn("doc_id", F.col("o_custkey") % 300))


@q("""select n.n_regionkey as domain, md5(string_agg(n_name || ' : nation ' || n_nationkey, chr(10) order by n_name)) as slice_md5, cast(floor(length(string_agg(n_name || ' : nation ' || n_nationkey, chr(10))) / 4) as bigint) as tokens from nation n group by 1""")
def static_slices(s, d):
    c = t(s, d, "nation").select(F.col("n_regionkey").alias("domain"), F.col("n_name").alias("label"), F.concat(F.lit("nation "), F.col("n_nationkey").cast("string")).alias("definition"))
    return ontology.build_slices(c).select("domain", F.md5("slice").alias("slice_md5"), "tokens")


@q(f"""with {TREE}, cls as (select 'n' || n_nationkey as type from nation union all select 'ships' union all select 'N3_type') select type, case when type = 'N3_type' then 'n3' when type in (select child from up) then type end as class_id from cls""")
def tag_types(s, d):
    edge, _, _ = _tree(s, d)
    classes = edge.select(F.explode(F.array("child", "parent")).alias("label")).distinct().select(F.col("label").alias("class_id"), "label", F.lit(None).cast("array<string>").alias("alt_labels"))
    ents = t(s, d, "nation").select(F.concat(F.lit("n"), F.col("n_nationkey").cast("string")).alias("type")).unionByName(s.createDataFrame([("ships",), ("N3_type",)], "type string"))
    return conform.tag_types(ents, classes).select("type", "class_id")


@q(f"""with {TREE}, rel as (select o_orderkey, 'n' || (o_custkey % 25) as st, 'r' || (o_orderkey % 5) as dt, 'at_r' || (o_orderkey % 7) as rel_type from orders)
select rel_type, case when p.pred_id is null then null else exists (select 1 from up where child = st and ancestor = p.domain) and exists (select 1 from up where child = dt and ancestor = p.range) end as valid, count(*) as n from rel left join pred p on p.pred_id = rel_type group by all""")
def validate_domain_range(s, d):
    edge, pred, _ = _tree(s, d)
    o = t(s, d, "orders")
    key = lambda p, c: F.concat(F.lit(p), c.cast("string"))
    st, dt = key("n", F.col("o_custkey") % 25), key("r", F.col("o_orderkey") % 5)
    ents = o.select(F.explode(F.array(st, dt)).alias("type")).distinct().select(F.lit(0).alias("doc_id"), F.col("type").alias("ent_id"), "type")
    rels = o.select(F.lit(0).alias("doc_id"), st.alias("src"), dt.alias("dst"), key("at_r", F.col("o_orderkey") % 7).alias("rel_type"))
    return conform.validate_domain_range(rels, ents, pred, ontology.closure(edge)).groupBy("rel_type", "valid").agg(F.count("*").alias("n"))


@q("select event_type as rel_type, count(*) as n from events where event_type not in ('click', 'purchase') group by 1")
def unknown_predicates(s, d):
    rels = t(s, d, "events").select(F.col("event_type").alias("rel_type"))
    return conform.unknown_predicates(conform.snap_predicates(rels, s.createDataFrame([("Click",), ("purchases",)], "label string")))


@q("""with p as (select doc_id, unnest([text, substring(text, 1, 400)]) as text from documents), w as (select distinct doc_id as page_id, unnest(string_split_regex(lower(text), '\\s+')) as token from p) select page_id, count(*) as tokens from w where token <> '' group by 1""")
def union_transcripts(s, d):
    docs = t(s, d, "documents").select(F.col("doc_id").alias("page_id"), "text")
    return pages.union_transcripts(docs.unionByName(docs.select("page_id", F.substring("text", 1, 400).alias("text"))))


@q("""with a as (select item_id, regexp_replace(text, '[^ -~]', 'x', 'g') as text from benchmark) select item_id, round(levenshtein(replace(text, 'e', ''), text) / greatest(length(text), 1), 6) as cer from a""")
def character_error_rate(s, d):
    b = t(s, d, "benchmark").select("item_id", F.regexp_replace("text", "[^ -~]", "x").alias("text"))
    return b.select("item_id", F.round(M.cer(F.replace("text", F.lit("e"), F.lit("")), F.col("text")), 6).alias("cer"))


@q("""with e as (select p_partkey, map_from_entries([('role', p_brand), ('org', p_type), ('loc', case when p_size > 25 then cast(p_size as varchar) end)]) as m from part) select p_partkey as ent_id, k as type, m[k] as value from e, (values ('role'), ('org'), ('loc')) v(k) where m[k] is not null""")
def context_attributes(s, d):
    p = t(s, d, "part")
    props = F.create_map(F.lit("position"), F.col("p_brand"), F.lit("organisation"), F.col("p_type"), F.lit("location"), F.when(F.col("p_size") > 25, F.col("p_size").cast("string")))
    return names.context_attributes(p.select(F.col("p_partkey").alias("ent_id"), props.alias("props"))).select("ent_id", "type", "value")


@q("select p_partkey as ent_id, sha256(concat_ws('|', 'PERSON', lower(p_name), lower(p_brand), lower(p_type), cast(cast(floor(p_size / 10) as bigint) as varchar))) as fingerprint from part")
def entity_fingerprint(s, d):
    return names.fingerprint(views.homonyms(s, d), F.col("name")).select("ent_id", "fingerprint")


@q(None)
def dedup_status(s, d):
    ents = views.homonyms(s, d)
    _, _, decided = names.enhance(ents)
    return names.dedup_status(ents, decided).groupBy("dedup_status").agg(F.count("*").alias("n"))


@q(None)
def alias_occurrences(s, d):
    """Mined aliases with their counts and at most three snippets."""
    docs, ents = views.planted_text(s, d)
    return names.alias_occurrences(names.mine_variants(ents, docs), docs).select("doc_id", "ent_id", "alias", "count", F.array_join("snippets", " / ").alias("snippets"))


@q(None)
def phonetic_codes(s, d):
    n = t(s, d, "part").select(F.col("p_name").alias("name")).distinct()
    return n.select("name", F.array_join(S.phonetic(F.col("name")), " ").alias("primary"), F.array_join(S.phonetic(F.col("name"), True), " ").alias("secondary"), F.soundex("name").alias("soundex"))


@q("select lower(p_name) as name, count(*) as n from part group by 1")
def hash_embedding_groups(s, d):
    """Equal texts, and only those, have equal pseudo-embeddings."""
    v = t(s, d, "part").select(F.lower("p_name").alias("name"), resolve.embed_hash(F.lower("p_name")).alias("v"))
    return v.groupBy(F.xxhash64("v").alias("h")).agg(F.min("name").alias("name"), F.count("*").alias("n")).select("name", "n")


@q("select event_id, case event_type when 'signup' then 'pdf' when 'purchase' then 'xlsx' when 'error' then 'unknown' else 'text' end as handler from events")
def route_format(s, d):
    e = t(s, d, "events")
    kind = F.when(F.col("event_type").isin("signup", "purchase", "error"), "file").otherwise("inline")
    mime = F.when(F.col("event_type") == "signup", "application/pdf")
    ext = F.when(F.col("event_type") == "purchase", "XLSX").when(F.col("event_type") == "error", "zzz")
    return records.route_format(e.select("event_id", kind.alias("kind"), mime.alias("mime"), ext.alias("ext"))).select("event_id", "handler")


@q("select cast(event_id as varchar) as record_id, case when event_type = 'signup' then 'file' else 'inline' end as kind, case when event_type <> 'signup' then event_type end as text, event_id as seq from events")
def normalize_records(s, d):
    e = t(s, d, "events")
    doc = F.when(F.col("event_type") == "signup", F.to_json(F.struct(F.struct(F.col("event_id").cast("string").alias("$oid")).alias("_id"), F.lit("a/b.pdf").alias("filePath"), F.col("event_id").alias("seq")))).otherwise(
        F.to_json(F.struct(F.col("event_id").cast("string").alias("recordId"), F.col("event_type").alias("report_text"), F.col("event_id").alias("seq"))))
    return records.normalize_records(e.select(doc.alias("value"))).select("record_id", "kind", "text", "seq")


@q("""with c as (select doc_id, i as chunk_no, substring(text, i * 1500 + 1, 1500) as text from documents, range(0, 1000) r(i) where i * 1500 < length(text))
select count(*) as calls, count(*) filter (regexp_matches(text, '[A-Z][a-z]+ [A-Z][a-z]+')) as with_entities from c""")
def provider_calls(s, d):
    """Calls to the rule provider, one for each chunk, and how many answers hold entities after recovery."""
    c = chunks.chunk_chars(t(s, d, "documents").where("length(text) > 0"), 1500, 0, annotate=False)
    got = extract.recover_json(extract.run_provider(c, extract.get_provider("rule")))
    n = F.size(F.from_json("json", "struct<entities:array<struct<name:string,type:string>>>")["entities"])
    return got.agg(F.count("*").alias("calls"), F.count_if(n > 0).alias("with_entities"))


@q("select (select count(*) from orders) as per_row_calls, 1::bigint as plan_calls")
def plan_vs_row_calls(s, d):
    calls = s.sparkContext.accumulator(0)

    def provider(profile):
        calls.add(1)
        return tabular.plan_table(profile, entity_type="ORDER")

    o = t(s, d, "orders").select("o_orderkey", "o_totalprice")
    out = tabular.execute_plan(o, tabular.plan_table(tabular.inspect_table(o), provider))
    return out.agg(F.count("*").alias("per_row_calls")).withColumn("plan_calls", F.lit(calls.value).cast("long"))


@q("select event_id as seq, epoch_us(ts) + cast(round(value * 1000) as bigint) < max(epoch_us(ts) + cast(round(value * 1000) as bigint)) over (order by event_id rows unbounded preceding) as parked from events")
def release_inversions(s, d):
    from kgrefine.streaming.ordered import inversions

    e = t(s, d, "events").select(F.col("event_id").alias("seq"), (F.unix_micros(F.col("ts").cast("timestamp")) + F.round(F.col("value") * 1000).cast("long")).alias("done_ts"))
    return inversions(e).select("seq", "parked")


_ATTESTED = """toks as (select distinct string_split(trim(name), ' ') as t, lower(trim(name)) as whole from ent), found as (select lower(replace(t[1], '.', '')) as token, lower(t[2] || ' ' || t[3]) as core from toks where len(t) = 3),
titles as (select token from found where core in (select whole from toks) group by token having count(distinct core) >= 3)"""


@q(f"with {V6}, {_ATTESTED} select token from titles")
def attested_titles(s, d):
    """Tokens that stand before at least three names which also occur on their own."""
    return clean.attested_titles(views.dirty_entities(s, d))


@q(f"""with {V6}, {_ATTESTED}, cut as (select doc_id, type, case when len(t) > 2 and lower(replace(t[1], '.', '')) in (select token from titles) then array_to_string(t[2:], ' ') else name end as aname, cname from (select *, string_split(name, ' ') as t from core))
select 'structural' as rule, count(*) as merged, cast(sum(n) as bigint) as mentions from (select count(*) as n from cut group by doc_id, type, lower(cname)) union all select 'attested', count(*), cast(sum(n) as bigint) from (select count(*) as n from cut group by doc_id, type, lower(aname))""")
def attested_vs_structural(s, d):
    """Groups of the structural title rule and of the attested one, which strips only tokens that stand before many known names."""
    e = clean.fix_entity_type(views.dirty_entities(s, d)).drop("retyped")
    tokens = clean.attested_titles(e).agg(F.array_sort(F.collect_set("token")).alias("known"))  # titles, a few words
    ruled = e.crossJoin(F.broadcast(tokens))
    out = None
    for rule, core in {"structural": None, "attested": clean.core_name(F.col("name"), attested=F.col("known"))}.items():
        row = clean.merge_entities(ruled, core=core)[0].agg(F.count("*").alias("merged"), F.sum("mentions").alias("mentions")).withColumn("rule", F.lit(rule))
        out = row if out is None else out.unionByName(row)
    return out


_WRONG = """select '{r}' as rule, count(*) as clusters, count(*) filter (golds > 1) as false_clusters, cast(sum((n * n - sq) / 2) as bigint) as false_pairs from (select c, sum(n) as n, sum(n * n) as sq, count(*) as golds from (select {k} as c, p_brand, p_type, floor(p_size / 10) as loc, p_name, count(*) as n from part group by all) group by c)"""


@q(_WRONG.format(r="name only", k="p_name") + " union all " + _WRONG.format(r="name and context", k="p_name || '|' || p_brand || '|' || p_type || '|' || floor(p_size / 10)"))
def false_merges(s, d):
    """Wrong pairs joined by merging equal names across contexts, with and without the context check."""
    p = views.homonyms(s, d).select("ent_id", "name", "role", "org", "loc")
    gold = p.select("ent_id", F.xxhash64("name", "role", "org", "loc").alias("gold_id"))
    out = None
    for rule, keys in {"name only": ["name"], "name and context": ["name", "role", "org", "loc"]}.items():
        c = p.withColumn("canonical_id", F.min("ent_id").over(Window.partitionBy(*keys))).select("ent_id", "canonical_id")
        row = M.false_merges(c, gold).withColumn("rule", F.lit(rule))
        out = row if out is None else out.unionByName(row)
    return out


@q(None)
def resolution_review(s, d):
    """The merged review queue of the rule layer and the embedding layer."""
    from .methods import _parts_as_entities

    e = _parts_as_entities(s, d)
    pairs = resolve.block_union(phonetic=resolve.block_phonetic(e), vector=resolve.block_vector(e.select(F.col("ent_id").alias("vec_id"), "vec")))
    decided = resolve.decide_resolution(resolve.score_pairs(pairs, e), review=0.5)
    rule = names.decide_rule(names.context_agreement(names.name_similarity(names.candidate_pairs(views.homonyms(s, d), keep=("name", "org"))), ("org",))).where("action = 'manual_review'")
    return resolve.review_queue(rule, decided.where("action in ('manual_review', 'codename_candidate')")).groupBy("layer").agg(F.count("*").alias("n"))


@q(None)
def stage_overhead(s, d):
    """Seconds of the rule layer beside those of extraction by the rule provider, for a corpus."""
    import time

    c = chunks.chunk_chars(t(s, d, "documents").where("length(text) > 0"), annotate=False)
    began = time.time()
    n = extract.run_provider(c, extract.get_provider("rule")).count()
    middle = time.time()
    names.expand_aliases(views.homonyms(s, d)).select(F.sum(F.size("aliases"))).collect()
    end = time.time()
    return s.createDataFrame([("extraction", n, middle - began), ("aliases", n, end - middle)], "stage string, chunks long, seconds double")


@q(f"""with {V1}, line as (select doc_id, length('class ' || class_id || ' : things of kind ' || class_id || ' and ' || repeat('x', cast(class_id * 37 % 400 as integer))) as n from best)
select doc_id, cast(sum(n) + count(*) - 1 as integer) as n, cast(floor((sum(n) + count(*) - 1) / 4) as bigint) as tokens from line group by doc_id""")
def catalogue_text(s, d):
    """Rendered catalogues of the live retrieval."""
    classes, _, _, best = _hits(s, d)
    return ontology.render_catalog(best.join(classes.select("class_id", "label", "definition"), "class_id")).select("doc_id", F.length("catalogue").alias("n"), "tokens")


@q("select doc_id, '' as catalogue, 0::bigint as tokens from documents")
def catalog_none(s, d):
    return ontology.catalog_none(t(s, d, "documents"))


@q("""with r as (select event_id, user_id % 20 as u, event_type, floor(epoch_us(ts) / 600000000.0) as slot from events), kept as (select distinct u, event_type, slot from r where event_id % 2 = 0)
select r.event_id as req_id, k.u is not null as stored from r left join kept k on r.u = k.u and r.event_type = k.event_type and r.slot = k.slot""")
def cache_store(s, d):
    """Requests that find a catalogue kept by an earlier run, which saw every second request."""
    e = t(s, d, "events").select(F.col("event_id").alias("req_id"), "ts", F.concat_ws("/", (F.col("user_id") % 20).cast("string"), "event_type").alias("text"))
    keyed = ontology.with_cache(e)
    store = keyed.where("req_id % 2 = 0").select("cache_key", F.lit("kept").alias("catalogue"))
    return ontology.with_store(keyed, store).select("req_id", F.col("stored").isNotNull().alias("stored"))


@q(None)
def search_recall(s, d):
    """Hits of four forms of each planted name by the name alone, with expanded aliases, and with mined variants as well."""
    docs, ents = views.planted_text(s, d)
    tk = F.split("name", " ")
    wrong = F.when(F.col("doc_id") % 2 == 0, F.concat(F.substring(tk[0], 1, 1), F.substring(tk[0], 3, 100))).otherwise(F.concat(tk[0], F.substring(tk[0], -1, 1)))
    forms = {"full": F.col("name"), "initial": F.concat(F.substring(tk[0], 1, 1), F.lit(". "), tk[1]), "initials": F.concat(F.substring(tk[0], 1, 1), F.substring(tk[1], 1, 1)), "misspelt": F.concat(wrong, F.lit(" "), tk[1])}
    qs = ents.select("ent_id", F.inline(F.array(*[F.struct(F.lit(k).alias("form"), S.norm_name(v).alias("q")) for k, v in forms.items()])))
    bare = ents.select("ent_id", F.col("name").alias("a"))
    more = names.expand_aliases(ents).select("ent_id", F.explode("aliases").alias("a"))
    mined = names.mine_variants(ents, docs).select("ent_id", F.col("alias").alias("a"))
    out = None
    for name, known in {"name": bare, "aliases": more, "aliases and variants": more.unionByName(mined)}.items():
        hit = qs.join(known.select("ent_id", S.norm_name(F.col("a")).alias("q")).distinct(), ["ent_id", "q"], "left_semi")
        row = qs.agg(F.count("*").alias("queries")).crossJoin(hit.agg(F.count("*").alias("hits"))).withColumn("known", F.lit(name)).withColumn("recall", F.round(F.col("hits") / F.col("queries"), 4))
        out = row if out is None else out.unionByName(row)
    return out


@q(CHUNKS.format(o=1000, p=7000) + """ select '1' as outcome, count(*) filter (doc_id % 3 <> 0) as n from c union all select '2', 0 from c where false union all select 'failed', count(*) filter (doc_id % 3 = 0) from c""")
def retry_budget(s, d):
    """Chunks answered and left by number of tries, when the provider fails on every third document."""
    import pandas as pd

    def provider(batches):
        for pdf in batches:
            ok = pdf["doc_id"] % 3 != 0
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "chunk_no": pdf["chunk_no"], "answer": ok.map({True: '{"entities":[]}', False: "no answer"})})

    good, left = extract.retry_loop(chunks.chunk_chars(t(s, d, "documents"), annotate=False), provider, 1)
    return good.groupBy(F.col("attempt").cast("string").alias("outcome")).agg(F.count("*").alias("n")).unionByName(left.agg(F.count("*").alias("n")).select(F.lit("failed").alias("outcome"), "n"))


_PLANTED = f"""pn as (select p_partkey - 1 as n, p_name, {_T}[1] as t1, {_T}[2] as t2 from part), pl as (select doc_id, p_name, t1, t2, case when doc_id % 2 = 0 then t1[1] || substring(t1, 3) else t1 || t1[-1] end as wrong, text as body
  from documents join pn on n = doc_id % (select count(*) from part)), documents as (select doc_id, p_name, body || chr(10) || 'seen: ' || p_name || ' then ' || t1[1] || '. ' || t2 || ' then ' || wrong || ' ' || t2 || ' end' as text from pl)"""


@q(f"with {_PLANTED}, " + CHUNKS.format(o=1000, p=7000).removeprefix("with ") + """, j as (select c.doc_id, count(*) as edges from c join pl using (doc_id) where contains(lower(substring(c.text, i * 7000 + 1, 8000)), lower(p_name)) and c.doc_id % 2 = 1 group by 1) select * from j""")
def second_pass_edges(s, d):
    """Co-occurring names of a document's catalogue in its chunks, for the documents that the gate sends to a second pass: those with few relations."""
    docs, ents = views.planted_text(s, d)
    two = ents.unionByName(ents.select("doc_id", F.concat("ent_id", F.lit("x")).alias("ent_id"), "type", F.split("name", " ")[1].alias("name")))
    many = F.explode(F.sequence(F.lit(1), F.when(F.col("doc_id") % 2 == 0, 60).otherwise(6)))
    rels = ents.select("doc_id", F.col("ent_id").alias("src"), F.col("ent_id").alias("dst"), many.alias("i")).withColumn("rel_type", F.concat(F.lit("R"), (F.col("i") % 6).cast("string")))
    sent = gates.quality_gate(two, rels).where("second_pass").select("doc_id")
    found = extract.second_pass(two.join(sent, "doc_id", "left_semi"), chunks.chunk_chars(docs.join(sent, "doc_id", "left_semi"), annotate=False))
    return found.groupBy("doc_id").agg(F.count("*").alias("edges"))


# intake and options without a workload elsewhere

@q("select event_id, case when event_type = 'signup' then 'base/' || 'application_pdf' || '/a/' || event_id || '.pdf' end as location from events")
def file_locations(s, d):
    e = t(s, d, "events")
    rows = e.select("event_id", F.when(F.col("event_type") == "signup", "file").otherwise("inline").alias("kind"), F.lit("application/pdf").alias("mime"), F.concat(F.lit("a/"), F.col("event_id").cast("string"), F.lit(".pdf")).alias("path"))
    return records.resolve_location(rows, "base/").select("event_id", "location")


@q("select 'turns' as handler, count(*) as n, count(distinct conv_id) as docs, 0::bigint as sheets from conversations union all select 'rows', count(*), count(distinct o_custkey), count(distinct o_orderpriority) from orders")
def unify_handlers(s, d):
    """Rows of two handlers as one table; a column that one lacks is null."""
    a = t(s, d, "conversations").select(F.col("conv_id").alias("doc_id"), "text", F.lit("turns").alias("handler"))
    b = t(s, d, "orders").select(F.col("o_custkey").cast("long").alias("doc_id"), F.col("o_orderpriority").alias("sheet"), F.lit("rows").alias("handler"))
    return records.unify(a, b).groupBy("handler").agg(F.count("*").alias("n"), F.count_distinct("doc_id").alias("docs"), F.count_distinct("sheet").alias("sheets"))


@q("select doc_id, case when doc_id % 3 = 0 then 0 else 1 end as entities from documents")
def empty_results(s, d):
    """A result for every document; those without one have empty arrays."""
    docs = t(s, d, "documents").select("doc_id")
    some = docs.where("doc_id % 3 <> 0").withColumn("entities", F.array(F.lit("e")))
    return extract.empty_results(docs, some).select("doc_id", F.size("entities").alias("entities"))


@q("select n_regionkey as doc_id, cast(count(*) as integer) as entities, 0 as relationships from nation group by 1")
def result_store(s, d):
    """Envelopes written as JSON lines and read again."""
    from kgrefine.plans.scratch import scratch_dir

    n = t(s, d, "nation").select(F.col("n_regionkey").alias("doc_id"), F.col("n_name").alias("name"))
    none = n.where("false").select("doc_id", F.lit("").alias("src"))
    import uuid

    path = f"{scratch_dir(s)}/results-{uuid.uuid4().hex}"
    records.write_results(records.result_envelopes(n, none, none, n), path)
    back = records.read_any(s, path, "text").select(F.from_json("value", "struct<doc_id:int,entities:array<struct<name:string>>,relationships:array<struct<src:string>>>").alias("r"))
    return back.select("r.doc_id", F.size("r.entities").alias("entities"), F.size("r.relationships").alias("relationships"))


@q(CHUNKS.format(o=1000, p=7000) + """ select doc_id, cast(i as integer) as chunk_no, 'characters ' || (i * 7000) || ' to ' || least(i * 7000 + 8000, n) || ', own part ' || (i * 7000) || ' to ' || (case when i = last then n else i * 7000 + 7000 end) as header from c""")
def chunk_headers(s, d):
    return chunks.chunk_chars(t(s, d, "documents")).select("doc_id", "chunk_no", "header")


@q("select doc_id, md5(substring(text, 1, 8000)) as text_md5 from documents")
def window_single(s, d):
    """The single-vector variant: one long window for each document."""
    return chunks.windows_fixed(t(s, d, "documents"), 8000, 0, 1).select("doc_id", F.md5("text").alias("text_md5"))


@q("select cast(sum(length(text)) as bigint) as unlimited, cast(sum(least(length(text), 1)) as bigint) as sentinel_raised, cast(sum(least(length(text), 500)) as bigint) as limited from documents")
def limit_sentinel(s, d):
    """Characters kept with no limit, with the sentinel 0 raised to 1, and with a limit of 500."""
    size = lambda c: F.sum(F.length(c)).cast("long")
    c = F.col("text")
    return t(s, d, "documents").agg(size(chunks.limit_text(c, 0)).alias("unlimited"), size(chunks.limit_text_buggy(c, 0)).alias("sentinel_raised"), size(chunks.limit_text(c, 500)).alias("limited"))


@q("select conv_id as doc_id, turn as page_no, md5(coalesce(role || chr(10), '') || coalesce(text || chr(10), '') || 'turn ' || turn) as text_md5 from conversations where role <> '' and text <> ''")
def slide_pages(s, d):
    """Turns as slides: title, body and notes as one page each."""
    c = t(s, d, "conversations").where("role <> '' and text <> ''")
    slides = c.select(F.col("conv_id").alias("doc_id"), F.col("turn").alias("slide_no"), F.col("role").alias("title"), F.array("text").alias("body"), F.array().cast("array<string>").alias("tables"), F.concat(F.lit("turn "), F.col("turn").cast("string")).alias("notes"))
    return pages.slide_pages(slides).select("doc_id", "page_no", F.md5("text").alias("text_md5"))


@q("""with p as (select page_id, regexp_replace(regexp_replace(html, '(?i)</(li|p|h1|tr|div|footer)>', chr(10), 'g'), '(?i)</t[dh]>\\s*<t[dh]>', ' | ', 'g') as html from pages),
b as (select page_id, trim(unnest(string_split_regex(regexp_replace(html, '<[^>]*>', '', 'g'), chr(10) || '+'))) as b from p)
select page_id, cast(sum(length(b)) as bigint) as chars from b where b <> '' group by page_id""")
def virtual_page_totals(s, d):
    """Characters of a page's virtual pages without the line feeds between blocks: cutting loses nothing."""
    v = pages.virtual_pages(t(s, d, "pages"))
    return v.groupBy("page_id").agg(F.sum(F.length(F.replace("text", F.lit("\n"), F.lit("")))).cast("long").alias("chars"))


# ontology, conformance, names, resolution

_BUDGET = f"""with {EXPANDED}, ct as (select *, 200 + class_id * 37 % 400 as tokens from ex where score >= 0.72), cu as (select doc_id, class_id, sum(tokens) over (partition by doc_id order by round(score, 9) desc, class_id rows unbounded preceding) as used from ct),
ck as (select * from cu where used <= 840), pt as (select doc_id, 'p' || class_id as pred_id, score, 130 + class_id % 50 as tokens from ex where score >= 0.72),
pu as (select doc_id, pred_id, sum(tokens) over (partition by doc_id order by round(score, 9) desc, pred_id rows unbounded preceding) as used from pt), sp as (select doc_id, max(used) as spent from ck group by 1),
pk as (select pu.*, spent from pu left join sp using (doc_id) where used <= 1200), f as (select doc_id, cast(max(used) filter (used <= 360) as bigint) as fixed, cast(max(used) filter (used <= 360 + 840 - coalesce(spent, 0)) as bigint) as rolled from pk group by 1)
select d.doc_id, cast(spent as bigint) as class_tokens, fixed, rolled from (select distinct doc_id from ct) d left join sp using (doc_id) left join f using (doc_id)"""


@q(_BUDGET)
def catalogue_budget_split(s, d):
    """A budget of 1,200 tokens: seven tenths for classes, the rest for predicates, without and with what the classes leave."""
    classes, _, _, best = _hits(s, d)
    hits = ontology.expand_children(best, views.subclass_edges(classes)).withColumn("score", F.round("score", 9))
    sized = hits.withColumn("tokens", F.lit(200) + F.col("class_id") * 37 % 400)
    preds = hits.select("doc_id", F.concat(F.lit("p"), F.col("class_id").cast("string")).alias("pred_id"), "score", (F.lit(130) + F.col("class_id") % 50).alias("tokens"))
    most = lambda df, name: df.groupBy("doc_id").agg(F.max("used").alias(name))
    kept, fixed = ontology.cutoff_split(sized, preds, 1200, 0.7)
    _, rolled = ontology.cutoff_split(sized, preds, 1200, 0.7, rollover=True)
    rows = hits.where("score >= 0.72").select("doc_id").distinct()
    for df, name in ((kept, "class_tokens"), (fixed, "fixed"), (rolled, "rolled")):
        rows = rows.join(most(df, name), "doc_id", "left")
    return rows


@q("select doc_id, md5(substring(text, 1, 30000)) as text_md5 from documents")
def fallback_evidence(s, d):
    return gates.evidence_window(t(s, d, "documents")).select("doc_id", F.md5("text").alias("text_md5"))


@q("""select doc_id, array_to_string(list_sort(list_distinct(list_concat(list_concat(regexp_extract_all(text, '[A-Z][a-zà-ÿ]+(?: [A-Z][a-zà-ÿ]+)+'), regexp_extract_all(text, '[A-Z]{2,}')), list_filter(['the', 'und'], lambda w: contains(lower(text), w))))), '|') as terms from documents""")
def term_strings(s, d):
    """The term string of each document, whose vector the first refinement adds; terms in order of their letters."""
    terms = F.split(ontology.extract_terms(F.col("text"), ("the", "und")), r"\|")
    return t(s, d, "documents").select("doc_id", F.array_join(F.array_sort(terms), "|").alias("terms"))


@q(f"""with {V3}, s as (select rel_type, lower(regexp_replace(trim(rel_type), '[ -]+', '_', 'g')) as k from edge) select 'raw' as stage, count(*) as n, count(*) filter (rel_type in ('flag_a_to_f', 'flag_n_to_o')) as conform from s
union all select 'snapped', count(*), count(*) filter (k in ('flag_a_to_f', 'flag_n_to_o')) from s""")
def conformance_snapping(s, d):
    """Labels that stand in the vocabulary as they come and after snapping."""
    words = ("flag_a_to_f", "flag_n_to_o")
    e = conform.snap_predicates(views.edges(s, d), s.createDataFrame([(w,) for w in words], "label string"))
    row = lambda c, stage: e.agg(F.count("*").alias("n"), F.count_if(F.col(c).isin(*words)).alias("conform")).withColumn("stage", F.lit(stage))
    return row("rel_type", "raw").unionByName(row("canon", "snapped"))


@q(f"""with {TREE}, ex as (select distinct doc_id, pred_id from hit join pred on class_id in (domain, range)), an as (select distinct doc_id, pred_id from hit join up on child = class_id join pred on ancestor in (domain, range))
select 'exact' as method, count(*) as predicates, count(distinct pred_id) filter (starts_with(pred_id, 'at_r')) as family, (select count(*) from region) as family_size from ex union all select 'ancestor', count(*), count(distinct pred_id) filter (starts_with(pred_id, 'at_r')), (select count(*) from region) from an""")
def predicate_families(s, d):
    """Predicates retrieved, and how many of the family that hangs on the upper classes."""
    edge, pred, hit = _tree(s, d)
    upper = pred.where("pred_id like 'at_r%'").agg(F.count("*").alias("family_size"))
    out = None
    for name, found in {"exact": ontology.predicates_exact(hit, pred), "ancestor": ontology.predicates_ancestor(hit, ontology.closure(edge), pred)}.items():
        row = found.agg(F.count("*").alias("predicates"), F.count_distinct(F.when(F.col("pred_id").startswith("at_r"), F.col("pred_id"))).alias("family")).crossJoin(upper).withColumn("method", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@q("""with n as (select n_regionkey, n_nationkey, n_name, 'R' || n_regionkey as region from nation) select cast(n_nationkey as bigint) as row_no, region, trim(unnest([n_name, 'also ' || n_name])) as member from n""")
def plan_merged_cells(s, d):
    """A sheet whose region stands in the first row of a merged range and whose member cell holds two values."""
    from pyspark.sql import Window as W

    n = t(s, d, "nation")
    first = F.row_number().over(W.partitionBy("n_regionkey").orderBy("n_nationkey")) == 1
    sheet = n.select(F.col("n_nationkey").alias("row_no"), F.when(first, F.concat(F.lit("R"), F.col("n_regionkey").cast("string"))).alias("region"), F.concat("n_name", F.lit(" ; also "), "n_name").alias("member"), "n_regionkey")
    plan = {"columns": {"row_no": "int", "region": "string", "member": "string"}, "fill": ["region"], "split": {"member": ";"}, "drop_where": None}
    return tabular.execute_plan(sheet, plan, "row_no", "n_regionkey").select("row_no", "region", "member")


@q(None)
def vector_ivf(s, d):
    return resolve.block_vector(views.near_duplicate_vectors(s, d), method="ivf").select("left_id", "right_id", F.round("cos", 4).alias("cos"))


@q("""with r as (select event_id, user_id % 20 as u, event_type, floor(epoch_us(ts) / 600000000.0) as slot, event_id % 3 = 0 as late, ts from events)
select event_id as req_id, row_number() over (partition by u, event_type, slot, late order by ts, event_id) > 1 as hit from r""")
def cache_versioned(s, d):
    """Every third request sees the vocabulary with a promoted label: its version hash differs, so the other requests' slices miss."""
    vocab = s.createDataFrame([("click",), ("purchase",)], "label string")
    grown = conform.promote(vocab, s.createDataFrame([("signup",)], "label string"))
    old, new = (v.agg(ontology.version_hash(v).alias("h")).first()["h"] for v in (vocab, grown))
    e = t(s, d, "events").select(F.col("event_id").alias("req_id"), "ts", F.concat_ws("/", (F.col("user_id") % 20).cast("string"), "event_type").alias("text"))
    return ontology.with_cache(e, version=F.when(F.col("req_id") % 3 == 0, new).otherwise(old)).select("req_id", "hit")


@q("select 'before' as stage, count(*) filter (event_type not in ('click', 'purchase')) as novel from events union all select 'after', count(*) filter (event_type not in ('click', 'purchase', 'signup')) from events")
def promotion(s, d):
    """Novel types before and after the most frequent proposal is promoted into the vocabulary."""
    e, vocab = t(s, d, "events"), s.createDataFrame([("clicks",), ("purchase",)], "label string")
    flagged = conform.flag_novel(e, vocab, "event_type")
    best = conform.proposed_extensions(flagged, "event_type").where("label = 'signup'")
    after = conform.flag_novel(e, conform.promote(vocab, best), "event_type")
    count = lambda df, name: df.agg(F.count_if(F.col("novel")).alias("novel")).withColumn("stage", F.lit(name))
    return count(flagged, "before").unionByName(count(after, "after"))


@q(f"""with {V3}, s as (select rel_type, lower(regexp_replace(trim(rel_type), '[ -]+', '_', 'g')) as k from edge) select rel_type, case when k = 'flag_a_to_f' then k when k = 'flag_n_to_o' then 'moved' else rel_type end as canon,
case when k = 'flag_a_to_f' then 'exact' when k = 'flag_n_to_o' then 'vector' else 'novel' end as tier, count(*) as n from s group by all""")
def snap_by_vector(s, d):
    """The vector tier: a label whose vector lies within a cosine of 0.80 of a vocabulary label's takes that label, one at 0.70 stays novel."""
    e = views.edges(s, d)
    low = F.lower(clean.canon_rel_type(F.col("label")))
    cos = F.when(low == "flag_n_to_o", 0.9).when(low == "flag_n_to_f", 0.7).otherwise(0.0)
    labels = e.select(F.col("rel_type").alias("label")).distinct().select("label", F.array(cos, F.sqrt(1 - cos * cos)).alias("vec"))
    vocab = s.createDataFrame([("flag_a_to_f",), ("moved",)], "label string")
    vecs = s.createDataFrame([("moved", [1.0, 0.0])], "label string, vec array<double>")
    return conform.snap_predicates(e, vocab, labels, vecs).groupBy("rel_type", "canon", "tier").agg(F.count("*").alias("n"))


@q("""with e as (select l_orderkey, l_linenumber, l_suppkey as a, l_partkey as b, (['commands', 'has_subordinate', 'subordinate_to', 'supplies'])[l_orderkey % 4 + 1] as r from lineitem),
f as (select *, case when r in ('commands', 'has_subordinate') then b else a end as src, case when r in ('commands', 'has_subordinate') then a else b end as dst, case when r = 'supplies' then r else 'subordinate_to' end as rel_type from e)
select rel_type, count(*) as n, cast(sum(case when rel_type = 'subordinate_to' and src % 4 < dst % 4 then dst else src end) as bigint) as src_sum from f group by 1""")
def conform_chain(s, d):
    """Snap, fold and orient in one chain on labels in upper case."""
    li = t(s, d, "lineitem")
    label = F.element_at(F.array(*[F.lit(x) for x in ("Commands", "HAS SUBORDINATE", "Subordinate-To", "SUPPLIES")]), (F.col("l_orderkey") % 4 + 1).cast("int"))
    rels = li.select(F.lit(0).alias("doc_id"), F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"), label.alias("rel_type"))
    unit = F.element_at(F.array(*[F.lit(x) for x in ("7 Corps", "2nd Division", "Iron Brigade", "3 battalion")]), (F.col("ent_id") % 4 + 1).cast("int"))
    ids = t(s, d, "part").select(F.col("p_partkey").alias("ent_id")).union(t(s, d, "supplier").select("s_suppkey")).distinct()
    ents = ids.select(F.lit(0).alias("doc_id"), "ent_id", F.lit("ORGANIZATION").alias("type"), unit.alias("name"))
    vocab = s.createDataFrame([(x,) for x in ("commands", "has_subordinate", "subordinate_to", "supplies")], "label string")
    return conform.conform(rels, ents, vocab).groupBy("rel_type").agg(F.count("*").alias("n"), F.sum("src").cast("long").alias("src_sum"))


@q(f"select count(*) as entities, round(avg(len(list_distinct({ALIASES}))), 6) as aliases_per_entity from part")
def aliases_per_entity(s, d):
    return M.alias_counts(names.expand_aliases(views.homonyms(s, d)))


@q("select p_name is not null and not contains(p_name, 'red') as embedded, count(*) as n from part group by 1")
def embedding_backfill(s, d):
    """Texts whose call fails take their batch with them; alone, only they stay without a vector."""
    def call(texts):
        if any("red" in x for x in texts):
            raise ValueError("refused")
        return [[float(len(x)), 1.0] for x in texts]

    rows = resolve.embed_batches(t(s, d, "part").select("p_partkey", F.col("p_name").alias("text")), call)
    return rows.groupBy(F.col("vec").isNotNull().alias("embedded")).agg(F.count("*").alias("n"))


@q("select cast(sum(n * (n - 1) // 2) as bigint) as pairs, count(*) as documents from (select p_partkey // 40 as doc_id, count(*) as n from part group by 1)")
def all_pairs_baseline(s, d):
    """The pairs that blocking is measured against: all of each document."""
    e = views.homonyms(s, d).select("doc_id", "ent_id")
    return resolve.block_all(e).agg(F.count("*").alias("pairs")).crossJoin(e.agg(F.count_distinct("doc_id").alias("documents")))


_TOP = f"""c as (select a.vec_id as a, b.vec_id as b, {DOT.format(a='a.v', b='b.v')} / sqrt({DOT.format(a='a.v', b='a.v')} * {DOT.format(a='b.v', b='b.v')}) as cos from al a join al b on a.vec_id <> b.vec_id),
r as (select *, row_number() over (partition by a order by cos desc, b) as rn from c), top as (select distinct least(a, b) as left_id, greatest(a, b) as right_id from r where rn <= 20), gold as (select vec_id - 1000000 as left_id, vec_id as right_id from al where vec_id >= 1000000)"""


@q(f"""with {V8}, {_TOP}, u as (select left_id, right_id, 'copies' as src from gold union all select left_id, right_id, 'vector' from top) select left_id, right_id, string_agg(src, '+' order by src) as sources from u group by all""")
def block_union(s, d):
    """Pairs of two blocks with the names of those that hold them."""
    v = views.near_duplicate_vectors(s, d)
    gold = v.where("vec_id <> gold_id").select(F.col("gold_id").alias("left_id"), F.col("vec_id").alias("right_id"))
    return resolve.block_union(vector=resolve.block_vector(v), copies=gold).select("left_id", "right_id", F.array_join("sources", "+").alias("sources"))


@q(f"""with {V8}, {_TOP} select count(*) as candidates, (select count(*) from gold) as gold, (select count(*) from top join gold using (left_id, right_id)) as kept, round((select count(*) from top join gold using (left_id, right_id)) / (select count(*) from gold), 6) as completeness,
round(1 - count(*) / ((select count(*) from al) * ((select count(*) from al) - 1) / 2), 6) as reduction from top""")
def blocking_exact(s, d):
    """Completeness and reduction of the exact nearest-neighbour block against planted copies."""
    v = views.near_duplicate_vectors(s, d)
    gold = v.where("vec_id <> gold_id").select(F.col("gold_id").alias("left_id"), F.col("vec_id").alias("right_id"))
    return M.blocking_quality(resolve.block_vector(v), gold, v.count())


@q(f"""with recursive {V8}, lk as (select a.vec_id as a, b.vec_id as b from al a join al b on b.vec_id = a.vec_id + 1000000), every as (select vec_id, case when vec_id >= 1000000 then vec_id - 1000000 else vec_id end as canonical_id from al)
select canonical_id, array_to_string(list_sort(list('v' || vec_id)), ',') as names, count(*) as members from every group by canonical_id""")
def resolution_collect(s, d):
    """Merged entities with their names and number of members, those without a partner included."""
    v = views.near_duplicate_vectors(s, d)
    pairs = resolve.block_vector(v).where("cos >= 0.95").withColumnRenamed("cos", "score")
    ents = v.select(F.col("vec_id").alias("ent_id"), F.concat(F.lit("v"), F.col("vec_id").cast("string")).alias("name"), F.create_map(F.lit("dob"), F.col("gold_id").cast("string")).alias("props"))
    decided = pairs.withColumn("action", F.lit("auto_merge")).withColumn("conflict", F.lit(False))
    merged, _, _, _ = resolve.collect_resolution(ents, resolve.clusters(pairs, ents), decided)
    return merged.select("canonical_id", F.array_join("names", ",").alias("names"), "members")


@q(None)
def phase_three_with_text(s, d):
    """The composed rule layer on planted documents: expansion, mining in the text, detection."""
    docs, ents = views.planted_text(s, d)
    with_aliases, mined, decided = names.enhance(ents, docs)
    known = mined.groupBy("rule").agg(F.count_distinct("ent_id").alias("n")).select(F.concat(F.lit("mined "), F.col("rule")).alias("step"), "n")
    return with_aliases.agg(F.sum(F.size("aliases")).alias("n")).select(F.lit("aliases").alias("step"), "n").unionByName(known).unionByName(decided.agg(F.count("*").alias("n")).select(F.lit("pairs").alias("step"), "n"))


@q(None)
def blocked_pairs_recall(s, d):
    """Pairs of a document alike at 0.75 among all pairs, and how many of them the blocks meet."""
    ents = views.homonyms(s, d)

    def alike(strategy):
        # few names, many pairs: pairs are counted by their names before anything is scored
        counted = names.candidate_pairs(ents, strategy).groupBy("name_a", "name_b").agg(F.count("*").alias("n"))
        return names.name_similarity(counted).where("score >= 0.75").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).withColumn("pairs", F.lit(strategy))

    return alike("all").unionByName(alike("blocked"))
