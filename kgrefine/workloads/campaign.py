"""The legacy chain against the full one on planted files, and the accuracy measures of both."""

from __future__ import annotations

from pyspark.sql import functions as F

from kgrefine import measures as M
from kgrefine.operators import chunks, clean, conform, extract, pages, relations
from kgrefine.plans.scratch import written
from kgrefine.sources import views

QUERIES: dict = {}
SQL: dict[str, str] = {}


def q(sql: str | None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return keep


#: Lines an answer holds before it is cut, as a model's answer is at its token limit.
ANSWER_LINES = 12
VOCABULARY = ("reported_to", "surveilled")
#: Pages a chunk has in the runs compared.
RUNS = {"legacy": 5, "full, 5 pages": 5, "full, 2 pages": 2}


def _chunks(rows, size):
    """(doc_id, chunk_no, text): the pages of a chunk under each other."""
    place = chunks.chunk_pages(rows, size, 0).select("doc_id", "chunk_no", F.col("page").alias("page_no"))
    line = F.struct("page_no", "text")
    return rows.join(place, ["doc_id", "page_no"]).groupBy("doc_id", "chunk_no").agg(F.array_join(F.transform(F.array_sort(F.collect_list(line)), lambda x: x["text"]), "\n").alias("text"))


def _pages(s, d):
    return written(views.planted_pages(s, d), "pages")


def _answers(s, rows, name):
    """Recovered answers of one run over pages: legacy reads the text layer of documents that the old guess sends to text; full routes each page."""
    if name == "legacy":
        rows = rows.join(pages.legacy_route(rows).where("legacy = 'text'"), "doc_id", "left_semi").select("doc_id", "page_no", "text")
    else:
        labelled = pages.classify_page(rows)
        routed = labelled.join(pages.route_document(labelled).select("doc_id", "route"), "doc_id")
        whole = routed.withColumn("label", F.when(F.col("route") == "mixed", F.col("label")).otherwise(F.col("route")))
        kept, seen = pages.split_mixed(whole.drop("vision_text"))
        rows = pages.merge_paths(kept, seen.join(rows.select("doc_id", "page_no", "vision_text"), ["doc_id", "page_no"])).select("doc_id", "page_no", "text")
    provider = extract.get_provider("statement", limit=ANSWER_LINES)
    return extract.recover_json(extract.run_provider(_chunks(rows, RUNS[name]), provider))


def _graph(s, rows, name):
    """(entities doc_id, name, type, surfaces; relations doc_id, src, dst, rel_type, quals by name) of one run."""
    got = written(_answers(s, rows, name), "answers")  # the model is called once
    ents, rels = extract.parse_entities(got).select("doc_id", "name", "type").distinct(), extract.parse_relations(got)
    if name == "legacy":
        return ents.withColumn("surfaces", F.array("name")), written(relations.dedup_relations(rels, "first"), "relations")
    snapped = conform.snap_predicates(rels, s.createDataFrame([(v,) for v in VOCABULARY], "label string")).withColumn("rel_type", F.col("canon")).drop("canon", "tier")
    ents, rels = clean.finalize(ents.withColumn("ent_id", F.col("name")), snapped, cut=lambda df: written(df, "graph"))
    ids = lambda end: ents.select("doc_id", F.col("ent_id").alias(end), F.col("name").alias(f"{end}_name"))
    rels = rels.join(ids("src"), ["doc_id", "src"]).join(ids("dst"), ["doc_id", "dst"]).withColumn("src", F.col("src_name")).withColumn("dst", F.col("dst_name"))
    ents, rels = written(ents, "graph"), written(rels, "graph")  # both are read more than once from here
    return ents.select("doc_id", "name", "type", F.array_union(F.array("name"), "aliases").alias("surfaces")), written(relations.dedup_relations(rels), "relations")


def _gold(s, d):
    """(entities doc_id, name, type, surface; relations doc_id, src, dst, rel_type, year) that the planted statements hold."""
    st = views.planted_statements(s, d)
    core = lambda c: F.lower(F.array_join(F.slice(F.split(c, " "), -2, 2), " "))
    label = F.when(F.col("label") == "surveiled", "SURVEILLED").otherwise("REPORTED_TO")
    rels = st.select("k", "doc_id", core("src").alias("src"), core("dst").alias("dst"), label.alias("rel_type"), "year").where("src <> dst")
    rels = rels.groupBy("doc_id", "src", "dst", "rel_type").agg(F.min_by("year", "k").alias("year"))
    ents = st.select("doc_id", F.explode(F.array("src", "dst")).alias("surface")).distinct()
    kind = F.when(F.col("surface").endswith(" Company"), "ORGANIZATION").otherwise("PERSON")
    return ents.select("doc_id", core("surface").alias("name"), kind.alias("type"), "surface"), rels


def _garbled(c: str, when: str) -> str:
    return f"case when {when} then translate({c}, 'aeiou', '43107') else {c} end"


_CORE = "lower(array_to_string(list_slice(string_split({c}, ' '), -2, -1), ' '))"
_LABEL = "case when label = 'surveiled' then 'SURVEILLED' else 'REPORTED_TO' end"
STATEMENTS = f"""nm as (select p_partkey as k, p_partkey // 20 as doc_id, case when p_partkey % 5 = 0 then (['Dr.', 'Captain', 'Agent'])[p_partkey % 3 + 1] || ' ' else '' end
  || array_to_string(list_transform(string_split(p_name, ' '), lambda w: upper(w[1]) || w[2:]), ' ') || case when p_partkey % 7 = 0 then ' Company' else '' end as src from part),
st as (select a.k, a.doc_id, (a.k % 20) // 4 + 1 as page_no, a.src, (['reported to', 'Reported-To', 'REPORTED_TO', 'surveiled'])[a.k % 4 + 1] as label, case when a.k % 9 = 0 then a.src else coalesce(b.src, a.src) end as dst,
  cast(1990 + a.k % 30 as varchar) as year from nm a left join nm b on b.k = a.doc_id * 20 + (a.k + 1) % 20),
rd as (select n.pipeline, n.size, st.*, (page_no - 1) // n.size as chunk_no, n.pipeline = 'legacy' and page_no between 2 and 4 as bad, row_number() over (partition by n.pipeline, doc_id, (page_no - 1) // n.size order by k) as rn
  from st, (values ('legacy', 5), ('full, 5 pages', 5), ('full, 2 pages', 2)) n(pipeline, size)),
seen as (select pipeline, k, doc_id, chunk_no, {_garbled('src', 'bad')} as src, {_garbled('label', 'bad')} as label, {_garbled('dst', 'bad')} as dst, year from rd where rn <= 12),
both_ as (select pipeline, doc_id, src as surface from seen union select pipeline, doc_id, dst from seen),
ent as (select pipeline, doc_id, case when pipeline = 'legacy' then lower(surface) else {_CORE.format(c='surface')} end as name, case when pipeline <> 'legacy' and ends_with(surface, ' Company') then 'ORGANIZATION' else 'PERSON' end as type, surface from both_),
ends as (select pipeline, doc_id, k, case when pipeline = 'legacy' then src else {_CORE.format(c='src')} end as src, case when pipeline = 'legacy' then dst else {_CORE.format(c='dst')} end as dst, case when pipeline = 'legacy' then label else {_LABEL} end as rel_type, year from seen),
rel as (select pipeline, doc_id, src, dst, rel_type, arg_min(year, k) as year from ends where pipeline = 'legacy' or src <> dst group by all),
g_all as (select doc_id, src as surface from st union select doc_id, dst from st),
g_ent as (select doc_id, {_CORE.format(c='surface')} as name, case when ends_with(surface, ' Company') then 'ORGANIZATION' else 'PERSON' end as type, surface from g_all),
g_rel as (select doc_id, src, dst, rel_type, arg_min(year, k) as year from (select k, doc_id, {_CORE.format(c='src')} as src, {_CORE.format(c='dst')} as dst, {_LABEL} as rel_type, year from st) where src <> dst group by all)"""


@q(f"""with {STATEMENTS}, e as (select distinct pipeline, doc_id, type, case when pipeline = 'legacy' then surface else name end as name from ent), g as (select distinct doc_id, name from g_ent)
select p as pipeline, (select count(*) from e where pipeline = p) as entities, (select count(distinct type) from e where pipeline = p) as entity_types, (select count(*) from rel where pipeline = p) as relations, (select count(distinct rel_type) from rel where pipeline = p) as relation_types,
 (select count(*) from rel where pipeline = p and src = dst) as self_loops, (select count(*) from g) as gold, (select count(*) from g where exists (select 1 from e where pipeline = p and e.doc_id = g.doc_id and lower(e.name) = g.name)) as gold_found,
 (select count(*) from e where pipeline = p and not exists (select 1 from g_ent x where x.doc_id = e.doc_id and lower(e.name) in (x.name, lower(x.surface)))) as hallucinated from (values ('legacy'), ('full, 5 pages'), ('full, 2 pages')) v(p)""")
def legacy_vs_full(s, d):
    """The unguided chain (old routing, raw labels, no cleaning) against the full one with five and two pages to a chunk, on the same planted files and provider."""
    gold, _ = _gold(s, d)
    known = gold.select("doc_id", F.explode(F.array("name", F.lower("surface"))).alias("low")).distinct()
    names, out, rows = written(gold.select("doc_id", "name").distinct(), "gold"), None, _pages(s, d)
    known = written(known, "gold")
    for name in RUNS:
        ents, rels = _graph(s, rows, name)
        ents = ents.select("doc_id", "type", F.lower("name").alias("low"))
        e = ents.agg(F.count("*").alias("entities"), F.count_distinct("type").alias("entity_types"))
        r = rels.agg(F.count("*").alias("relations"), F.count_distinct("rel_type").alias("relation_types"), F.count_if(F.col("src") == F.col("dst")).alias("self_loops"))
        g = names.join(ents.select("doc_id", F.col("low").alias("name"), F.lit(1).alias("hit")).distinct(), ["doc_id", "name"], "left").agg(F.count("*").alias("gold"), F.count("hit").alias("gold_found"))
        h = ents.join(known, ["doc_id", "low"], "left_anti").agg(F.count("*").alias("hallucinated"))
        row = e.crossJoin(r).crossJoin(g).crossJoin(h).withColumn("pipeline", F.lit(name))  # one row each
        out = row if out is None else out.unionByName(row)
    return out


def _f1_sql(found: str, gold: str, keys: str) -> str:
    return f"""with {STATEMENTS}, f as ({found}), g as ({gold}), j as (select v.pipeline, f.pipeline is not null as in_f, g.one is not null as in_g from (values ('legacy'), ('full, 5 pages'), ('full, 2 pages')) v(pipeline)
  join (select * from f) f using (pipeline) left join g using ({keys}) union all select v.pipeline, false, true from (values ('legacy'), ('full, 5 pages'), ('full, 2 pages')) v(pipeline) cross join g where not exists (select 1 from f where f.pipeline = v.pipeline and {' and '.join(f'f.{k.strip()} = g.{k.strip()}' for k in keys.split(','))}))
select pipeline, count(*) filter (in_f and in_g) as tp, count(*) filter (not in_g) as fp, count(*) filter (not in_f) as fn, round(count(*) filter (in_f and in_g) / greatest(count(*) filter (in_f), 1), 6) as precision,
 round(count(*) filter (in_f and in_g) / greatest(count(*) filter (in_g), 1), 6) as recall, round(2 * count(*) filter (in_f and in_g) / (count(*) filter (in_f) + count(*) filter (in_g)), 6) as f1 from j group by pipeline"""


def _each_run(s, d, found, gold, keys):
    out = None
    for name in RUNS:
        row = M.set_f1(found(name), gold, keys).withColumn("pipeline", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


@q(_f1_sql("select distinct pipeline, doc_id, cast(rd_page as integer) as page_no, place, name from (select s.pipeline, s.doc_id, st.page_no as rd_page, s.k * 2 as place, s.src as name from seen s join st using (k) union all select s.pipeline, s.doc_id, st.page_no, s.k * 2 + 1, s.dst from seen s join st using (k))",
           "select distinct doc_id, cast(page_no as integer) as page_no, k * 2 as place, src as name, 1 as one from st union all select doc_id, cast(page_no as integer), k * 2 + 1, dst, 1 from st", "doc_id, place, name"))
def entity_span_f1(s, d):
    """Mentions at their places in the document, right only if the name is read right; places come from the provider's character offsets."""
    st = views.planted_statements(s, d)
    size = F.length("src") + F.length("label") + F.length("dst") + F.length("year") + 13
    from pyspark.sql import Window

    def lines(name):
        """(doc_id, chunk_no, start, place): where each mention stands in its chunk."""
        rows = st.withColumn("chunk_no", F.expr(f"(page_no - 1) div {RUNS[name]}").cast("int"))
        w = Window.partitionBy("doc_id", "chunk_no").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)  # a chunk has twenty lines at most
        rows = rows.withColumn("at", F.coalesce(F.sum(size).over(w), F.lit(0)))
        ends = F.array(F.struct(F.col("at").alias("start"), (F.col("k") * 2).alias("place")), F.struct((F.col("at") + F.length("src") + F.length("label") + 8).alias("start"), (F.col("k") * 2 + 1).alias("place")))
        return rows.select("doc_id", "chunk_no", F.inline(ends))

    rows = _pages(s, d)

    def found(name):
        return extract.parse_spans(_answers(s, rows, name)).join(lines(name), ["doc_id", "chunk_no", "start"])

    gold = st.select("doc_id", F.inline(F.array(F.struct((F.col("k") * 2).alias("place"), F.col("src").alias("name")), F.struct((F.col("k") * 2 + 1).alias("place"), F.col("dst").alias("name")))))
    return _each_run(s, d, found, gold, ["doc_id", "place", "name"])


@q(_f1_sql("select distinct pipeline, doc_id, lower(src) as src, lower(dst) as dst from rel", "select distinct doc_id, src, dst, 1 as one from g_rel", "doc_id, src, dst"))
def relation_pair_f1(s, d):
    """Ordered pairs of related names, whatever the label."""
    low = lambda r: r.select("doc_id", F.lower("src").alias("src"), F.lower("dst").alias("dst"))
    rows = _pages(s, d)
    return _each_run(s, d, lambda name: low(_graph(s, rows, name)[1]), low(_gold(s, d)[1]), ["doc_id", "src", "dst"])


@q(_f1_sql("select distinct pipeline, doc_id, lower(src) as src, lower(dst) as dst, rel_type from rel", "select distinct doc_id, src, dst, rel_type, 1 as one from g_rel", "doc_id, src, dst, rel_type"))
def triple_f1(s, d):
    """Names and label together."""
    low = lambda r: r.select("doc_id", F.lower("src").alias("src"), F.lower("dst").alias("dst"), "rel_type")
    rows = _pages(s, d)
    return _each_run(s, d, lambda name: low(_graph(s, rows, name)[1]), low(_gold(s, d)[1]), ["doc_id", "src", "dst", "rel_type"])


@q(f"""with {STATEMENTS}, e as (select distinct doc_id, name, type from ent where pipeline = 'full, 5 pages'), f as (select * from ent where pipeline = 'full, 5 pages'), r as (select * from rel where pipeline = 'full, 5 pages'), ge as (select distinct doc_id, name, type from g_ent),
x as (select 'entity completeness' as dimension, exists (select 1 from e where e.doc_id = ge.doc_id and e.name = ge.name) as ok from ge
 union all select 'entity typing', exists (select 1 from ge where e.doc_id = ge.doc_id and e.name = ge.name and e.type = ge.type) from e
 union all select 'entity properties', exists (select 1 from f where f.doc_id = g.doc_id and f.surface = g.surface) from g_ent g where lower(surface) <> name
 union all select 'relation completeness', exists (select 1 from r where r.doc_id = g.doc_id and r.src = g.src and r.dst = g.dst and r.rel_type = g.rel_type) from g_rel g
 union all select 'relation accuracy', exists (select 1 from g_rel g where r.doc_id = g.doc_id and r.src = g.src and r.dst = g.dst and r.rel_type = g.rel_type) from r
 union all select 'qualifier accuracy', r.year = g.year from r join g_rel g on r.doc_id = g.doc_id and r.src = g.src and r.dst = g.dst and r.rel_type = g.rel_type),
m as (select dimension, round(100 * avg(case when ok then 1.0 else 0.0 end), 4) as pct from x group by dimension) select dimension, pct from m union all select 'mean', round(avg(pct), 4) from m""")
def accuracy_dimensions(s, d):
    """The six dimensions of the full run with five pages to a chunk against the planted statements: what is there, its other forms and type; relations found, right, and with the right year."""
    ents, rels = _graph(s, _pages(s, d), "full, 5 pages")
    gold, gold_rels = (written(df, "gold") for df in _gold(s, d))
    ents = ents.withColumn("name", F.lower("name"))
    rels = rels.select("doc_id", F.lower("src").alias("src"), F.lower("dst").alias("dst"), "rel_type", F.col("quals")["year"].alias("found_year"))
    key = ["doc_id", "src", "dst", "rel_type"]

    def part(name, rows, other, keys):
        hit = rows.join(other.select(*keys).distinct().withColumn("hit", F.lit(True)), keys, "left")
        return hit.select(F.lit(name).alias("dimension"), F.coalesce("hit", F.lit(False)).alias("ok"))

    whole = gold.select("doc_id", "name", "type").distinct()
    surfaces = ents.select("doc_id", F.explode("surfaces").alias("surface"))
    checks = [part("entity completeness", whole, ents, ["doc_id", "name"]), part("entity typing", ents.select("doc_id", "name", "type"), whole, ["doc_id", "name", "type"]),
              part("entity properties", gold.where("lower(surface) <> name").select("doc_id", "surface"), surfaces, ["doc_id", "surface"]),
              part("relation completeness", gold_rels, rels, key), part("relation accuracy", rels, gold_rels, key),
              rels.join(gold_rels, key).select(F.lit("qualifier accuracy").alias("dimension"), (F.col("found_year") == F.col("year")).alias("ok"))]
    out = checks[0]
    for c in checks[1:]:
        out = out.unionByName(c)
    return M.accuracy_dimensions(out)


#: Lines that the answers of the providers compared may hold; 0: all.
PROVIDERS = {"all lines": 0, "twelve lines": 12, "three lines": 3}


@q(f"""with {STATEMENTS}, p as (select * from (values ('all lines', 1000), ('twelve lines', 12), ('three lines', 3)) v(provider, most)), l as (select doc_id, k, src, dst, rn from rd where pipeline = 'full, 5 pages'),
f as (select provider, doc_id, src as name from l, p where rn <= most union select provider, doc_id, dst from l, p where rn <= most), c as (select provider, count(*) as tp from f group by 1), g as (select count(*) as n from g_all)
select provider, tp, 0::bigint as fp, n - tp as fn, 1.0::double as precision, round(tp / n, 6) as recall, round(2 * tp / (tp + n), 6) as f1 from c, g""")
def provider_comparison(s, d):
    """Providers whose answers end after different numbers of lines, on the same chunks, against the names that the planted statements hold."""
    rows = views.planted_pages(s, d).select("doc_id", "page_no", F.col("vision_text").alias("text"))
    c = written(_chunks(rows, 5), "chunks")
    st = views.planted_statements(s, d)
    gold = st.select("doc_id", F.explode(F.array("src", "dst")).alias("name"))
    out = None
    for name, limit in PROVIDERS.items():
        found = extract.parse_entities(extract.recover_json(extract.run_provider(c, extract.get_provider("statement", limit=limit))))
        row = M.set_f1(found, gold, ["doc_id", "name"]).withColumn("provider", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out
