"""The experiment workloads on the given tables, each with the SQL of the same rows where SQL can express it."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgrefine import measures as M
from kgrefine.operators import chunks, clean, conform, extract, gates, names, ontology, pages, relations, resolve, tabular
from kgrefine.plans.scratch import written
from kgrefine.sources import views
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


# pages and routing

V4 = """sig as (select l_orderkey as doc_id, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey) as page_no,
  case when l_tax = 0 and l_discount = 0 then 0.0 else 1.0 end as area, l_discount * 1.8 as img_block, l_tax * 2 as img_xref, case when l_tax > 0 then 1 else 0 end as n_xref,
  cast(greatest(l_quantity - 15, 0) * 20 as bigint) as chars, l_linenumber * 45 as drawings from lineitem)"""


def _label(xref: bool = True, draw: bool = True) -> str:
    return ("case when area = 0 then 'skip' when img_block > 0.15 then 'ocr' " + ("when n_xref > 0 and img_xref > 0.15 then 'ocr' " if xref else "") + "when chars > 50 then 'text' "
            + ("when drawings > 200 then 'ocr' " if draw else "") + "when chars > 0 then 'text' else 'skip' end")


LABELLED = f"with {V4}, lab as (select *, {_label()} as label from sig)"
ROUTED = LABELLED + """, cnt as (select doc_id, count(*) filter (label = 'text') as n_text, count(*) filter (label = 'ocr') as n_ocr, count(*) filter (label = 'skip') as n_skip,
  avg(case when chars > 0 then 1.0 else 0.0 end) >= 0.5 and avg(chars) >= 50 as good from lab group by doc_id), rt as (select doc_id, n_text, n_ocr, n_skip, good,
  case when n_text + n_ocr = 0 then case when good then 'text' else 'ocr' end when n_text >= 0.8 * (n_text + n_ocr) then 'text' when n_text <= 0.2 * (n_text + n_ocr) then 'ocr' else 'mixed' end as route,
  n_text + n_ocr = 0 as fallback from cnt)"""


@q(LABELLED + " select doc_id, cast(page_no as integer) as page_no, label from lab")
def page_classify(s, d):
    return pages.classify_page(views.page_signals(s, d)).select("doc_id", "page_no", "label")


@q(f"with {V4} select {_label()} as label, {_label(xref=False)} as no_xref, {_label(draw=False)} as no_draw, count(*) as n from sig group by all")
def page_ablation(s, d):
    sig = views.page_signals(s, d)
    rows = pages.classify_page(sig).withColumnRenamed("label", "l0").drop("deciding")
    rows = pages.classify_page(rows, disable={"xref"}).withColumnRenamed("label", "no_xref").drop("deciding")
    rows = pages.classify_page(rows, disable={"draw"}).withColumnRenamed("label", "no_draw").withColumnRenamed("l0", "label")
    return rows.groupBy("label", "no_xref", "no_draw").agg(F.count("*").alias("n"))


@q(ROUTED + " select doc_id, n_text, n_ocr, n_skip, route, fallback from rt")
def doc_route(s, d):
    return pages.route_document(pages.classify_page(views.page_signals(s, d)))


@q(ROUTED + """ select route, case when good then 'text' else 'ocr' end as legacy, count(*) as docs, cast(sum(case when good then n_ocr else 0 end) as bigint) as pages_lost,
 cast(sum(case when good then 0 else n_text end) as bigint) as pages_wasted from rt group by all""")
def route_vs_legacy(s, d):
    sig = views.page_signals(s, d)
    return M.route_confusion(pages.route_document(pages.classify_page(sig)), pages.legacy_route(sig))


@q("""select page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) as chars, cast(len(regexp_extract_all(html, '<[^>]+>')) as bigint) as tags, cast(len(regexp_extract_all(html, '<li>')) as bigint) as list_items,
 round(1 - length(regexp_replace(html, '<[^>]*>', '', 'g')) / length(html), 6) as markup_share from pages""")
def html_page_signals(s, d):
    return pages.html_signals(t(s, d, "pages"))


@q(None)
def virtual_pages(s, d):
    return pages.virtual_pages(t(s, d, "pages"))


@q(ROUTED + " select 'text' as path, count(*) as n from lab join rt using (doc_id) where route = 'mixed' and label = 'text' union all select 'ocr', count(*) from lab join rt using (doc_id) where route = 'mixed' and label = 'ocr'")
def mixed_split(s, d):
    lab = pages.classify_page(views.page_signals(s, d)).withColumn("text", F.lit("x"))
    mixed = lab.join(pages.route_document(lab).where("route = 'mixed'").select("doc_id"), "doc_id", "left_semi")
    kept, seen = pages.split_mixed(mixed)
    both = pages.merge_paths(kept, seen.withColumn("vision_text", F.lit("y")))
    return both.where("text <> ''").groupBy(F.when(F.col("text") == "x", "text").otherwise("ocr").alias("path")).agg(F.count("*").alias("n"))


# chunks and windows

CHUNKS = """with n as (select doc_id, text, length(text) as n, greatest(cast(ceil((length(text) - {o}) / {p}.0) as bigint) - 1, 0) as last from documents),
c as (select doc_id, text, n, last, i from n, range(0, 100000) r(i) where i <= last)"""


@q(CHUNKS.format(o=1000, p=7000) + """ select doc_id, cast(i as integer) as chunk_no, cast(i * 7000 as integer) as p_start, cast(case when i = last then n else i * 7000 + 7000 end as integer) as p_end,
 cast(i * 7000 as integer) as o_start, cast(least(i * 7000 + 8000, n) as integer) as o_end, md5(substring(text, i * 7000 + 1, 8000)) as text_md5 from c""")
def chunk_chars(s, d):
    rows = chunks.chunk_chars(t(s, d, "documents"), annotate=False)
    return rows.select("doc_id", "chunk_no", "p_start", "p_end", "o_start", "o_end", F.md5("text").alias("text_md5"))


@q("""with p as (select conv_id, cast(turn + 1 as bigint) as page from conversations), e as (select conv_id, page, cast(floor((page - 1) / 5) as bigint) as own, greatest(cast(floor((page - 2) / 5.0) as bigint), 0) as lo, cast(floor(page / 5) as bigint) as hi from p),
x as (select conv_id, page, c, own = c as is_own from e, range(0, 100) r(c) where c between lo and hi) select conv_id as doc_id, cast(c as integer) as chunk_no, cast(page as integer) as page, is_own as "primary" from x
where exists (select 1 from e where e.conv_id = x.conv_id and e.own = x.c)""")
def chunk_turns(s, d):
    return chunks.chunk_pages(t(s, d, "conversations").withColumn("page_no", F.col("turn") + 1), id_col="conv_id")


@q(CHUNKS.format(o=300, p=1200) + " select doc_id, cast(i as integer) as win_no, cast(i * 1200 as integer) as w_start, cast(least(i * 1200 + 1500, n) as integer) as w_end, md5(substring(text, i * 1200 + 1, 1500)) as text_md5 from c where i < 4")
def windows_fixed(s, d):
    return chunks.windows_fixed(t(s, d, "documents")).select("doc_id", "win_no", "w_start", "w_end", F.md5("text").alias("text_md5"))


LEXICON = ("the", "und", "les", "que")


@q(None)
def windows_dense(s, d):
    return chunks.windows_dense(t(s, d, "documents"), LEXICON).select("doc_id", "win_no", F.round("density", 6).alias("density"), F.length("text").alias("n"))


@q("""with p as (select doc_id, unnest(string_split_regex(text, chr(10) || '+')) as para from documents)
select doc_id, md5(para) as para, round((coalesce(list_sum(list_transform(regexp_extract_all(para, '[a-z,;] ([A-Z][a-z]+)', 1), lambda w: length(w))), 0)
 + 6 * len(regexp_extract_all(lower(para), '(^|[^a-z])(the|und|les|que)($|[^a-z])'))) / length(para), 6) as density, count(*) as n from p where para <> '' group by all""")
def paragraph_density(s, d):
    p = t(s, d, "documents").select("doc_id", F.explode(F.split("text", "\n+")).alias("para")).where("para <> ''")
    return p.groupBy("doc_id", F.md5("para").alias("para"), F.round(chunks.density(F.col("para"), LEXICON), 6).alias("density")).agg(F.count("*").alias("n"))


# ontology retrieval

DOT = "list_sum(list_transform(list_zip({a}, {b}), lambda p: p[1] * p[2]))"
UNIT = "list_transform({v}, lambda x: x / sqrt(list_sum(list_transform({v}, lambda y: y * y))))"
V1 = f"""e as (select vec_id, list_transform(embedding, lambda x: cast(x as double)) as v from embeddings),
cls as (select c.vec_id as class_id, case when c.vec_id >= 10 then p.vec_id end as parent, case when c.vec_id < 10 then c.v else {UNIT.format(v='list_transform(list_zip(p.v, c.v), lambda z: 0.8 * z[1] + 0.6 * z[2])')} end as vec
  from e c join e p on p.vec_id = c.vec_id % 10 where c.vec_id < 100),
qw as (select e.vec_id, cast(floor(e.vec_id / 4) as bigint) as doc_id, cast(e.vec_id % 4 as integer) as win_no, e.vec_id % 100 as gold_class,
  {UNIT.format(v='list_transform(list_zip(c.vec, e.v), lambda z: z[1] * ([0.45, 0.5, 0.55, 0.65])[cast(floor(e.vec_id / 100) as bigint) % 4 + 1] + z[2] * (1 - ([0.45, 0.5, 0.55, 0.65])[cast(floor(e.vec_id / 100) as bigint) % 4 + 1]))')} as vec
  from e join cls c on c.class_id = e.vec_id % 100 where e.vec_id >= 100),
raw as (select qw.vec_id, doc_id, win_no, gold_class, class_id, {DOT.format(a='qw.vec', b='cls.vec')} / sqrt({DOT.format(a='qw.vec', b='qw.vec')} * {DOT.format(a='cls.vec', b='cls.vec')}) as cos from qw, cls),
best as (select doc_id, class_id, max(cos) as score from raw where cos >= 0.72 group by all)"""
EXPANDED = V1 + """, ex as (select doc_id, class_id, max(score) as score, max(prov) as provenance from (select doc_id, class_id, score, 'retrieved' as prov from best
  union all select b.doc_id, c.class_id, 0.78, 'expanded' from best b join cls c on c.parent = b.class_id where b.score >= 0.80) group by all)"""


def _hits(s, d):
    classes = views.ontology_classes(s, d)
    windows = views.query_windows(s, d, classes)
    hits = ontology.retrieve_classes(windows, classes, 0.72)
    return classes, windows, hits, ontology.best_per_class(hits, "cos")


@q(f"with {V1} select doc_id, class_id, round(score, 4) as score from best")
def class_retrieval_baseline(s, d):
    return _hits(s, d)[3].select("doc_id", "class_id", F.round("score", 4).alias("score"))


@q(f"with {EXPANDED} select doc_id, class_id, round(score, 4) as score, provenance from ex")
def class_retrieval_refined(s, d):
    classes, _, _, best = _hits(s, d)
    return ontology.expand_children(best, views.subclass_edges(classes)).select("doc_id", "class_id", F.round("score", 4).alias("score"), "provenance")


@q(f"""with {V1} select count(*) as windows, count(*) filter (hit72) as found_72, count(*) filter (hit50) as found_50, round(avg(n72), 6) as hits_72, round(avg(n50), 6) as hits_50 from
(select vec_id, bool_or(class_id = gold_class and cos >= 0.72) as hit72, bool_or(class_id = gold_class and cos >= 0.5) as hit50, count(*) filter (cos >= 0.72) as n72, count(*) filter (cos >= 0.5) as n50 from raw group by vec_id)""")
def retrieval_recall_planted(s, d):
    classes = views.ontology_classes(s, d)
    w = views.query_windows(s, d, classes)
    hits = ontology.retrieve_classes(w, classes, 0.5).join(w.select("doc_id", "win_no", "gold_class"), ["doc_id", "win_no"])
    own = F.col("class_id") == F.col("gold_class")
    per = hits.groupBy("doc_id", "win_no").agg(F.max(own & (F.col("cos") >= 0.72)).alias("h72"), F.max(own).alias("h50"), F.count_if(F.col("cos") >= 0.72).alias("n72"), F.count("*").alias("n50"))
    rows = w.select("doc_id", "win_no").join(per, ["doc_id", "win_no"], "left").na.fill(0)
    return rows.agg(F.count("*").alias("windows"), F.count_if(F.col("h72")).alias("found_72"), F.count_if(F.col("h50")).alias("found_50"), F.round(F.avg("n72"), 6).alias("hits_72"), F.round(F.avg("n50"), 6).alias("hits_50"))


@q(f"with {V1} select vec_id, class_id, cast(rank as integer) as rank from (select vec_id, class_id, row_number() over (partition by vec_id order by round(cos, 9) desc, class_id) as rank from raw) where rank <= 5")
def class_retrieval_topk(s, d):
    classes = views.ontology_classes(s, d)
    w = views.query_windows(s, d, classes)
    hits = ontology.retrieve_classes(w, classes, -1.0).withColumn("score", F.round("cos", 9)).select(F.col("doc_id").alias("dd"), (F.col("doc_id") * 4 + F.col("win_no")).alias("doc_id"), "class_id", "score")
    return ontology.cutoff_topk(hits, 5).select(F.col("doc_id").alias("vec_id"), "class_id", "rank")


@q(f"""with {EXPANDED}, tok as (select *, 200 + class_id * 37 % 400 as tokens from ex), run as (select *, sum(tokens) over (partition by doc_id order by round(score, 9) desc, class_id rows unbounded preceding) as used from tok where score >= 0.72)
select doc_id, class_id, cast(used as bigint) as used from run where used <= 1200""")
def token_budget_cutoff(s, d):
    classes, _, _, best = _hits(s, d)
    hits = ontology.expand_children(best, views.subclass_edges(classes)).withColumn("tokens", F.lit(200) + F.col("class_id") * 37 % 400).withColumn("score", F.round("score", 9))
    return ontology.cutoff(hits, budget=1200).select("doc_id", "class_id", "used")


@q(f"""with {EXPANDED}, full_slice as (select cast(sum(floor(length('class ' || class_id || ' : things of kind ' || class_id || ' and ' || repeat('x', cast(class_id * 37 % 400 as integer))) / 4)) as bigint) as tokens from cls),
live as (select doc_id, cast(sum(floor(length('class ' || class_id || ' : things of kind ' || class_id || ' and ' || repeat('x', cast(class_id * 37 % 400 as integer))) / 4)) as bigint) as tokens from ex group by doc_id)
select count(*) as docs, (select tokens from full_slice) as static_tokens, round(avg(tokens), 4) as live_tokens, round(100 * (1 - avg(tokens) / (select tokens from full_slice)), 4) as saved_pct from live""")
def catalog_tokens_static_vs_live(s, d):
    classes, _, _, best = _hits(s, d)
    sized = classes.select("class_id", ontology.token_estimate(F.concat_ws(" : ", "label", "definition")).alias("tokens"))
    full = sized.agg(F.sum("tokens").alias("static_tokens"))
    live = ontology.expand_children(best, views.subclass_edges(classes)).join(sized, "class_id").groupBy("doc_id").agg(F.sum("tokens").alias("tokens"))
    rows = live.agg(F.count("*").alias("docs"), F.avg("tokens").alias("mean")).crossJoin(F.broadcast(full))
    return rows.select("docs", "static_tokens", F.round("mean", 4).alias("live_tokens"), F.round(100 * (1 - F.col("mean") / F.col("static_tokens")), 4).alias("saved_pct"))


TREE = """recursive edge as (select 'n' || n_nationkey as child, 'r' || n_regionkey as parent from nation union all select 'r' || r_regionkey, 'root' from region),
up as (select child, child as ancestor, 0 as hop from (select child from edge union select parent from edge) union all select u.child, e.parent, u.hop + 1 from up u join edge e on u.ancestor = e.child),
pred as (select 'at_r' || r_regionkey as pred_id, 'r' || r_regionkey as domain, 'root' as range from region union all select 'by_n' || n_nationkey, 'n' || n_nationkey, 'r' || n_regionkey from nation where n_nationkey % 2 = 0),
hit as (select distinct o_custkey % 50 as doc_id, 'n' || (o_custkey % 25) as class_id from orders)"""


def _tree(s, d):
    n, r = t(s, d, "nation"), t(s, d, "region")
    key = lambda p, c: F.concat(F.lit(p), F.col(c).cast("string"))
    edge = n.select(key("n", "n_nationkey").alias("child"), key("r", "n_regionkey").alias("parent")).unionByName(r.select(key("r", "r_regionkey").alias("child"), F.lit("root").alias("parent")))
    pred = r.select(key("at_r", "r_regionkey").alias("pred_id"), key("r", "r_regionkey").alias("domain"), F.lit("root").alias("range")).unionByName(
        n.where("n_nationkey % 2 = 0").select(key("by_n", "n_nationkey").alias("pred_id"), key("n", "n_nationkey").alias("domain"), key("r", "n_regionkey").alias("range")))
    hit = t(s, d, "orders").select((F.col("o_custkey") % 50).alias("doc_id"), F.concat(F.lit("n"), (F.col("o_custkey") % 25).cast("string")).alias("class_id")).distinct()
    return edge, pred, hit


@q(f"with {TREE} select child, ancestor, min(hop) as hop from up group by all")
def class_closure(s, d):
    return ontology.closure(_tree(s, d)[0])


@q(f"with {TREE} select distinct doc_id, pred_id from hit join pred on class_id in (domain, range)")
def predicates_exact(s, d):
    _, pred, hit = _tree(s, d)
    return ontology.predicates_exact(hit, pred).select("doc_id", "pred_id")


@q(f"with {TREE} select doc_id, pred_id, min(hop) as hop from hit join up on child = class_id join pred on ancestor in (domain, range) group by all")
def predicates_ancestor(s, d):
    edge, pred, hit = _tree(s, d)
    return ontology.predicates_ancestor(hit, ontology.closure(edge), pred)


@q("""with w as (select item_id, unnest(string_split_regex(lower(text), '[^a-z0-9]+')) as term from benchmark), tf as (select item_id, term, count(*) as tf from w where term <> '' group by all),
len as (select item_id, sum(tf) as len from tf group by all), df as (select term, count(*) as df from tf group by all), st as (select count(*) as n, avg(len) as mean from len),
qt as (select distinct doc_id, unnest(string_split_regex(lower(text), '[^a-z0-9]+')) as term from documents)
select doc_id, item_id as pred_id, round(sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * len / mean))), 4) as bm25 from qt join tf using (term) join df using (term) join len using (item_id), st group by all""")
def predicates_fulltext(s, d):
    b = t(s, d, "benchmark").select(F.col("item_id").alias("pred_id"), F.lit("").alias("label"), F.col("text").alias("definition"))
    terms = t(s, d, "documents").select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-z0-9]+"))).alias("term"))
    return ontology.predicate_fulltext(terms, b).select("doc_id", "pred_id", F.round("bm25", 4).alias("bm25"))


def _rank_parts(edge: str, rounds: int = 10) -> list[str]:
    parts = [f"edge as ({edge})", "node as (select src as node from edge union select dst from edge)",
             "deg as (select src, count(*) as deg from edge group by src)", "r0 as (select node, 1.0::double / (select count(*) from node) as pr from node)"]
    for i in range(1, rounds + 1):
        parts.append(f"""r{i} as (select n.node, 0.15 / (select count(*) from node) + 0.85 * (coalesce((select sum(p.pr / d.deg) from edge e join r{i - 1} p on p.node = e.src join deg d on d.src = e.src where e.dst = n.node), 0)
          + (select coalesce(sum(pr), 0) from r{i - 1} where node not in (select src from edge)) / (select count(*) from node)) as pr from node n)""")
    return parts


_UP = "select 'n' || n_nationkey as src, 'r' || n_regionkey as dst from nation union all select 'r' || r_regionkey, 'root' from region"


@q("with " + ", ".join(_rank_parts(_UP)) + " select node, round(pr, 8) as pr, round(pr / (select max(pr) from r10), 8) as pr_max from r10")
def ontology_pagerank(s, d):
    edge = _tree(s, d)[0].select(F.col("child").alias("src"), F.col("parent").alias("dst"))
    return ontology.pagerank(edge, rounds=10).select("node", F.round("pr", 8).alias("pr"), F.round("pr_max", 8).alias("pr_max"))


@q(f"with {V1}, " + ", ".join(_rank_parts("select class_id as src, parent as dst from cls where parent is not null")) + """, pr as (select node, pr / (select max(pr) from r10) as pr from r10)
select doc_id, class_id, round(max(cos * (1 - 0.4 * coalesce(pr, 0))), 4) as score from raw left join pr on node = class_id where cos >= 0.72 group by doc_id, class_id""")
def class_retrieval_penalized(s, d):
    classes, _, hits, _ = _hits(s, d)
    pr = ontology.pagerank(views.subclass_edges(classes).select(F.col("child").alias("src"), F.col("parent").alias("dst")), rounds=10).select(F.col("node").alias("class_id"), F.col("pr_max").alias("pr"))
    return ontology.best_per_class(ontology.penalize(hits, pr)).select("doc_id", "class_id", F.round("score", 4).alias("score"))


VOCAB = {"de": ("der", "die", "und", "das"), "en": ("the", "and", "of"), "es": ("los", "que", "del"), "fr": ("les", "des", "une")}


def _router_sql() -> str:
    hit = lambda text, words: "len(list_filter(string_split_regex(lower(coalesce(" + text + ", '')), '[^a-zà-ÿ]+'), lambda w: w in (" + ", ".join(f"'{w}'" for w in words) + ")))"
    cols = ", ".join(f"{hit('url', w)} as n_{k}, {hit('substring(html, 1, 2048)', w)} as c_{k}" for k, w in VOCAB.items())
    best = lambda f: "list_max([" + ", ".join(f"{f(k)} * 10 + {3 - i}" for i, k in enumerate(sorted(VOCAB))) + "])"
    lang = lambda x: f"(['fr', 'es', 'en', 'de'])[{x} % 10 + 1]"
    return f"""with h as (select page_id, {cols} from pages), b as (select page_id, {best(lambda k: f'n_{k}')} as n, {best(lambda k: f'c_{k}')} as c, {best(lambda k: f'(n_{k} * 3 + c_{k})')} as m from h)
select page_id as doc_id, cast(n // 10 as bigint) as name_hits, case when n // 10 >= 2 then {lang('n')} when n // 10 = 1 then {lang('m')} when c // 10 > 0 then {lang('c')} else 'bridge' end as slice,
case when n // 10 >= 2 then 'name' when n // 10 = 1 then 'name+content' when c // 10 > 0 then 'content' else 'default' end as tier from b"""


@q(_router_sql())
def slice_router(s, d):
    p = t(s, d, "pages").select(F.col("page_id").alias("doc_id"), F.col("url").alias("file_name"), F.col("html").alias("text"))
    return ontology.route_slices(p, VOCAB)


_MIX = "list_transform(list_zip(c.vec, e.v), lambda z: z[1] * {a} + z[2] * (1 - {a}))"


def _settings() -> dict[str, frozenset[str]]:
    every = sorted(ontology.REFINEMENTS)
    return {"none": frozenset(), "all": ontology.REFINEMENTS, **{f"{g} alone": frozenset({g}) for g in every}, **{f"without {g}": ontology.REFINEMENTS - {g} for g in every}}


def _refined_sql() -> str:
    cos = f"{DOT.format(a='q.vec', b='cls.vec')} / sqrt({DOT.format(a='q.vec', b='q.vec')} * {DOT.format(a='cls.vec', b='cls.vec')})"
    more = f"""dw as (select floor(e.vec_id / 4) as doc_id, {UNIT.format(v=_MIX.format(a="([0.5, 0.55, 0.6, 0.7])[cast(floor(e.vec_id / 100) as bigint) % 4 + 1]"))} as vec from e join cls c on c.class_id = e.vec_id % 100 where e.vec_id >= 100),
tw as (select floor(e.vec_id / 4) as doc_id, {UNIT.format(v=_MIX.format(a='0.65'))} as vec from e join cls c on c.class_id = e.vec_id * 7 % 100 where e.vec_id >= 100 and e.vec_id % 4 = 0),
hit as materialized (select src, cast(doc_id as bigint) as doc_id, class_id, max(cos) as score from (select q.src, q.doc_id, class_id, {cos} as cos from (select 'q' as src, doc_id, vec from qw union all select 'd', doc_id, vec from dw union all select 't', doc_id, vec from tw) q, cls) where cos >= 0.72 group by all),
term as (select distinct doc_id, 'p' || ((gold_class + 1) % 100) as pred_id from qw where win_no = 0), pred as (select 'p' || class_id as pred_id, class_id as domain, coalesce(parent, class_id) as range from cls), up as (select class_id as child, class_id as ancestor from cls union select class_id, parent from cls where parent is not null)"""
    rows = []
    for name, on in _settings().items():
        srcs = ("d" if "G4" in on else "q", *(["t"] if "G1" in on else []))
        found = "select distinct doc_id, class_id from b" + (" union select b.doc_id, c.class_id from b join cls c on c.parent = b.class_id where b.score >= 0.80" if "G2" in on else "")
        ends = "select distinct doc_id, pred_id from f join up on child = class_id join pred on ancestor in (domain, range)" if "G5" in on else "select distinct doc_id, pred_id from f join pred on class_id in (domain, range)"
        ends += " union select doc_id, pred_id from term" if "G3" in on else ""
        rows.append(f"select * from (with b as (select doc_id, class_id, max(score) as score from hit where src in {srcs if len(srcs) > 1 else f'({srcs[0]!r})'} group by all), f as ({found}), p as ({ends}) select '{name}' as setting, (select count(*) from f) as class_hits, (select count(*) from p) as predicates)")
    return f"with {V1}, {more} " + " union all ".join(rows)


@q(_refined_sql())
def refinement_ablation(s, d):
    """Class hits and predicates with no refinement, all five, each alone and each left out; denser windows and term strings are planted vectors, terms the number of a neighbouring class."""
    classes = written(views.ontology_classes(s, d), "classes")
    windows = written(views.query_windows(s, d, classes), "windows")
    dense = written(views.query_windows(s, d, classes, lean=(0.5, 0.55, 0.6, 0.7)), "windows")
    lines = written(views.query_windows(s, d, classes, lean=(0.65,) * 4, turn=7).where("vec_id % 4 = 0").withColumn("win_no", F.lit(100)), "windows")
    terms = windows.where("win_no = 0").select("doc_id", ((F.col("gold_class") + 1) % 100).cast("string").alias("term"))
    sub = views.subclass_edges(classes)
    preds = classes.select(F.concat(F.lit("p"), F.col("class_id").cast("string")).alias("pred_id"), F.col("label"), F.col("definition"), F.col("class_id").alias("domain"), F.coalesce("parent", F.col("class_id")).alias("range"))
    reach, out = ontology.closure(sub), None
    for name, on in _settings().items():
        hits, found = ontology.retrieve(windows, classes, sub, preds, on, term_windows=lines, terms=terms, dense_windows=dense, reach=reach)
        row = hits.agg(F.count("*").alias("class_hits")).crossJoin(found.agg(F.count("*").alias("predicates"))).withColumn("setting", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


# conformance

V3 = """edge as (select l_orderkey % 200 as doc_id, l_suppkey as src, l_partkey as dst, case l_orderkey % 3 when 0 then 'Flag ' || l_returnflag || ' To ' || l_linestatus
  when 1 then upper(replace('Flag ' || l_returnflag || ' To ' || l_linestatus, ' ', '_')) else lower(replace('Flag ' || l_returnflag || ' To ' || l_linestatus, ' ', '-')) end as rel_type,
  case when l_partkey % 3 <> 0 then strftime(l_shipdate, '%Y-%m-%d') end as q_date, case when l_partkey % 5 <> 0 then cast(l_discount as varchar) end as q_discount,
  case when l_suppkey % 2 = 0 then cast(cast(l_quantity as integer) as varchar) end as q_quantity, l_orderkey * 1000000 + l_linenumber * 100000 + l_partkey as ord from lineitem),
canon as (select * replace (upper(regexp_replace(trim(rel_type), '[ -]+', '_', 'g')) as rel_type) from edge)"""


@q(f"with {V3}, b as (select doc_id, rel_type, count(*) as n from canon group by all) select doc_id, cast(sum(n) as bigint) as edges, count(*) as types, max(n) as top_type_edges, round(max(n) / sum(n), 6) as top_share from b group by doc_id")
def relation_concentration(s, d):
    e = views.edges(s, d)
    return gates.relation_concentration(e.withColumn("rel_type", clean.canon_rel_type(F.col("rel_type"))))


@q(f"""with {V3}, g as (select doc_id, rel_type, src % 4 as src, dst % 10 as dst from canon union all select 1000, 'GRID', i, j from range(0, 2) a(i), range(0, 58) b(j)), u as (select distinct * from g)
select doc_id, rel_type, count(*) as edges, count(distinct src) as n_src, count(distinct dst) as n_dst, round(count(*) / (count(distinct src) * count(distinct dst)), 6) as fill,
count(*) >= 20 and round(count(*) / (count(distinct src) * count(distinct dst)), 6) >= 0.9 and count(distinct src) > 1 and count(distinct dst) > 1 as grid from u group by doc_id, rel_type""")
def grid_detect(s, d):
    e = views.edges(s, d).select("doc_id", clean.canon_rel_type(F.col("rel_type")).alias("rel_type"), (F.col("src") % 4).alias("src"), (F.col("dst") % 10).alias("dst"))
    plant = s.range(2).select(F.col("id").alias("src")).crossJoin(s.range(58).select(F.col("id").alias("dst"))).select(F.lit(1000).cast("long").alias("doc_id"), F.lit("GRID").alias("rel_type"), "src", "dst")
    return gates.detect_grid(e.unionByName(plant))


_UNIT = "(['corps', 'division', 'brigade', 'battalion'])[{k} % 4 + 1]"


@q(f"""with e as (select l_orderkey, l_linenumber, l_suppkey as a, l_partkey as b, (['commands', 'has_subordinate', 'subordinate_to', 'supplies'])[l_orderkey % 4 + 1] as r from lineitem),
f as (select *, case when r in ('commands', 'has_subordinate') then b else a end as src, case when r in ('commands', 'has_subordinate') then a else b end as dst, case when r = 'supplies' then r else 'subordinate_to' end as rel_type from e)
select l_orderkey, l_linenumber, rel_type, case when rel_type = 'subordinate_to' and src % 4 < dst % 4 then dst else src end as src, case when rel_type = 'subordinate_to' and src % 4 < dst % 4 then src else dst end as dst from f""")
def orient_edges(s, d):
    li = t(s, d, "lineitem")
    label = F.element_at(F.array(*[F.lit(x) for x in ("commands", "has_subordinate", "subordinate_to", "supplies")]), (F.col("l_orderkey") % 4 + 1).cast("int"))
    rels = li.select(F.lit(0).alias("doc_id"), "l_orderkey", "l_linenumber", F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"), label.alias("rel_type"))
    unit = F.element_at(F.array(*[F.lit(x) for x in ("7 Corps", "2nd Division", "Iron Brigade", "3 battalion")]), (F.col("ent_id") % 4 + 1).cast("int"))
    ids = t(s, d, "part").select(F.col("p_partkey").alias("ent_id")).union(t(s, d, "supplier").select("s_suppkey")).distinct()
    ents = ids.select(F.lit(0).alias("doc_id"), "ent_id", F.lit("ORGANIZATION").alias("type"), unit.alias("name"))
    return conform.orient_by_rank(conform.fold_inverse(rels), ents).select("l_orderkey", "l_linenumber", "rel_type", "src", "dst")


@q(f"""with {V3}, snap as (select rel_type, lower(regexp_replace(trim(rel_type), '[ -]+', '_', 'g')) as k from edge) select rel_type, case when k in ('flag_a_to_f', 'flag_r_to_f') then k else rel_type end as canon,
case when k in ('flag_a_to_f', 'flag_r_to_f') then 'exact' else 'novel' end as tier, count(*) as n from snap group by all""")
def snap_predicates(s, d):
    vocab = s.createDataFrame([("flag_a_to_f",), ("flag_r_to_f",)], "label string")
    return conform.snap_predicates(views.edges(s, d), vocab).groupBy("rel_type", "canon", "tier").agg(F.count("*").alias("n"))


@q("select event_type, event_type not in ('click', 'purchase') as novel, count(*) as n from events group by all")
def novel_types(s, d):
    vocab = s.createDataFrame([("Clicks",), ("purchase",)], "label string")
    return conform.flag_novel(t(s, d, "events"), vocab, "event_type").groupBy("event_type", "novel").agg(F.count("*").alias("n"))


@q("""with ent as (select distinct o_custkey % 300 as doc_id, o_custkey as ent_id, case when c_mktsegment = 'BUILDING' then 'FINANCIAL' when c_mktsegment in ('AUTOMOBILE', 'MACHINERY') then 'PERSON' else 'ORGANIZATION' end as type from orders join customer on o_custkey = c_custkey),
rel as (select o_custkey % 300 as doc_id, o_custkey as src, (o_custkey + 300 * (o_orderkey % 3)) as dst, (['REPORTED_TO', 'FUNDS', 'MEMBER_OF'])[case when o_custkey % 3 = 0 then o_orderkey % 3 + 1 else 1 end] as rel_type from orders),
doc as (select doc_id, count(*) filter (type = 'FINANCIAL') as n_fin, count(*) filter (type <> 'FINANCIAL') as n_other, count(*) filter (type = 'PERSON') as n_person from ent group by doc_id),
typed as (select r.doc_id, rel_type, coalesce((a.type = 'FINANCIAL') <> (b.type = 'FINANCIAL'), false) as across, coalesce(a.type = 'PERSON', false) or coalesce(b.type = 'PERSON', false) as person from rel r
  left join ent a on a.doc_id = r.doc_id and a.ent_id = r.src left join ent b on b.doc_id = r.doc_id and b.ent_id = r.dst),
bt as (select doc_id, rel_type, count(*) as n, count(*) filter (across) as n_across, count(*) filter (person and rel_type <> 'REPORTED_TO') as n_prel from typed group by all),
st as (select doc_id, sum(n) as n_rels, max(n) as top, count(*) as n_types, sum(n_across) as n_across, sum(n_prel) as n_prel, count(*) filter (regexp_matches(rel_type, '(?i)(fund|budget|approv)')) as n_labels from bt group by doc_id),
f as (select d.doc_id, cast(coalesce(n_rels, 0) as bigint) as n_rels, concat_ws(',', case when n_fin > 0 and n_other > 0 and coalesce(n_across, 0) = 0 then 'financial_links' end, case when n_fin > 0 and coalesce(n_labels, 0) = 0 then 'financial_labels' end,
  case when n_person >= 8 and coalesce(n_prel, 0) < 4 then 'person_diversity' end, case when n_rels > 0 and top > 0.3 * n_rels and n_types < 6 then 'concentration' end) as reasons from doc d left join st using (doc_id))
select doc_id, n_rels, reasons, reasons <> '' as force, reasons <> '' or n_rels < 50 as second_pass from f""")
def quality_gate(s, d):
    o, c = t(s, d, "orders"), t(s, d, "customer")
    seg = F.col("c_mktsegment")
    kind = F.when(seg == "BUILDING", "FINANCIAL").when(seg.isin("AUTOMOBILE", "MACHINERY"), "PERSON").otherwise("ORGANIZATION")
    ents = o.join(c, F.col("o_custkey") == F.col("c_custkey")).select((F.col("o_custkey") % 300).alias("doc_id"), F.col("o_custkey").alias("ent_id"), kind.alias("type")).distinct()
    which = F.when(F.col("o_custkey") % 3 == 0, F.col("o_orderkey") % 3 + 1).otherwise(1).cast("int")
    rels = o.select((F.col("o_custkey") % 300).alias("doc_id"), F.col("o_custkey").alias("src"), (F.col("o_custkey") + 300 * (F.col("o_orderkey") % 3)).alias("dst"), F.element_at(F.array(F.lit("REPORTED_TO"), F.lit("FUNDS"), F.lit("MEMBER_OF")), which).alias("rel_type"))
    return gates.quality_gate(ents, rels).withColumn("reasons", F.array_join("reasons", ","))


# cleaning

_ID = "(['per_', 'P-', 'e', 'id:', 'n', 'x_', '#'])[{k} % 7 + 1] || {k}"
V6 = f"""ent as (select p_partkey % 50 as doc_id, {_ID.format(k='p_partkey')} as ent_id, case when p_partkey % 5 = 0 then (['Dr.', 'Captain', 'Agent'])[p_partkey % 3 + 1] || ' ' || p_name else p_name end || case when p_partkey % 7 = 0 then ' company' else '' end as name, p_partkey as k from part),
rel as (select p_partkey % 50 as doc_id, {_ID.format(k='p_partkey')} as src, case when p_partkey % 9 = 0 then {_ID.format(k='p_partkey')} when p_partkey % 50 = 1 then 'gone_' || p_partkey else {_ID.format(k='(p_partkey + 50)')} end as dst,
 (['reported to', 'Reported-To', 'REPORTED_TO', 'surveiled'])[p_partkey % 4 + 1] as rel_type, p_partkey as ord from part where p_partkey + 50 <= (select max(p_partkey) from part)),
typed as (select *, case when k % 7 = 0 then 'ORGANIZATION' else 'PERSON' end as type from ent),
core as (select *, case when k % 5 = 0 then case when k % 7 = 0 then p2 else p1 end else case when k % 7 = 0 then p3 else name end end as cname from (select *, array_to_string(list_slice(string_split(name, ' '), 2, 3), ' ') as p1,
 array_to_string(list_slice(string_split(name, ' '), -2, -1), ' ') as p2, array_to_string(list_slice(string_split(name, ' '), -2, -1), ' ') as p3 from typed))"""


@q("select l_returnflag as flag, upper(regexp_replace(trim(rel), '[ -]+', '_', 'g')) as rel_type, count(*) as n from (select l_returnflag, case l_orderkey % 2 when 0 then ' moved  to-' || l_linestatus else 'Moved To ' || l_linestatus end as rel from lineitem) group by all")
def rel_type_normalize(s, d):
    rel = F.when(F.col("l_orderkey") % 2 == 0, F.concat(F.lit(" moved  to-"), "l_linestatus")).otherwise(F.concat(F.lit("Moved To "), "l_linestatus"))
    return t(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("flag"), clean.canon_rel_type(rel).alias("rel_type")).agg(F.count("*").alias("n"))


@q(f"with {V6} select doc_id, src, dst, ord from rel where src <> dst")
def self_loops(s, d):
    return clean.drop_self_loops(views.dirty_relations(s, d)).select("doc_id", "src", "dst", "ord")


@q(f"with {V6} select doc_id, ent_id, type, type <> 'PERSON' as retyped from typed")
def type_fix(s, d):
    return clean.fix_entity_type(views.dirty_entities(s, d)).select("doc_id", "ent_id", "type", "retyped")


@q(f"with {V6} select r.doc_id, src, dst, ord from rel r where exists (select 1 from ent e where e.doc_id = r.doc_id and e.ent_id = r.src) and exists (select 1 from ent e where e.doc_id = r.doc_id and e.ent_id = r.dst)")
def dangling(s, d):
    return clean.drop_dangling(views.dirty_relations(s, d), views.dirty_entities(s, d)).select("doc_id", "src", "dst", "ord")


@q(f"with {V6} select doc_id, ent_id as old_id, (case type when 'PERSON' then 'p_' else 'o_' end) || lpad(cast(dense_rank() over (partition by doc_id, type order by ent_id) as varchar), 3, '0') as new_id from typed")
def renumber_ids(s, d):
    return clean.renumber(clean.fix_entity_type(views.dirty_entities(s, d)))[1].select("doc_id", F.col("ent_id").alias("old_id"), F.col("merged_id").alias("new_id"))


@q(f"with {V6} select doc_id, type, lower(cname) as name, min(ent_id) as ent_id, count(*) as mentions from core group by doc_id, type, lower(cname)")
def title_merge(s, d):
    merged, _ = clean.merge_entities(clean.fix_entity_type(views.dirty_entities(s, d)).drop("retyped"))
    return merged.select("doc_id", "type", F.lower("name").alias("name"), "ent_id", "mentions")


@q(f"with {V6} select count(distinct (doc_id, type, lower(name))) as verbatim, count(distinct (doc_id, type, lower(cname))) as core from core")
def title_merge_vs_verbatim(s, d):
    e = clean.fix_entity_type(views.dirty_entities(s, d)).drop("retyped")
    return clean.merge_entities(e, "verbatim")[0].agg(F.count("*").alias("verbatim")).crossJoin(clean.merge_entities(e)[0].agg(F.count("*").alias("core")))


@q(f"""with {V6}, raw as (select 'before' as stage, (select count(*) from ent) as entities, (select count(*) from ent) as persons, count(*) as relations, count(*) filter (src = dst) as self_loops, count(distinct rel_type) as type_variants,
 (select count(distinct regexp_replace(ent_id, '[0-9]+', '9', 'g')) from ent) as id_shapes from rel)
select stage, entities, persons, relations, self_loops, type_variants, id_shapes, (select count(*) from (select doc_id, src as i from rel union all select doc_id, dst from rel where dst <> src) x where not exists (select 1 from ent e where e.doc_id = x.doc_id and e.ent_id = x.i)) as dangling_ends from raw""")
def quality_before(s, d):
    return clean.quality_table(views.dirty_entities(s, d), views.dirty_relations(s, d)).withColumn("stage", F.lit("before"))


def _quality_sql(name: str, fixes: tuple[str, ...]) -> str:
    """Defect counts of the planted files after the given fixes."""
    kind = "case when k % 7 = 0 then 'ORGANIZATION' else 'PERSON' end" if "types" in fixes else "'PERSON'"
    label = "replace(upper(regexp_replace(trim(rel_type), '[ -]+', '_', 'g')), 'SURVEILED', 'SURVEILLED')" if "labels" in fixes else "rel_type"
    loop = "src <> dst" if "loops" in fixes else "true"
    merged = "min(ent_id) over (partition by doc_id, type, lower(cname))" if "titles" in fixes else "ent_id"
    new = "(case type when 'PERSON' then 'p_' else 'o_' end) || lpad(cast(dense_rank() over (partition by doc_id, type order by mid) as varchar), 3, '0')" if "ids" in fixes else "mid"
    lost = "exists (select 1 from ids i where i.doc_id = r.doc_id and i.fid = r.src) and exists (select 1 from ids i where i.doc_id = r.doc_id and i.fid = r.dst)" if "dangling" in fixes else "true"
    return f"""(with a as (select doc_id, ent_id, {kind} as type, cname from core), b as (select *, {merged} as mid from a), c as (select *, {new} as fid from b),
ids as (select distinct doc_id, fid, type from c), {'ents as (select * from ids)' if 'titles' in fixes else 'ents as (select doc_id, fid, type from c)'},
r0 as (select doc_id, src, dst, {label} as rel_type from rel where {loop}), r1 as (select r0.doc_id, coalesce(s.mid, src) as src, coalesce(t.mid, dst) as dst, rel_type, s.fid as sf, t.fid as tf from r0 left join c s on s.doc_id = r0.doc_id and s.ent_id = src left join c t on t.doc_id = r0.doc_id and t.ent_id = dst),
r2 as (select doc_id, coalesce(sf, src) as src, coalesce(tf, dst) as dst, rel_type from r1 where {loop}), r as (select * from r2 r where {lost}),
ends as (select doc_id, src as i from r union all select doc_id, dst from r where dst <> src)
select '{name}' as stage, (select count(*) from ents) as entities, (select count(*) from ents where type = 'PERSON') as persons, (select count(*) from r) as relations, (select count(*) from r where src = dst) as self_loops,
 (select count(distinct rel_type) from r) as type_variants, (select count(distinct regexp_replace(fid, '[0-9]+', '9', 'g')) from ents) as id_shapes,
 (select count(*) from ends x where not exists (select 1 from ids where ids.doc_id = x.doc_id and ids.fid = x.i)) as dangling_ends)"""


_STAGES = {"before": (), "after": clean.FIXES, **{f"without {x}": tuple(y for y in clean.FIXES if y != x) for x in clean.FIXES}}


@q(f"with {V6} " + " union all ".join(f"select * from {_quality_sql(name, fixes)}" for name, fixes in _STAGES.items()))
def quality_before_after(s, d):
    """Defect counts before, after all fixes, and with each fix left out; the files are made once, what a chain reads twice is written, and chains share equal beginnings."""
    e, r = written(views.dirty_entities(s, d), "entities"), written(views.dirty_relations(s, d), "relations")
    out, known = None, {}
    for name, fixes in _STAGES.items():
        ents, rels = clean.finalize(e, r, fixes, cut=lambda df: written(df, "cleaned"), known=known)
        row = clean.quality_table(ents, rels).withColumn("stage", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


# relation deduplication

_Q = "coalesce('date=' || {p}date || ';', '') || coalesce('discount=' || {p}discount || ';', '') || coalesce('quantity=' || {p}quantity || ';', '')"


@q(f"with {V3} select doc_id, src, dst, rel_type, {_Q.format(p='a_')} as quals, n_merged from (select doc_id, src, dst, rel_type, arg_min(q_date, ord) filter (q_date is not null) as a_date, arg_min(q_discount, ord) filter (q_discount is not null) as a_discount, arg_min(q_quantity, ord) filter (q_quantity is not null) as a_quantity, count(*) as n_merged from canon group by all)")
def relation_dedup_union(s, d):
    e = views.edges(s, d).withColumn("rel_type", clean.canon_rel_type(F.col("rel_type")))
    return relations.dedup_relations(e).select(*relations.KEY, relations.show_quals(F.col("quals")).alias("quals"), "n_merged")


@q(f"with {V3} select doc_id, src, dst, rel_type, arg_min({_Q.format(p='q_')}, ord) as quals, count(*) as n_merged from canon group by doc_id, src, dst, rel_type")
def relation_dedup_first(s, d):
    e = views.edges(s, d).withColumn("rel_type", clean.canon_rel_type(F.col("rel_type")))
    return relations.dedup_relations(e, "first").select(*relations.KEY, relations.show_quals(F.col("quals")).alias("quals"), "n_merged")


@q(None)
def relation_dedup_fold(s, d):
    e = views.edges(s, d).withColumn("rel_type", clean.canon_rel_type(F.col("rel_type")))
    return relations.dedup_relations(e, "fold").select(*relations.KEY, relations.show_quals(F.col("quals")).alias("quals"), "n_merged")


# names

_T = "string_split(p_name, ' ')"
ALIASES = f"[p_name, upper({_T}[1][1]) || '. ' || {_T}[2], {_T}[1] || ' ' || upper({_T}[2][1]) || '.', upper({_T}[1][1]) || upper({_T}[2][1]), upper({_T}[1][1]) || '.' || upper({_T}[2][1]) || '.']"


@q(f"select p_partkey as ent_id, array_to_string({ALIASES}, ';') as aliases from part")
def alias_expand(s, d):
    return names.expand_aliases(views.homonyms(s, d)).select("ent_id", F.array_join("aliases", ";").alias("aliases"))


def _forms():
    tk = F.split("name", " ")
    a, b = tk[0], tk[1]
    pairs = {"full": F.col("name"), "initial": F.concat(F.substring(a, 1, 1), F.lit(". "), b), "initials": F.concat(F.substring(a, 1, 1), F.substring(b, 1, 1)), "misspelt": F.concat(a, F.substring(a, -1, 1), F.lit(" "), b), "titled": F.concat(F.lit("captain "), F.col("name"))}
    return F.array(*[F.struct(F.lit(k).alias("form"), v.alias("query")) for k, v in pairs.items()])


@q(f"""with qs as (select p_partkey, f.k as form, lower(f.v) as q from (select p_partkey, unnest([{{'k': 'full', 'v': p_name}}, {{'k': 'initial', 'v': {_T}[1][1] || '. ' || {_T}[2]}}, {{'k': 'initials', 'v': {_T}[1][1] || {_T}[2][1]}}, {{'k': 'misspelt', 'v': {_T}[1] || {_T}[1][-1] || ' ' || {_T}[2]}}, {{'k': 'titled', 'v': 'captain ' || p_name}}]) as f from part)),
al as (select p_partkey, lower(unnest({ALIASES})) as a, lower(p_name) as n from part)
select form, count(*) as queries, count(*) filter (exists (select 1 from al where al.p_partkey = qs.p_partkey and al.n = q)) as hits_name, count(*) filter (exists (select 1 from al where al.p_partkey = qs.p_partkey and al.a = q)) as hits_alias from qs group by form""")
def alias_search_recall(s, d):
    ents = views.homonyms(s, d)
    qs = ents.select("ent_id", F.inline(_forms()))

    # a query counts when its own entity answers; names are shared, so the entity is part of the key
    form = names.S.norm_name(F.col("alias"))
    known = names.expand_aliases(ents).select("ent_id", "name", F.explode("aliases").alias("alias")).groupBy("ent_id", form.alias("q")).agg(F.max(form == names.S.norm_name(F.col("name"))).alias("bare"))
    # aliases are several times the table and look small in its statistics: never a broadcast
    found = qs.withColumn("q", names.S.norm_name(F.col("query"))).join(known.hint("merge"), ["ent_id", "q"], "left")
    return found.groupBy("form").agg(F.count("*").alias("queries"), F.count_if("bare").alias("hits_name"), F.count("bare").alias("hits_alias"))


@q(None)
def variant_mining(s, d):
    docs, ents = views.planted_text(s, d)
    return names.mine_variants(ents, docs)


@q(None)
def variant_discovery(s, d):
    """How many planted initialled and misspelt names the miner finds, and how many it should by the ratio's formula."""
    docs, ents = views.planted_text(s, d)
    mined = names.mine_variants(ents, docs)
    n = docs.agg(F.count("*").alias("documents"))
    got = mined.groupBy().agg(F.count_distinct(F.when(F.col("rule") == "initial", F.col("doc_id"))).alias("initial_found"), F.count_distinct(F.when(F.col("rule") == "spelling", F.col("doc_id"))).alias("spelling_found"))
    return n.crossJoin(got)


def _name_pairs(s, d):
    p = t(s, d, "part").select("p_name").distinct()
    return p.select(F.col("p_name").alias("name_a")).join(p.select(F.col("p_name").alias("name_b")), F.col("name_a") < F.col("name_b"))


NAMES = "n as (select distinct p_name from part), pr as (select a.p_name as name_a, b.p_name as name_b from n a join n b on a.p_name < b.p_name)"


@q(f"""with {NAMES} select name_a, name_b, round(jaro_winkler_similarity(name_a, name_b), 6) as jaro_winkler,
 round(len(list_intersect(string_split(name_a, ' '), string_split(name_b, ' '))) / len(list_distinct(list_concat(string_split(name_a, ' '), string_split(name_b, ' ')))), 6) as tokens from pr""")
def name_similarity_pairs(s, d):
    return names.name_similarity(_name_pairs(s, d)).select("name_a", "name_b", F.round("jaro_winkler", 6).alias("jaro_winkler"), F.round("tokens", 6).alias("tokens"))


@q(None)
def name_scores(s, d):
    """Composite with and without the boost, and tiered, for every pair of names."""
    p = _name_pairs(s, d)
    a = names.name_similarity(p).select("name_a", "name_b", F.round("score", 6).alias("composite"), "reason")
    b = names.name_similarity(p, boost=False).select("name_a", "name_b", F.round("score", 6).alias("no_boost"))
    c = names.name_similarity(p, "tiered").select("name_a", "name_b", F.round("score", 6).alias("tiered"))
    return a.join(b, ["name_a", "name_b"]).join(c, ["name_a", "name_b"])


@q(f"with {NAMES} select count(*) as pairs, count(*) filter (string_split(name_a, ' ')[1][1] = string_split(name_b, ' ')[1][1] and string_split(name_a, ' ')[2][1] = string_split(name_b, ' ')[2][1]) as first_letter, 0::bigint as fixed from pr")
def first_letter_false_positives(s, d):
    p = _name_pairs(s, d)
    one = lambda mode: names.S.abbrev_signal(F.col("name_a"), F.col("name_b"), mode) == 1
    return p.agg(F.count("*").alias("pairs"), F.count_if(one("first_letter")).alias("first_letter"), F.count_if(one("fixed")).alias("fixed"))


@q("""with e as (select p_partkey // 40 as doc_id, p_partkey as id, p_name, p_brand, p_type, cast(cast(floor(p_size / 10) as bigint) as varchar) as loc from part),
p as (select a.doc_id, a.id as left_id, b.id as right_id, jaro_winkler_similarity(a.p_name, b.p_name) as score, case when a.p_brand = b.p_brand and a.p_type = b.p_type and a.loc = b.loc then 1 else 0 end as delta from e a join e b on a.doc_id = b.doc_id and a.id < b.id)
select doc_id, left_id, right_id, delta, case when delta = 1 and score > 0.95 then 'auto_merge' when delta = 1 and score > 0.90 then 'manual_review' else 'different_contexts' end as action from p where score >= 0.75""")
def context_dedup(s, d):
    """The decision surface over all pairs of a document, scored by Jaro-Winkler alone so that SQL can follow."""
    p = names.candidate_pairs(views.homonyms(s, d), "all", keep=("name", "role", "org", "loc"))
    key = p.select("name_a", "name_b").distinct().withColumn("score", names.S.jaro_winkler(F.col("name_a"), F.col("name_b")))
    return names.decide_rule(names.context_agreement(p.join(key, ["name_a", "name_b"]))).select("doc_id", "left_id", "right_id", "delta", "action")


@q(None)
def phase_three(s, d):
    """Aliases, candidate pairs and decisions of the composed rule layer."""
    ents = views.homonyms(s, d)
    _, _, decided = names.enhance(ents)
    return decided.groupBy("action", "verdict", "confidence").agg(F.count("*").alias("n"))


# resolution

V8 = f"""e as (select vec_id, list_transform(embedding, lambda x: cast(x as double)) as v from embeddings),
cp as (select a.vec_id + 1000000 as vec_id, {UNIT.format(v='list_transform(list_zip(a.v, b.v), lambda z: 0.9 * z[1] + 0.1 * z[2])')} as v from e a join e b on b.vec_id = a.vec_id + 1 where a.vec_id % 10 = 0), al as (select * from e union all select * from cp)"""


@q(f"""with {V8}, c as (select a.vec_id as a, b.vec_id as b, {DOT.format(a='a.v', b='b.v')} / sqrt({DOT.format(a='a.v', b='a.v')} * {DOT.format(a='b.v', b='b.v')}) as cos from al a join al b on a.vec_id <> b.vec_id),
r as (select *, row_number() over (partition by a order by cos desc, b) as rn from c) select least(a, b) as left_id, greatest(a, b) as right_id, round(max(cos), 4) as cos from r where rn <= 20 group by 1, 2""")
def vector_topk(s, d):
    return resolve.block_vector(views.near_duplicate_vectors(s, d)).select("left_id", "right_id", F.round("cos", 4).alias("cos"))


@q(None)
def vector_lsh(s, d):
    return resolve.block_vector(views.near_duplicate_vectors(s, d), method="lsh").select("left_id", "right_id", F.round("cos", 4).alias("cos"))


@q(None)
def blocking_quality(s, d):
    """Pairs kept and compared by exact top-k, hashing and their union with phonetic blocks, against planted copies."""
    v = views.near_duplicate_vectors(s, d)
    gold = v.where("vec_id <> gold_id").select(F.col("gold_id").alias("left_id"), F.col("vec_id").alias("right_id"))
    n = v.count()
    exact, lsh = resolve.block_vector(v), resolve.block_vector(v, method="lsh")
    out = M.blocking_quality(exact, gold, n).withColumn("method", F.lit("exact"))
    return out.unionByName(M.blocking_quality(lsh, gold, n).withColumn("method", F.lit("lsh"))).unionByName(M.blocking_quality(resolve.block_union(exact=exact, lsh=lsh), gold, n).withColumn("method", F.lit("union")))


def _parts_as_entities(s, d):
    """Parts after the rule layer, one entity for each name and brand; brands with an odd last digit are a discriminator."""
    p = t(s, d, "part").groupBy("p_name", "p_brand").agg(F.min("p_partkey").alias("ent_id"), F.min("p_type").alias("org"))
    props = F.map_filter(F.create_map(F.lit("org"), F.col("org"), F.lit("employee_no"), F.when(F.col("p_brand").rlike("[13579]$"), F.col("p_brand"))), lambda k, v: v.isNotNull())
    e = p.select("ent_id", F.col("p_name").alias("name"), F.lit("PERSON").alias("type"), props.alias("props"), (F.col("ent_id") % 50).alias("doc_id"), F.lit(0).alias("chunk_no"))
    return resolve.embed_ngrams(resolve.render_entity(names.expand_aliases(e)), "rendered")


@q(None)
def phonetic_blocks(s, d):
    return resolve.block_phonetic(_parts_as_entities(s, d))


@q(None)
def resolution_decisions(s, d):
    """Embed, block, score and decide parts as entities, whose names are shared and whose brands may conflict."""
    e = _parts_as_entities(s, d)
    pairs = resolve.block_union(phonetic=resolve.block_phonetic(e), vector=resolve.block_vector(e.select(F.col("ent_id").alias("vec_id"), "vec")))
    decided = resolve.decide_resolution(resolve.score_pairs(pairs, e))
    return decided.groupBy("action", "conflict").agg(F.count("*").alias("n"), F.round(F.avg("score"), 4).alias("mean_score"))


@q(f"""with recursive {V8}, lk as (select a.vec_id as a, b.vec_id as b from al a join al b on b.vec_id = a.vec_id + 1000000), both_ as (select a, b from lk union all select b, a from lk), rc as (select a as node, a as root from both_ union select r.node, x.b from rc r join both_ x on x.a = r.root)
select node as ent_id, min(root) as canonical_id from rc group by node""")
def resolution_clusters(s, d):
    v = views.near_duplicate_vectors(s, d)
    pairs = resolve.block_vector(v).where("cos >= 0.95").withColumnRenamed("cos", "score")
    ents = v.select(F.col("vec_id").alias("ent_id"), F.create_map(F.lit("dob"), F.col("gold_id").cast("string")).alias("props"))
    return resolve.with_partner(resolve.clusters(pairs, ents))


# order, cache, breaker, failures, workers

@q("select event_id as seq, max(epoch_us(ts) + cast(round(value * 1000) as bigint)) over (order by event_id rows unbounded preceding) as release_us from events")
def ordered_release(s, d):
    from kgrefine.streaming.ordered import ordered_release as release

    e = t(s, d, "events").select(F.col("event_id").alias("seq"), (F.unix_micros(F.col("ts").cast("timestamp")) + F.round(F.col("value") * 1000).cast("long")).alias("done_ts"))
    return release(e).select("seq", F.col("release_ts").alias("release_us"))


@q("select event_id as req_id, row_number() over (partition by user_id % 20, event_type, floor(epoch_us(ts) / 600000000.0) order by ts, event_id) > 1 as hit from events")
def cache_hits(s, d):
    e = t(s, d, "events").select(F.col("event_id").alias("req_id"), "ts", F.concat_ws("/", (F.col("user_id") % 20).cast("string"), "event_type").alias("text"))
    return ontology.with_cache(e).select("req_id", "hit")


def _requests(s, d):
    return t(s, d, "events").select((F.col("user_id") % 8).alias("source"), F.col("event_id").alias("req_id"), "ts", (F.col("event_type") == "error").alias("failed"))


@q(None)
def breaker_state(s, d):
    return ontology.circuit_breaker(_requests(s, d), 3600)


@q("select user_id % 8 as source, event_id as req_id, case when coalesce(max(case when event_type = 'error' then 1 else 0 end) over (partition by user_id % 8 order by epoch_us(ts) range between 3599999999 preceding and 1 preceding), 0) = 1 then 'unguided' else 'guided' end as state from events")
def breaker_extending(s, d):
    return ontology.breaker_extending(_requests(s, d), 3600).select("source", "req_id", "state")


@q("select event_id, user_id from events where user_id in (select user_id from events where event_type = 'error' and value > 20)")
def failure_rerun(s, d):
    e = t(s, d, "events")
    return extract.rerun_from_failures(e, e.where("event_type = 'error' and value > 20"), ("user_id",)).select("event_id", "user_id")


@q(None)
def worker_simulation(s, d):
    """Mean makespan and wait of each hour's requests with 1, 4 and 10 workers; an hour is one small group."""
    import pandas as pd

    def hour(pdf):
        jobs = pdf.sort_values("event_id")["value"].tolist()
        return pd.DataFrame([{"jobs": len(jobs), **M.simulate_workers(jobs, k)} for k in (1, 4, 10)])

    e = t(s, d, "events").select("event_id", F.coalesce("value", F.lit(0.0)).alias("value"), F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("h"))
    rows = e.groupBy("h").applyInPandas(hour, "jobs long, workers int, makespan double, mean_wait double")
    return rows.groupBy("workers").agg(F.sum("jobs").alias("jobs"), F.round(F.avg("makespan"), 4).alias("makespan"), F.round(F.avg("mean_wait"), 4).alias("mean_wait"))


# tables

@q("""select o_orderkey, try_cast(day as date) as day, cast(o_totalprice as double) as price, day is not null and try_cast(day as date) is null as bad from (select o_orderkey, o_totalprice, case when o_orderkey % 97 = 0 then '2024-13-01' else strftime(o_orderdate, '%Y-%m-%d') end as day from orders where o_orderpriority <> '5-LOW')""")
def plan_execute_orders(s, d):
    day = F.when(F.col("o_orderkey") % 97 == 0, F.lit("2024-13-01")).otherwise(F.date_format("o_orderdate", "yyyy-MM-dd"))
    sheet = t(s, d, "orders").select("o_orderkey", day.alias("day"), F.col("o_totalprice").alias("price"), "o_orderpriority")
    plan = {**tabular.plan_table(tabular.inspect_table(sheet), entity_type="ORDER"), "drop_where": "o_orderpriority = '5-LOW'"}
    return tabular.execute_plan(sheet, plan).select("o_orderkey", "day", "price", F.col("day__bad").alias("bad"))


@q("select 'day' as \"column\", count(*) filter (o_orderkey % 97 = 0) as unparsed from orders")
def plan_warnings(s, d):
    day = F.when(F.col("o_orderkey") % 97 == 0, F.lit("2024-13-01")).otherwise(F.date_format("o_orderdate", "yyyy-MM-dd"))
    sheet = t(s, d, "orders").select("o_orderkey", day.alias("day"))
    plan = tabular.plan_table(tabular.inspect_table(sheet), entity_type="ORDER")
    return tabular.map_records(tabular.execute_plan(sheet, plan), plan, "o_orderkey")[2]


@q("""with e as (select o_custkey % 300 as doc_id, count(distinct o_custkey) as n_ents from orders group by 1), r as (select o_custkey % 300 as doc_id, count(*) as n_rels from orders where o_orderstatus = 'P' group by 1)
select e.doc_id, n_ents, coalesce(n_rels, 0) as n_rels, n_ents >= 3 and coalesce(n_rels, 0) < 0.5 * n_ents as warning from e left join r using (doc_id)""")
def coverage_warnings(s, d):
    o = t(s, d, "orders").withColumn("doc_id", F.col("o_custkey") % 300)
    return gates.coverage_warnings(o.select("doc_id", "o_custkey").distinct(), o.where("o_orderstatus = 'P'"), 0.5, 3)


# extraction, measures

@q("""with j as (select conv_id, turn, '{"entities":[{"name":"' || role || '","type":"ROLE"},{"name":"t' || turn || '","type":"TURN"}]}' as j from conversations)
select conv_id, turn, case conv_id % 3 when 0 then 'closed_fence' when 1 then 'open_fence' else 'raw' end as stage, case when conv_id % 3 = 1 then '{"entities":[{"name":"' || regexp_extract(j, 'name":"([a-z]+)"', 1) || '","type":"ROLE"}]}' else j end as json from j""")
def json_recovery(s, d):
    c = t(s, d, "conversations")
    j = F.concat(F.lit('{"entities":[{"name":"'), "role", F.lit('","type":"ROLE"},{"name":"t'), F.col("turn").cast("string"), F.lit('","type":"TURN"}]}'))
    cut = F.substring_index(j, ',"type":"TURN"', 1)  # an answer cut inside its second entity
    m = F.col("conv_id") % 3
    answer = F.when(m == 0, F.concat(F.lit("Answer: ```json\n"), j, F.lit("\n``` done"))).when(m == 1, F.concat(F.lit("```json\n"), F.regexp_replace(cut, r'"name":"t\d+"$', '"na'))).otherwise(F.concat(F.lit("here "), j))
    return extract.recover_json(c.select("conv_id", "turn", answer.alias("answer"))).select("conv_id", "turn", "stage", F.trim("json").alias("json"))


@q("""with g as (select doc_id, quality from labels), f as (select doc_id, case when n_chars > 300 then 1 else 0 end as quality from documents where doc_id % 3 <> 0), a as (select count(*) filter (f.doc_id is not null and g.doc_id is not null) as tp,
 count(*) filter (g.doc_id is null) as fp, count(*) filter (f.doc_id is null) as fn from f full join g on f.doc_id = g.doc_id and f.quality = g.quality) select tp, fp, fn, round(tp / (tp + fp), 6) as precision, round(tp / (tp + fn), 6) as recall, round(2 * tp / (2 * tp + fp + fn), 6) as f1 from a""")
def extraction_f1(s, d):
    found = t(s, d, "documents").where("doc_id % 3 <> 0").select("doc_id", F.when(F.col("n_chars") > 300, 1).otherwise(0).alias("quality"))
    return M.set_f1(found, t(s, d, "labels"), ["doc_id", "quality"])


@q("""with a as (select doc_id as id, unnest(string_split_regex(lower(text), '\\s+')) as token from documents), f as (select id, token, count(*) as n from a where token <> '' group by all),
b as (select doc_id - 1 as id, unnest(string_split_regex(lower(text), '\\s+')) as token from documents), g as (select id, token, count(*) as m from b where token <> '' group by all),
j as (select coalesce(f.id, g.id) as id, coalesce(n, 0) as n, coalesce(m, 0) as m from f full join g on f.id = g.id and f.token = g.token)
select id, cast(sum(least(n, m)) as bigint) as overlap, cast(sum(n) as bigint) as n_found, cast(sum(m) as bigint) as n_gold, round(2 * sum(least(n, m)) / (sum(n) + sum(m)), 6) as f1 from j group by id""")
def token_f1(s, d):
    docs = t(s, d, "documents")
    return M.token_f1(docs.select(F.col("doc_id").alias("id"), "text"), docs.select((F.col("doc_id") - 1).alias("id"), "text"))


@q("""with e as (select doc_id, split_part(text, ' ', 1) as name, lang as type from documents where doc_id % 4 <> 0 union all select doc_id, 'name ' || doc_id, 'xx' from documents where doc_id % 4 = 0)
select count(*) as n, round(100 * count(*) filter (type in ('en', 'fr')) / count(*), 4) as conform_pct, round(100 * count(*) filter (not contains((select lower(text) from documents d where d.doc_id = e.doc_id), lower(name))) / count(*), 4) as hallucination_pct,
round(100 * count(*) filter (type = (select lang from documents d where d.doc_id = e.doc_id) and doc_id % 4 <> 0) / count(*), 4) as mapping_pct from e""")
def conformance(s, d):
    docs = t(s, d, "documents")
    first = F.split_part("text", F.lit(" "), F.lit(1))
    e = docs.where("doc_id % 4 <> 0").select("doc_id", first.alias("name"), F.col("lang").alias("type")).unionByName(docs.where("doc_id % 4 = 0").select("doc_id", F.concat(F.lit("name "), F.col("doc_id").cast("string")).alias("name"), F.lit("xx").alias("type")))
    vocab = s.createDataFrame([("en",), ("fr",)], "label string")
    gold = docs.where("doc_id % 4 <> 0").select("doc_id", first.alias("name"), F.col("lang").alias("type"))
    return M.conformance(e, vocab, docs, gold)


_FILES = """with nm as (select p_partkey - 1 as n, p_name from part), pl as (select doc_id, text || chr(10) || 'seen: ' || p_name as text from documents join nm on n = doc_id % (select count(*) from part)),
fl as (select doc_id // 20 as file_id, string_agg(text, chr(10) order by doc_id) as text from pl group by 1), g as (select distinct p_name from part)"""


def _ablation_sql(pages_per_chunk: int) -> str:
    size = 1500 * pages_per_chunk
    return f"""(with c as (select file_id, i, substring(text, i * {size} + 1, {size}) as text from fl, range(0, 10000) r(i) where i * {size} < length(text)),
 h as (select c.file_id, p_name, row_number() over (partition by c.file_id, c.i order by p_name) as rn from c join g on contains(c.text, p_name))
 select {pages_per_chunk} as chunk_pages, (select count(*) from c) as calls, (select count(*) from (select distinct file_id, p_name from h where rn <= 1)) as found, (select count(*) from (select distinct file_id, p_name from h)) as present from h limit 1)"""


@q(f"{_FILES} select * from {_ablation_sql(5)} union all select * from {_ablation_sql(2)}")
def chunk_size_ablation(s, d):
    """Planted names found in files of twenty documents when a provider returns at most one for each chunk, with five and with two pages to a chunk."""
    nm = t(s, d, "part").select((F.col("p_partkey") - 1).alias("n"), "p_name")
    count = nm.agg(F.count("*").alias("count"))
    docs = t(s, d, "documents").select("doc_id", "text").crossJoin(F.broadcast(count)).withColumn("n", F.col("doc_id") % F.col("count")).join(nm, "n")
    line = F.struct("doc_id", F.concat("text", F.lit("\nseen: "), "p_name").alias("x"))
    # a file is twenty documents, so a group is bounded
    files = docs.groupBy(F.expr("doc_id div 20").alias("doc_id")).agg(F.array_join(F.transform(F.array_sort(F.collect_list(line)), lambda r: r["x"]), "\n").alias("text"))
    gold = F.broadcast(t(s, d, "part").select("p_name").distinct())  # 64 names at any scale
    out = None
    for pages_ in (5, 2):
        c = chunks.chunk_chars(files, 1500 * pages_, 0, annotate=False)
        hits = c.join(gold, F.contains(F.col("text"), F.col("p_name"))).withColumn("rn", F.row_number().over(Window.partitionBy("doc_id", "chunk_no").orderBy("p_name")))
        got = hits.agg(F.count_distinct(F.when(F.col("rn") <= 1, F.struct("doc_id", "p_name"))).alias("found"), F.count_distinct("doc_id", "p_name").alias("present"))
        row = c.agg(F.count("*").alias("calls")).crossJoin(got).select(F.lit(pages_).alias("chunk_pages"), "calls", "found", "present")
        out = row if out is None else out.unionByName(row)
    return out
