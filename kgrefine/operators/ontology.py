"""Ontology slice retrieval: slices and router, vector search, penalties, expansion, predicates, budget, rendering."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT
from kgrefine.plans.scratch import forget, written


def token_estimate(text: Column) -> Column:
    return F.floor(F.length(text) / 4).cast("long")


def catalog_none(docs: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The unguided baseline: an empty catalogue for every document."""
    return docs.select(F.col(id_col).alias("doc_id"), F.lit("").alias("catalogue"), F.lit(0).cast("long").alias("tokens"))


def prompt_policy(explicit_only: bool = True, no_grid: bool = True) -> list[str]:
    """Rules for an extraction prompt that keep one statement from becoming a grid of relations; the guard after extraction is ``gates.detect_grid``."""
    rules = []
    if explicit_only:
        rules.append("State a relation only if one sentence names both ends and the relation.")
    if no_grid:
        rules.append("Do not combine every member of one list with every member of another.")
    return rules


def build_slices(classes: DataFrame, predicates: DataFrame | None = None, domain_col: str = "domain") -> DataFrame:
    """(domain, slice, tokens): one pre-rendered catalogue for each domain, lines in label order."""
    line = F.concat_ws(" : ", "label", "definition")
    rows = classes.select(domain_col, "label", line.alias("line"))
    if predicates is not None:
        rows = rows.unionByName(predicates.select(domain_col, "label", line.alias("line")))
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("label", "line"))), lambda x: x["line"]), "\n")
    return rows.groupBy(F.col(domain_col).alias("domain")).agg(text.alias("slice")).withColumn("tokens", token_estimate(F.col("slice")))


def route_slices(docs: DataFrame, vocab: dict[str, tuple[str, ...]], default: str = "bridge", head: int = 2048, force: str | None = None) -> DataFrame:
    """(doc_id, name_hits, slice, tier) for (doc_id, file_name, text).

    Two or more words of one domain in the file name decide (``name``); a single one is weighed with
    the first ``head`` characters of the content (``name+content``); without any the content decides
    alone (``content``), else the default (``default``). Ties go to the domain first in name order.
    """
    def hits(text: Column, words: tuple[str, ...]) -> Column:
        t = F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^a-zà-ÿ]+")
        return F.size(F.filter(t, lambda w: w.isin(*words)))

    def best(score: dict[str, Column]) -> Column:
        return F.array_max(F.array(*[F.struct(s.alias("n"), F.lit(-i).alias("i"), F.lit(d).alias("d")) for i, (d, s) in enumerate(sorted(score.items()))]))

    name = {d: hits(F.col("file_name"), w) for d, w in vocab.items()}
    body = {d: hits(F.substring("text", 1, head), w) for d, w in vocab.items()}
    rows = docs.select("doc_id", best(name).alias("n"), best(body).alias("c"), best({d: name[d] * 3 + body[d] for d in vocab}).alias("b"))
    tier = F.when(F.col("n.n") >= 2, "name").when(F.col("n.n") == 1, "name+content").when(F.col("c.n") > 0, "content").otherwise("default")
    pick = F.when(F.col("n.n") >= 2, F.col("n.d")).when(F.col("n.n") == 1, F.col("b.d")).when(F.col("c.n") > 0, F.col("c.d")).otherwise(F.lit(default))
    if force:
        tier, pick = F.lit("forced"), F.lit(force)
    return rows.select("doc_id", F.col("n.n").cast("long").alias("name_hits"), pick.alias("slice"), tier.alias("tier"))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def retrieve_classes(windows: DataFrame, classes: DataFrame, floor: float = 0.0, method: str = "matrix", most_bytes: int = 256 << 20) -> DataFrame:
    """(doc_id, win_no, class_id, cos): classes at or over ``floor`` for each window's vector ``vec``.

    ``matrix`` broadcasts the class vectors as one packed matrix and multiplies Arrow batches with it, so
    only hits come back; classes over ``most_bytes`` are met part by part. ``join`` is the same in column
    expressions: the windows meet the classes in blocks, one key for each part of the classes.
    """
    size, dim = classes.agg(F.count("*"), F.max(F.size("vec"))).first()
    parts = max(1, -(-size * (dim or 0) * 8 // most_bytes))
    if method == "join":
        dealt = classes.select("class_id", F.col("vec").alias("cvec"), F.pmod(F.xxhash64("class_id"), F.lit(max(parts, 8))).alias("part"))
        every = windows.select("doc_id", "win_no", "vec", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(max(parts, 8) - 1).cast("long"))).alias("part"))
        return every.join(dealt, "part").select("doc_id", "win_no", "class_id", cosine(F.col("vec"), F.col("cvec")).alias("cos")).where(F.col("cos") >= floor)
    if parts > 1:
        out = None
        for part in range(parts):
            some = retrieve_classes(windows, classes.where(F.pmod(F.xxhash64("class_id"), F.lit(parts)) == part), floor, most_bytes=2 * most_bytes)
            out = some if out is None else out.unionByName(some)
        return out
    rows = classes.select("class_id", "vec").orderBy("class_id").collect()
    ids = np.array([r[0] for r in rows], dtype=np.int64)
    mat = np.array([r[1] for r in rows], dtype=np.float64)
    mat /= np.linalg.norm(mat, axis=1, keepdims=True)
    shared = windows.sparkSession.sparkContext.broadcast((ids, mat))

    def go(batches):
        ids, mat = shared.value
        for b in batches:
            if not b.num_rows:
                continue
            x = np.array(b.column(2).to_pylist(), dtype=np.float64)
            cos = (x / np.linalg.norm(x, axis=1, keepdims=True)) @ mat.T
            r, c = np.nonzero(cos >= floor)
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(r)), b.column(1).take(pa.array(r)), pa.array(ids[c]), pa.array(cos[r, c])], ["doc_id", "win_no", "class_id", "cos"])

    return windows.select(F.col("doc_id").cast("long"), F.col("win_no").cast("int"), "vec").mapInArrow(go, "doc_id long, win_no int, class_id long, cos double")


def pagerank(edges: DataFrame, damping: float = 0.85, rounds: int = 20, tol: float = 0.0) -> DataFrame:
    """(node, pr, pr_max): rank over (src, dst) edges, and scaled to a largest value of 1.

    Dangling mass is shared by all nodes. Each round is one join and one aggregate and is written every
    fifth time, so the plan stays short; ``tol`` stops early on the largest change.
    """
    nodes = written(edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct(), "pr")
    n = nodes.count()
    if not n:
        return nodes.select("node", F.lit(0.0).alias("pr"), F.lit(0.0).alias("pr_max"))
    out = edges.groupBy("src").agg(F.count("*").alias("deg"))
    links = written(edges.join(out, "src"), "pr")
    now = nodes.withColumn("pr", F.lit(1.0 / n))
    for r in range(1, rounds + 1):
        given = links.join(now.withColumnRenamed("node", "src"), "src").groupBy(F.col("dst").alias("node")).agg(F.sum(F.col("pr") / F.col("deg")).alias("in"))
        dangling = now.join(out.withColumnRenamed("src", "node"), "node", "left_anti").agg(F.coalesce(F.sum("pr"), F.lit(0.0)).alias("lost"))
        step = nodes.join(given, "node", "left").crossJoin(F.broadcast(dangling))
        step = step.select("node", ((1 - damping) / n + damping * (F.coalesce("in", F.lit(0.0)) + F.col("lost") / n)).alias("pr"))
        if r % 5 == 0 or tol:
            step = written(step, "pr")
            if tol and step.alias("a").join(now.alias("b"), "node").agg(F.max(F.abs(F.col("a.pr") - F.col("b.pr")))).first()[0] < tol:
                now = step
                break
        now = step
    return now.withColumn("pr_max", F.col("pr") / F.max("pr").over(Window.partitionBy()))


def penalize(hits: DataFrame, centrality: DataFrame, weight: float = DEFAULT.centrality_weight) -> DataFrame:
    """Adds ``score`` = cos * (1 - weight * pr); classes without a centrality count as 0. ``centrality`` has (class_id, pr)."""
    rows = hits.join(centrality.select("class_id", "pr"), "class_id", "left")
    return rows.withColumn("score", F.col("cos") * (1 - weight * F.coalesce("pr", F.lit(0.0)))).drop("pr")


def best_per_class(hits: DataFrame, score: str = "score") -> DataFrame:
    """(doc_id, class_id, score): the largest over windows and query vectors."""
    return hits.groupBy("doc_id", "class_id").agg(F.max(score).alias("score"))


def expand_children(hits: DataFrame, subclass: DataFrame, trigger: float = DEFAULT.expand_from, give: float = DEFAULT.expand_score) -> DataFrame:
    """(doc_id, class_id, score, provenance): direct children of classes at or over ``trigger`` join at ``give``; the larger score stays."""
    kids = hits.where(F.col("score") >= trigger).join(subclass.withColumnRenamed("parent", "class_id"), "class_id").select("doc_id", F.col("child").alias("class_id"), F.lit(give).alias("score"), F.lit("expanded").alias("provenance"))
    every = hits.select("doc_id", "class_id", "score", F.lit("retrieved").alias("provenance")).unionByName(kids)
    # "retrieved" sorts after "expanded": it wins wherever the class was found on its own
    return every.groupBy("doc_id", "class_id").agg(F.max("score").alias("score"), F.max("provenance").alias("provenance"))


def cutoff(hits: DataFrame, min_score: float = DEFAULT.class_floor, budget: int = DEFAULT.catalogue_tokens, share: float = 1.0, score: Column | None = None,
           id_col: str = "class_id") -> DataFrame:
    """Rows at or over the floor whose running tokens, in falling score, stay in share * budget; the prefix stops at the first that does not fit.

    Needs ``tokens``. Adds ``used``.
    """
    order = [F.desc("score") if score is None else score, F.col(id_col)]
    used = F.sum("tokens").over(Window.partitionBy("doc_id").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return hits.where(F.col("score") >= min_score).withColumn("used", used).where(F.col("used") <= F.floor(F.lit(share * budget)))


def cutoff_split(classes: DataFrame, predicates: DataFrame, budget: int = DEFAULT.catalogue_tokens, share: float = DEFAULT.class_share, rollover: bool = False,
                 min_score: float = DEFAULT.class_floor) -> tuple[DataFrame, DataFrame]:
    """(classes, predicates) kept in their shares of one budget; with ``rollover`` predicates may also use what a document's classes leave of theirs.

    Both need ``tokens`` and ``score``; predicates have pred_id.
    """
    kept = cutoff(classes, min_score, budget, share)
    own = int(budget * (1 - share) + 1e-9)
    spent = kept.groupBy(F.col("doc_id").alias("of_doc")).agg(F.max("used").alias("spent"))
    left = F.floor(F.lit(share * budget)) - F.coalesce("spent", F.lit(0)) if rollover else F.lit(0)
    held = cutoff(predicates, min_score, budget, 1.0, id_col="pred_id").join(spent, F.col("doc_id") == F.col("of_doc"), "left")
    return kept, held.where(F.col("used") <= own + left).drop("of_doc", "spent")


def cutoff_topk(hits: DataFrame, k: int) -> DataFrame:
    """The fixed top-k alternative."""
    w = Window.partitionBy("doc_id").orderBy(F.desc("score"), "class_id")
    return hits.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def closure(subclass: DataFrame, max_depth: int = 10_000) -> DataFrame:
    """(child, ancestor, hop): every class with itself at 0 and its ancestors; the smallest hop, safe on cycles.

    Hops are added until one finds nothing new; a chain over ``max_depth`` is an error, never a shorter answer.
    """
    edges = subclass.select("child", "parent").distinct()
    reach = edges.select(F.explode(F.array("child", "parent")).alias("child")).distinct().select("child", F.col("child").alias("ancestor"), F.lit(0).alias("hop"))
    reach = written(reach, "closure")
    last = reach
    for hop in range(1, max_depth + 1):
        step = last.join(edges.select(F.col("child").alias("ancestor"), F.col("parent").alias("up")), "ancestor").select("child", F.col("up").alias("ancestor"), F.lit(hop).alias("hop")).distinct()
        step = written(step.join(reach, ["child", "ancestor"], "left_anti"), "closure")
        if not step.limit(1).count():
            forget(step)
            return reach
        reach, last = reach.unionByName(step), step
        if hop % 20 == 0:
            reach = written(reach, "closure")
    raise RuntimeError(f"a class has ancestors over {max_depth} steps away")


def predicates_exact(hits: DataFrame, predicates: DataFrame) -> DataFrame:
    """(doc_id, pred_id, hop = 0): predicates whose domain or range is a retrieved class."""
    ends = predicates.select("pred_id", F.explode(F.array_distinct(F.array("domain", "range"))).alias("class_id"))
    return hits.select("doc_id", "class_id").join(ends, "class_id").select("doc_id", "pred_id").distinct().withColumn("hop", F.lit(0))


def predicates_ancestor(hits: DataFrame, reach: DataFrame, predicates: DataFrame) -> DataFrame:
    """(doc_id, pred_id, hop): predicates anchored at a retrieved class or any ancestor, with the smallest distance."""
    ends = predicates.select("pred_id", F.explode(F.array_distinct(F.array("domain", "range"))).alias("ancestor"))
    up = hits.select("doc_id", F.col("class_id").alias("child")).join(reach, "child")
    return up.join(ends, "ancestor").groupBy("doc_id", "pred_id").agg(F.min("hop").alias("hop"))


def predicate_fulltext(terms: DataFrame, predicates: DataFrame | None, k1: float = 1.2, b: float = 0.75) -> DataFrame | None:
    """(doc_id, pred_id, bm25) of key terms (doc_id, term) over predicate labels and definitions; None without an index."""
    if predicates is None:
        return None
    words = predicates.select("pred_id", F.explode(F.split(F.lower(F.concat_ws(" ", "label", "definition")), "[^a-z0-9]+")).alias("term")).where("term <> ''")
    tf = words.groupBy("pred_id", "term").agg(F.count("*").alias("tf"))
    size = words.groupBy("pred_id").agg(F.count("*").alias("len"))
    stats = size.agg(F.count("*").alias("n"), F.avg("len").alias("mean"))
    df = tf.groupBy("term").agg(F.count("*").alias("df"))
    idx = tf.join(df, "term").join(size, "pred_id").crossJoin(F.broadcast(stats))
    idf = F.log1p((F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    weight = idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.col("mean")))
    return terms.select("doc_id", F.lower("term").alias("term")).distinct().join(idx.select("pred_id", "term", weight.alias("w")), "term").groupBy("doc_id", "pred_id").agg(F.sum("w").alias("bm25"))


def extract_terms(text: Column, lexicon: tuple[str, ...] = ()) -> Column:
    """Proper-noun phrases, abbreviations and lexicon words of a window, joined by pipes."""
    nouns = F.regexp_extract_all(text, F.lit(r"[A-Z][a-zà-ÿ]+(?: [A-Z][a-zà-ÿ]+)+"), F.lit(0))
    short = F.regexp_extract_all(text, F.lit(r"[A-Z]{2,}"), F.lit(0))
    words = F.filter(F.array(*[F.when(F.lower(text).contains(w), F.lit(w)) for w in lexicon]), lambda w: w.isNotNull()) if lexicon else F.array().cast("array<string>")
    return F.array_join(F.array_distinct(F.concat(nouns, short, words)), "|")


def render_catalog(hits: DataFrame) -> DataFrame:
    """(doc_id, catalogue, tokens): one line for each kept (label, definition), best first."""
    line = F.struct((-F.col("score")).alias("s"), F.col("class_id"), F.concat_ws(" : ", "label", "definition").alias("line"))
    text = F.array_join(F.transform(F.array_sort(F.collect_list(line)), lambda x: x["line"]), "\n")
    return hits.groupBy("doc_id").agg(text.alias("catalogue")).withColumn("tokens", token_estimate(F.col("catalogue")))


REFINEMENTS = frozenset({"G1", "G2", "G3", "G4", "G5"})


def retrieve(windows: DataFrame, classes: DataFrame, subclass: DataFrame, predicates: DataFrame, refinements: frozenset[str] = REFINEMENTS, centrality: DataFrame | None = None,
             term_windows: DataFrame | None = None, terms: DataFrame | None = None, dense_windows: DataFrame | None = None, min_score: float = DEFAULT.class_floor,
             reach: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """(class hits, predicates) of each document; switching a refinement off, or leaving out what it needs, never fails.

    G1 adds the vectors of term strings, G2 direct children, G3 full-text predicates, G4 the denser
    windows, G5 predicates of ancestors (``reach``: their closure, if it is there already).
    """
    src = dense_windows if "G4" in refinements and dense_windows is not None else windows
    if "G1" in refinements and term_windows is not None:
        src = src.select("doc_id", "win_no", "vec").unionByName(term_windows.select("doc_id", "win_no", "vec"))
    hits = retrieve_classes(src, classes, min_score)
    hits = penalize(hits, centrality) if centrality is not None else hits.withColumn("score", F.col("cos"))
    hits = best_per_class(hits).where(F.col("score") >= min_score)
    found = expand_children(hits, subclass) if "G2" in refinements else hits.withColumn("provenance", F.lit("retrieved"))
    preds = predicates_ancestor(found, closure(subclass) if reach is None else reach, predicates) if "G5" in refinements else predicates_exact(found, predicates)
    if "G3" in refinements and terms is not None:
        more = predicate_fulltext(terms, predicates).select("doc_id", "pred_id", F.lit(0).alias("hop"))
        preds = preds.unionByName(more).groupBy("doc_id", "pred_id").agg(F.min("hop").alias("hop"))
    return found, preds


def version_hash(onto: DataFrame) -> Column:
    """An aggregate that does not depend on the order of rows: the ontology's version."""
    return F.sha2(F.concat_ws("|", F.count("*").cast("string"), F.sum(F.xxhash64(*[F.col(c).cast("string") for c in onto.columns]).cast("decimal(38,0)")).cast("string")), 256)


def with_cache(requests: DataFrame, minutes: int = DEFAULT.cache_minutes, version: Column | None = None) -> DataFrame:
    """Adds ``version_no``, ``cache_key`` and ``hit`` to (ts, text, ...): a hit is an earlier request of the key in the same time window, under the same ``version`` of the ontology (``version_hash``)."""
    slot = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / (minutes * 60_000_000)).cast("long")
    key = F.concat_ws("|", F.col("text"), F.col("version_no").cast("string"), *([version] if version is not None else []))
    rows = requests.withColumn("version_no", slot).withColumn("cache_key", F.sha2(key, 256))
    order = Window.partitionBy("cache_key").orderBy("ts", "req_id")
    return rows.withColumn("hit", F.row_number().over(order) > 1)


def with_store(requests: DataFrame, store: DataFrame | None) -> DataFrame:
    """Adds ``stored``, the catalogue kept for a request's ``cache_key`` (from ``with_cache``), null on a miss; ``store`` has (cache_key, catalogue)."""
    if store is None:
        return requests.withColumn("stored", F.lit(None).cast("string"))
    kept = store.groupBy("cache_key").agg(F.min("catalogue").alias("stored"))
    return requests.join(kept, "cache_key", "left")


def circuit_breaker(requests: DataFrame, seconds: int = DEFAULT.breaker_seconds) -> DataFrame:
    """(source, req_id, us, failed, state) for (source, req_id, ts, failed): a failure opens the breaker for ``seconds``; failures while open do not extend it.

    Which failures open it depends on the one before, so each source's failures alone are walked in
    order, as (time, id) arrays. A request looks back at most ``seconds``: openings go to their own and
    the next stretch of that length, so requests meet them in stretches and a source that holds most of
    the requests is many tasks.
    """
    span = seconds * 1_000_000

    def openings(pdf):
        pdf = pdf.sort_values(["us", "req_id"], kind="stable")
        keep, until = [], None
        for us in pdf["us"].tolist():
            keep.append(until is None or us >= until)
            until = us + span if keep[-1] else until
        return pdf[keep]

    us = F.unix_micros(F.col("ts").cast("timestamp"))
    rows = requests.select("source", "req_id", us.alias("us"), "failed").withColumn("stretch", F.expr(f"us div {span}L"))
    kinds = dict(rows.dtypes)
    opened = rows.where("failed").select("source", "req_id", "us").groupBy("source").applyInPandas(openings, f"source {kinds['source']}, req_id {kinds['req_id']}, us long")
    opened = opened.withColumn("stretch", F.explode(F.array(F.expr(f"us div {span}L"), F.expr(f"us div {span}L + 1"))))
    opened = opened.select(F.col("source").alias("o_source"), F.col("stretch").alias("o_stretch"), F.col("us").alias("o_us"), F.col("req_id").alias("o_id"))
    after = (F.col("us") > F.col("o_us")) | ((F.col("us") == F.col("o_us")) & (F.col("req_id") > F.col("o_id")))
    # openings of a source are at least ``seconds`` apart, so a request meets two at most
    met = rows.join(opened, (F.col("source") == F.col("o_source")) & (F.col("stretch") == F.col("o_stretch")) & after & (F.col("us") < F.col("o_us") + span), "left")
    return met.select("source", "req_id", "us", "failed", F.when(F.col("o_us").isNull(), "guided").otherwise("unguided").alias("state"))


def breaker_extending(requests: DataFrame, seconds: int = DEFAULT.breaker_seconds) -> DataFrame:
    """The variant in which every failure reopens, as one range window: unguided within ``seconds`` after a failure."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("source").orderBy("us").rangeBetween(-seconds * 1_000_000 + 1, -1)
    rows = requests.select("source", "req_id", us.alias("us"), "failed")
    return rows.withColumn("state", F.when(F.coalesce(F.max(F.col("failed").cast("int")).over(w), F.lit(0)) == 1, "unguided").otherwise("guided"))
