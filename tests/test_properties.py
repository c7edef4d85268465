"""Invariants and brute-force comparisons."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from kgrefine import measures as M
from kgrefine.config import Settings
from kgrefine.functions import strings as S
from kgrefine.operators import clean, conform, extract, names, ontology, pages, relations, resolve
from kgrefine.plans.components import connected_components
from kgrefine.sources import records, views

words = st.text(alphabet="abcdeo .", max_size=12)


@given(words, words)
@settings(max_examples=200, deadline=None)
def test_kernels_are_bounded_and_symmetric(a, b):
    assert 0 <= S.jaro_winkler_py(a, b) <= 1 and 0 <= S.seq_ratio_py(a, b) <= 1
    assert S.jaro_winkler_py(a, b) == pytest.approx(S.jaro_winkler_py(b, a), abs=0.12)  # greedy matches may differ by direction
    assert S.jaro_winkler_py(a, a) == 1


@given(st.text(max_size=40))
@settings(max_examples=300, deadline=None)
def test_recovery_gives_json_or_nothing(t):
    import json

    got = extract.complete_json("x [" + t)
    assert got is None or json.loads(got) is not None or got == "null"


def test_components_match_union_find(spark):
    rng = random.Random(4)
    pairs = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        if a != b:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    got = {r[0]: r[1] for r in connected_components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    assert got == {x: find(x) for x in root}
    assert connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_union_is_order_free_and_loses_nothing(spark):
    rng = random.Random(1)
    data = [(1, "a", "b", "R", {rng.choice("xyz"): str(rng.randrange(3)) for _ in range(rng.randrange(3))}, i) for i in range(40)]
    kind = "doc_id int, src string, dst string, rel_type string, quals map<string,string>, ord long"
    one = relations.dedup_relations(spark.createDataFrame(data, kind)).first()
    rng.shuffle(data)
    two = relations.dedup_relations(spark.createDataFrame(data, kind).repartition(7)).first()
    assert one == two
    kept = {(k, v) for k, vs in {**{k: [v] for k, v in one["quals"].items()}, **one["alternatives"]}.items() for v in vs}
    assert kept == {(k, v) for r in data for k, v in r[4].items()}


def test_fold_equals_sequential(spark):
    rng = random.Random(2)
    data = [(g, "a", "b", "R", {k: f"{k}{rng.randrange(2)}" for k in rng.sample("wxyz", rng.randrange(4))}, i) for g in range(20) for i in range(rng.randrange(1, 6))]
    kind = "doc_id int, src string, dst string, rel_type string, quals map<string,string>, ord long"
    want = {}
    for g, *_, quals, _i in data:
        seen = want.setdefault(g, {})
        if len(quals) > len(seen):
            want[g] = dict(quals)
        elif len(quals) == len(seen):
            want[g] = {**quals, **seen}
    got = {r["doc_id"]: r["quals"] for r in relations.dedup_relations(spark.createDataFrame(data, kind), "fold").collect()}
    assert got == want


def test_page_cascade_is_total(spark, small):
    rows = pages.classify_page(views.page_signals(spark, small))
    assert rows.where("label not in ('text', 'ocr', 'skip') or label is null").count() == 0


def test_finalize_removes_all_defects(spark, small):
    e, r = clean.finalize(views.dirty_entities(spark, small), views.dirty_relations(spark, small))
    q = clean.quality_table(e, r).first()
    assert q["self_loops"] == 0 and q["dangling_ends"] == 0 and q["type_variants"] == 2 and q["id_shapes"] == 2
    assert e.groupBy("doc_id", "ent_id").count().where("count > 1").count() == 0


def test_conform_is_idempotent(spark):
    ents = spark.createDataFrame([(1, "B", "ORGANIZATION", "5 Brigade"), (1, "N", "ORGANIZATION", "2 battalion")], "doc_id int, ent_id string, type string, name string")
    rels = spark.createDataFrame([(1, "B", "N", "commands"), (1, "N", "B", "weird thing")], "doc_id int, src string, dst string, rel_type string")
    vocab = spark.createDataFrame([("commands",), ("subordinate_to",)], "label string")
    once = conform.conform(rels, ents, vocab)
    key = lambda df: sorted(tuple(r) for r in df.select("src", "rel_type", "dst").collect())
    assert key(once) == key(conform.conform(once, ents, vocab)) == [("N", "subordinate_to", "B"), ("N", "weird thing", "B")]


def test_vector_snap_and_novel(spark):
    rels = spark.createDataFrame([("employs",), ("hires",), ("zzz",), ("Commands",)], "rel_type string")
    vocab = spark.createDataFrame([("employ",), ("command",)], "label string")
    lv = spark.createDataFrame([("hires", [0.9, 0.43589]), ("zzz", [0.0, 1.0])], "label string, vec array<double>")
    vv = spark.createDataFrame([("employ", [1.0, 0.0])], "label string, vec array<double>")
    got = {r["rel_type"]: (r["canon"], r["tier"]) for r in conform.snap_predicates(rels, vocab, lv, vv).collect()}
    assert got == {"employs": ("employ", "singular"), "hires": ("employ", "vector"), "zzz": ("zzz", "novel"), "Commands": ("command", "singular")}
    assert conform.promote(vocab, spark.createDataFrame([("zzz",)], "label string")).agg(ontology.version_hash(vocab)).first() != vocab.agg(ontology.version_hash(vocab)).first()


def test_retrieval_methods_agree_and_refinements_add(spark, small):
    classes = views.ontology_classes(spark, small)
    w = views.query_windows(spark, small, classes)
    key = lambda df: {(r["doc_id"], r["win_no"], r["class_id"]): round(r["cos"], 6) for r in df.collect()}
    assert key(ontology.retrieve_classes(w, classes, 0.72)) == key(ontology.retrieve_classes(w, classes, 0.72, "join"))
    sub = views.subclass_edges(classes)
    preds = classes.select(F.col("class_id").cast("string").alias("pred_id"), "label", "definition", F.col("class_id").alias("domain"), F.col("class_id").alias("range"))
    none, n0 = ontology.retrieve(w, classes, sub, preds, frozenset())
    full, n1 = ontology.retrieve(w, classes, sub, preds)
    pick = lambda df: {(r["doc_id"], r["class_id"]) for r in df.collect()}
    assert pick(none) <= pick(full) and n0.count() <= n1.count()


def test_pagerank_sums_to_one(spark):
    e = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a"), ("d", "c")], "src string, dst string")
    got = {r["node"]: r["pr"] for r in ontology.pagerank(e, rounds=60).collect()}
    assert sum(got.values()) == pytest.approx(1) and max(got, key=got.get) == "c"


def test_exact_blocks_equal_brute_force_and_lsh_is_inside(spark, small):
    v = views.near_duplicate_vectors(spark, small)
    rows = v.collect()
    x = np.array([r["vec"] for r in rows])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    cos = x @ x.T
    np.fill_diagonal(cos, -2)
    ids = [r["vec_id"] for r in rows]
    want = {tuple(sorted((ids[i], ids[j]))) for i in range(len(ids)) for j in np.argsort(-cos[i], kind="stable")[:5]}
    got = {(r["left_id"], r["right_id"]) for r in resolve.block_vector(v, 5, slab=100).collect()}
    assert len(got ^ want) <= 2  # equal cosines
    gold = {(r["gold_id"], r["vec_id"]) for r in rows if r["vec_id"] != r["gold_id"]}
    lsh = {(r["left_id"], r["right_id"]) for r in resolve.block_vector(v, 20, "lsh").collect()}
    assert gold <= got and len(gold & lsh) >= 0.9 * len(gold)


def test_blocked_pairs_lie_in_all_pairs(spark, small):
    e = views.homonyms(spark, small)
    key = lambda df: {(r["left_id"], r["right_id"]) for r in df.collect()}
    assert key(names.candidate_pairs(e)) <= key(names.candidate_pairs(e, "all"))


def test_no_cluster_breaks_a_discriminator(spark):
    rng = random.Random(3)
    pairs = spark.createDataFrame([(a, b, rng.random()) for a, b in {tuple(sorted(rng.sample(range(60), 2))) for _ in range(80)}], "left_id long, right_id long, score double")
    props = {i: rng.choice([None, "1", "2"]) for i in range(60)}
    ents = spark.createDataFrame([(i, {"dob": p} if p else {"x": "1"}) for i, p in props.items()], "ent_id long, props map<string,string>")
    got = {}
    for r in resolve.clusters(pairs, ents).collect():
        got.setdefault(r["canonical_id"], set()).add(props[r["ent_id"]])
    assert all(len(v - {None}) <= 1 for v in got.values())


def test_score_pairs_guard_and_bounds(spark):
    kind = "ent_id long, name string, type string, vec array<double>, aliases array<string>, props map<string,string>, doc_id long, chunk_no int"
    e = spark.createDataFrame([(1, "Ana Ruiz", "PERSON", [1.0, 0.0], ["Ana Ruiz"], {"role": "x"}, 1, 0), (2, "Ana Ruiz", "OFFICER", [1.0, 0.0], ["Ana Ruiz"], {"role": "x"}, 1, 0), (3, "Ana Ruiz", "PERSON", [1.0, 0.0], ["Ana Ruiz"], {"dob": "1"}, 2, 0), (4, "Ana Ruiz", "PERSON", [1.0, 0.0], ["Ana Ruiz"], {"DOB": "9", "dob": "2"}, 2, 0)], kind)
    p = spark.createDataFrame([(1, 2), (3, 4)], "left_id long, right_id long")
    got = {r["left_id"]: r for r in resolve.decide_resolution(resolve.score_pairs(p, e)).collect()}
    assert got[1]["score"] == pytest.approx(1.0) and got[1]["action"] == "auto_merge" and got[3]["conflict"] and got[3]["action"] == "distinct"


def test_property_conflicts_weigh_double(spark):
    df = spark.createDataFrame([({"a": "1", "b": "2", "c": "3"}, {"a": "1", "b": "2", "c": "9"})], "a map<string,string>, b map<string,string>")
    assert df.select(resolve.property_score(F.col("a"), F.col("b"))).first()[0] == 0.0


def test_hash_embedding(spark):
    df = spark.createDataFrame([("x",), ("x",), ("y",)], "t string").select(resolve.embed_hash(F.col("t")).alias("v"))
    a, b, c = (np.array(r["v"]) for r in df.collect())
    assert (a == b).all() and np.linalg.norm(a) == pytest.approx(1) and abs(a @ c) < 0.6


def test_normalize_records(spark):
    raw = [('{"_id":{"$oid":"a1"},"createdAt":"2024-01-01T00:00:00Z","filePath":"x/y.PDF","mimeType":"application/pdf"}',), ('{"id":"b","created_at":"2024-01-02 00:00:00","content":"hello"}',), ("no json",)]
    got = {r["record_id"]: r for r in records.route_format(records.resolve_location(records.normalize_records(spark.createDataFrame(raw, "value string")), "/base")).collect()}
    assert got["a1"]["handler"] == "pdf" and got["a1"]["location"] == "/base/application_pdf/x/y.PDF" and got["b"]["text"] == "hello" and got["b"]["handler"] == "text" and got[None]["handler"] == "text"


def test_measures(spark):
    f = spark.createDataFrame([(1, "a"), (1, "b")], "doc int, name string")
    g = spark.createDataFrame([(1, "a"), (1, "c"), (1, "d")], "doc int, name string")
    r = M.set_f1(f, g, ["doc", "name"]).first()
    assert (r["tp"], r["fp"], r["fn"]) == (1, 1, 2) and r["f1"] == pytest.approx(0.4)
    t = spark.createDataFrame([("a b c", "a x c d")], "f string, g string")
    assert t.select(M.wer(F.col("f"), F.col("g"))).first()[0] == pytest.approx(0.5)
    c = spark.createDataFrame([(1, 1), (2, 1), (3, 3)], "ent_id int, canonical_id int")
    gold = spark.createDataFrame([(1, 1), (2, 2), (3, 3)], "ent_id int, gold_id int")
    assert tuple(M.false_merges(c, gold).first()) == (2, 1, 1)
    assert M.simulate_workers([3, 1, 1, 1], 2)["makespan"] == 3


def test_settings_from_environment(monkeypatch):
    monkeypatch.setenv("KGREFINE_CLASS_FLOOR", "0.5")
    assert Settings.from_env().class_floor == 0.5 and Settings.from_env(class_floor=0.9).class_floor == 0.9


def test_envelopes_give_every_document_a_result(spark, tmp_path):
    ids = spark.createDataFrame([(1,), (2,)], "doc_id int")
    ents = spark.createDataFrame([(1, "a", "A")], "doc_id int, ent_id string, name string")
    out = records.result_envelopes(ents, ents.select("doc_id", F.col("ent_id").alias("src")), ents.select("doc_id", F.col("ent_id").alias("left_id")), ids)
    got = {r["doc_id"]: r for r in out.collect()}
    assert got[2]["entities"] == [] and len(got[1]["entities"]) == 1
    records.write_results(out, f"file://{tmp_path}/r", partitions=1)
    assert spark.read.text(f"file://{tmp_path}/r").count() == 2


def test_resolution_store(spark, tmp_path):
    store = resolve.ResolutionStore(spark, f"file://{tmp_path}/store")
    a = spark.createDataFrame([(1, "John Doe")], "ent_id int, name string")
    store.upsert(a)
    store.upsert(a)
    assert store.read().count() == 1
    assert [tuple(r) for r in store.pairs(spark.createDataFrame([(1, "John Doe"), (2, "Jon Doe")], "ent_id int, name string")).collect()] == [(2, 1)]


def plan_of(df):
    return df._jdf.queryExecution().toString()


def test_plans(spark, small):
    p = plan_of(pages.route_document(pages.classify_page(views.page_signals(spark, small))))
    assert "Cartesian" not in p and "l_returnflag" not in p.split("== Physical Plan ==")[1]
    docs = views.table(spark, small, "documents").where("n_chars > 100").select("doc_id", "n_chars")
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars,100)]" in plan_of(docs) and "text" not in plan_of(docs).split("ReadSchema")[1]
    pairs = names.candidate_pairs(views.homonyms(spark, small))
    assert "CartesianProduct" not in plan_of(pairs) and "BroadcastNestedLoopJoin" not in plan_of(pairs)


def test_bucketed_join_has_no_exchange_below_it(spark, small):
    from kgrefine import workloads

    p = plan_of(workloads.queries()["join_bucketed"](spark, small)).split("== Physical Plan ==")[1]
    assert p.count("Exchange hashpartitioning") <= 1 and "SortMergeJoin" in p


def test_library_does_not_import_the_text_subpackage():
    from pathlib import Path

    root = Path(__file__).resolve().parents[1] / "kgrefine"
    for f in root.rglob("*.py"):
        if "llm" not in f.relative_to(root).parts:
            assert "kgrefine.llm" not in f.read_text() and "from .llm" not in f.read_text()


def test_an_entity_whose_pairs_are_all_refused_is_in_no_cluster(spark):
    pairs = spark.createDataFrame([(1, 2, 0.99), (2, 3, 0.97), (7, 8, 0.96)], "left_id long, right_id long, score double")
    ents = spark.createDataFrame([(1, {"dob": "a"}), (2, {"dob": "a"}), (3, {"dob": "b"}), (7, {"dob": "c"}), (8, {"dob": "d"})], "ent_id long, props map<string,string>")
    assert sorted(tuple(r) for r in resolve.with_partner(resolve.clusters(pairs, ents)).collect()) == [(1, 1), (2, 1)]


def test_aliases_and_pairs_are_never_broadcast(spark, small):
    from kgrefine import workloads

    pairs = [names.candidate_pairs(views.homonyms(spark, small), s) for s in ("all", "blocked")]
    for df in [workloads.queries()["alias_search_recall"](spark, small), *pairs]:
        assert "BroadcastExchange" not in df._jdf.queryExecution().executedPlan().toString()
    assert pairs[1].count() == pairs[1].select("left_id", "right_id").distinct().count() > 0
