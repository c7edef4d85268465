"""Worked examples with values that follow from the formulas."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from kgrefine.functions import strings as S
from kgrefine.operators import chunks, clean, conform, extract, gates, names, ontology, pages, relations, resolve, tabular


def rows(df, *cols):
    return [tuple(r) for r in (df.select(*cols) if cols else df).collect()]


@pytest.mark.parametrize("sig,label", [((0.0, .9, 0.0, 900, 0), "skip"), ((1.0, .16, 0.0, 900, 0), "ocr"), ((1.0, .15, 0.0, 900, 0), "text"), ((1.0, 0.0, .2, 900, 0), "ocr"), ((1.0, 0.0, 0.0, 51, 900), "text"),
                                       ((1.0, 0.0, 0.0, 50, 201), "ocr"), ((1.0, 0.0, 0.0, 50, 200), "text"), ((1.0, 0.0, 0.0, 0, 201), "ocr"), ((1.0, 0.0, 0.0, 0, 200), "skip"), ((1.0, 0.0, 0.0, 1, 0), "text")])
def test_page_cascade(spark, sig, label):
    a, block, xref, chars, draw = sig
    df = spark.createDataFrame([(a, block, xref, 1 if xref else 0, chars, draw)], "area double, img_block double, img_xref double, n_xref int, chars long, drawings long")
    assert pages.classify_page(df).first()["label"] == label


def test_xref_gate_and_ablation(spark):
    df = spark.createDataFrame([(1.0, 0.0, .9, 0, 10, 300)], "area double, img_block double, img_xref double, n_xref int, chars long, drawings long")
    assert pages.classify_page(df).first()["deciding"] == "drawings"
    assert pages.classify_page(df, disable={"draw"}).first()["label"] == "text"


@pytest.mark.parametrize("n,route", [((4, 1, 7), "text"), ((1, 4, 0), "ocr"), ((5, 4, 1), "mixed")])
def test_routes_are_inclusive(spark, n, route):
    data = [(1, v, 100) for v, k in zip(("text", "ocr", "skip"), n) for _ in range(k)]
    assert pages.route_document(spark.createDataFrame(data, "doc_id int, label string, chars long")).first()["route"] == route


def test_route_without_usable_page_falls_back(spark):
    got = pages.route_document(spark.createDataFrame([(1, "skip", 0)] * 3, "doc_id int, label string, chars long")).first()
    assert got["fallback"] and got["route"] == "ocr"


@pytest.mark.parametrize("a,b,seq,jw", [("cold bolt", "old bolt", .941176, .962963), ("hot ring", "old ring", .75, .833333), ("red rod", "red ring", .666667, .867857), ("marta lindov", "marta lindova", .96, .984615),
                                        ("t. vale", "tomas vale", .705882, .787143), ("captain marta lindov", "marta lindov", .75, .755556), ("small widget", "shiny wagon", .347826, .626263), ("stefan", "stephan", .769231, .894444), ("hot", "ht", .8, .611111)])
def test_string_kernels(a, b, seq, jw):
    assert S.seq_ratio_py(a, b) == pytest.approx(seq, abs=1e-6) and S.jaro_winkler_py(a, b) == pytest.approx(jw, abs=1e-6)


def test_phonetic_families():
    assert len({S.double_metaphone_py(n)[0] for n in ("John", "Jon", "Jhon")}) == 1
    assert S.double_metaphone_py("Smith")[1] == S.double_metaphone_py("Smit")[0] and S.double_metaphone_py("Knight")[0] == S.double_metaphone_py("Night")[0]


def _pair(spark, a, b):
    return spark.createDataFrame([(a, b)], "name_a string, name_b string")


def test_composite_and_tiers(spark):
    got = names.name_similarity(_pair(spark, "john doe", "jon doe")).first()
    bare = names.name_similarity(_pair(spark, "john doe", "jon doe"), boost=False).first()
    assert bare["score"] == pytest.approx(.7067, abs=1e-3) and got["score"] == pytest.approx(.8)
    same = names.name_similarity(_pair(spark, "John  Doe", "john doe")).first()
    assert (same["score"], same["reason"]) == (1.0, "exact")
    for a, b, score in (("ana lindov", "ana lindova", .85), ("t. vale", "tomas vale", .92), ("cold bolt", "old bolt", .941176)):
        assert names.name_similarity(_pair(spark, a, b), "tiered").first()["score"] == pytest.approx(score, abs=1e-6)
        assert names.name_similarity(_pair(spark, b, a), "tiered").first()["score"] == pytest.approx(score, abs=1e-6)


def test_abbreviation(spark):
    df = spark.createDataFrame([("Small Widget", "Shiny Wagon"), ("T. Vale", "Tomas Vale")], "a string, b string")
    got = rows(df, S.abbrev_signal(F.col("a"), F.col("b"), "first_letter"), S.abbrev_signal(F.col("a"), F.col("b")))
    assert got == [(1.0, 0.0), (1.0, 1.0)]


@pytest.mark.parametrize("sim,delta,action", [(.951, 1, "auto_merge"), (.95, 1, "manual_review"), (.901, 1, "manual_review"), (.90, 1, "different_contexts"), (.75, 1, "different_contexts"), (.749, 1, None), (1.0, 0, "different_contexts")])
def test_decision_surface(spark, sim, delta, action):
    got = names.decide_rule(spark.createDataFrame([(sim, delta, 1)], "score double, delta int, n_shared int")).first()
    assert (got and got["action"]) == action


def test_vacuous_agreement_lowers_confidence(spark):
    df = names.context_agreement(spark.createDataFrame([("a", None, 0.99)], "role_a string, role_b string, score double"), ("role",))
    assert names.decide_rule(df).first()["confidence"] == "medium"
    assert names.decide_rule(df, require_evidence=True).first()["action"] == "manual_review"


@pytest.mark.parametrize("score,name,conflict,action", [(.85, "x", False, "auto_merge"), (.8499, "x", False, "manual_review"), (.60, "x", False, "manual_review"), (.55, "Operation Dawn", False, "codename_candidate"), (.55, "x", False, "distinct"),
                                                        (.49, "Operation Dawn", False, "distinct"), (.99, "x", True, "distinct")])
def test_resolution_decision(spark, score, name, conflict, action):
    df = spark.createDataFrame([(score, name, "y", conflict)], "score double, name_a string, name_b string, conflict boolean")
    assert resolve.decide_resolution(df).first()["action"] == action


def test_constrained_cluster(spark):
    pairs = spark.createDataFrame([(1, 2, .95), (2, 3, .90)], "left_id long, right_id long, score double")
    ents = spark.createDataFrame([(1, {"dob": "1"}), (2, {"x": "1"}), (3, {"dob": "2"})], "ent_id long, props map<string,string>")
    assert dict(rows(resolve.clusters(pairs, ents))) == {1: 1, 2: 1, 3: 3}


def test_alias_expansion_and_idempotence(spark):
    df = spark.createDataFrame([("PERSON", "Tomas Vale"), ("PERSON", "Vale"), ("ORGANIZATION", "Vale Works")], "type string, name string")
    once = names.expand_aliases(df)
    got = {r["name"]: r["aliases"] for r in once.collect()}
    assert set(got["Tomas Vale"]) == {"Tomas Vale", "T. Vale", "Tomas V.", "TV", "T.V."} and got["Vale"] == ["Vale"] and got["Vale Works"] == ["Vale Works"]
    assert rows(names.expand_aliases(once)) == rows(once)


def test_variant_mining(spark):
    docs = spark.createDataFrame([(1, "c. bolt and cld bolt, cold bolts but hot ring")], "doc_id int, text string")
    ents = spark.createDataFrame([(1, "e", "PERSON", "cold bolt"), (1, "h", "PERSON", "ht ring")], "doc_id int, ent_id string, type string, name string")
    got = {(r["ent_id"], r["alias"], r["rule"]) for r in names.mine_variants(ents, docs).collect()}
    assert got == {("e", "c. bolt", "initial"), ("e", "cld bolt", "spelling"), ("e", "cold bolts", "spelling")}


@pytest.mark.parametrize("name,core", [("Agent Dr. Ana Ruiz", "Ana Ruiz"), ("Ana Ruiz", "Ana Ruiz"), ("Maria Elena Ruiz", "Elena Ruiz"), ("Commissionersgeneral Ana Ruiz", "Commissionersgeneral Ana Ruiz"), ("Ruiz", "Ruiz")])
def test_core_name(spark, name, core):
    df = spark.createDataFrame([(name,)], "n string").select(clean.core_name(F.col("n")).alias("n"))
    assert df.first()[0] == core
    assert df.select(clean.core_name(F.col("n"))).first()[0] == core


def test_attested_titles_keep_given_names(spark):
    df = spark.createDataFrame([("Maria Elena Ruiz",), ("Dr. Ana Ruiz",)], "n string")
    assert rows(df, clean.core_name(F.col("n"), attested=F.array(F.lit("dr")))) == [("Maria Elena Ruiz",), ("Ana Ruiz",)]


def test_relation_labels(spark):
    df = spark.createDataFrame([("reported to",), ("Reported-To",), ("REPORTED_TO",), ("surveiled",)], "r string")
    assert [r[0] for r in rows(df, clean.canon_rel_type(F.col("r")))] == ["REPORTED_TO"] * 3 + ["SURVEILLED"]


def _rels(spark, *quals):
    return spark.createDataFrame([(1, "a", "b", "R", q, i) for i, q in enumerate(quals)], "doc_id int, src string, dst string, rel_type string, quals map<string,string>, ord long")


def test_relation_dedup_modes(spark):
    show = lambda df: df.select(relations.show_quals(F.col("quals"))).first()[0]
    r = _rels(spark, {}, {"date": "1"}, {"place": "x"})
    assert show(relations.dedup_relations(r)) == show(relations.dedup_relations(r, "fold")) == "date=1;place=x;"
    r = _rels(spark, {"date": "1"}, {"place": "x", "note": "n"})
    assert show(relations.dedup_relations(r)) == "date=1;note=n;place=x;" and show(relations.dedup_relations(r, "fold")) == "note=n;place=x;" and show(relations.dedup_relations(r, "first")) == "date=1;"
    got = relations.dedup_relations(_rels(spark, {"date": "2"}, {"date": "1"})).first()
    assert got["quals"] == {"date": "2"} and got["alternatives"] == {"date": ["1", "2"]}


def test_orientation_converges(spark):
    ents = spark.createDataFrame([(1, "B", "ORGANIZATION", "5 Brigade"), (1, "N", "ORGANIZATION", "2 battalion"), (1, "M", "ORGANIZATION", "3 battalion"), (1, "p", "PERSON", "Brigade Joe")], "doc_id int, ent_id string, type string, name string")
    four = [("B", "N", "subordinate_to"), ("B", "N", "commands"), ("B", "N", "Has-Subordinate"), ("N", "B", "subordinate_to")]
    rels = spark.createDataFrame([(1, *x) for x in four], "doc_id int, src string, dst string, rel_type string")
    assert set(rows(conform.orient_by_rank(conform.fold_inverse(rels), ents), "src", "rel_type", "dst")) == {("N", "subordinate_to", "B")}
    rest = spark.createDataFrame([(1, "N", "M", "subordinate_to"), (1, "p", "N", "subordinate_to")], "doc_id int, src string, dst string, rel_type string")
    assert set(rows(conform.orient_by_rank(rest, ents), "src", "dst")) == {("N", "M"), ("p", "N")}


def test_grid(spark):
    grid = [(1, "R", i, j) for i in range(2) for j in range(58)] + [(2, "R", i, i) for i in range(58)]
    got = {r["doc_id"]: r for r in gates.detect_grid(spark.createDataFrame(grid, "doc_id int, rel_type string, src int, dst int")).collect()}
    assert got[1]["grid"] and got[1]["fill"] == 1.0 and not got[2]["grid"]


def test_quality_gate(spark):
    ents = spark.createDataFrame([(d, f"p{i}", "PERSON") for d, n in ((1, 9), (2, 7)) for i in range(n)], "doc_id int, ent_id string, type string")
    rels = spark.createDataFrame([(d, "p0", "p1", "REPORTED_TO") for d in (1, 2) for _ in range(60)], "doc_id int, src string, dst string, rel_type string")
    got = {r["doc_id"]: r for r in gates.quality_gate(ents, rels).collect()}
    assert got[1]["reasons"] == ["person_diversity", "concentration"] and got[1]["second_pass"] and got[2]["reasons"] == ["concentration"]
    fin = spark.createDataFrame([(1, "f", "FINANCIAL"), (1, "o", "ORGANIZATION")], "doc_id int, ent_id string, type string")
    none = rels.where("false")
    assert gates.quality_gate(fin, none).first()["reasons"] == ["financial_links", "financial_labels"]
    cross = spark.createDataFrame([(1, "f", "o", "OWNS")], "doc_id int, src string, dst string, rel_type string")
    assert "financial_labels" in gates.quality_gate(fin, cross).first()["reasons"] and "financial_links" not in gates.quality_gate(fin, cross).first()["reasons"]


def test_budget_is_a_prefix(spark):
    df = spark.createDataFrame([(1, 1, .9, 2000), (1, 2, .8, 1400), (1, 3, .75, 200)], "doc_id int, class_id int, score double, tokens long")
    assert [r["class_id"] for r in ontology.cutoff(df, budget=5000, share=.7).orderBy("class_id").collect()] == [1, 2]


def test_subclass_expansion(spark):
    sub = spark.createDataFrame([(10, 1), (11, 1), (20, 2)], "child int, parent int")
    hits = spark.createDataFrame([(1, 1, .80), (1, 2, .799), (1, 11, .82)], "doc_id int, class_id int, score double")
    got = {r["class_id"]: (r["score"], r["provenance"]) for r in ontology.expand_children(hits, sub).collect()}
    assert got == {1: (.80, "retrieved"), 2: (.799, "retrieved"), 10: (.78, "expanded"), 11: (.82, "retrieved")}


def test_ancestor_predicates_and_cycles(spark):
    sub = spark.createDataFrame([("c", "b"), ("b", "a"), ("a", "b")], "child string, parent string")
    preds = spark.createDataFrame([("p", "a", "z")], "pred_id string, domain string, range string")
    hits = spark.createDataFrame([(1, "c")], "doc_id int, class_id string")
    assert ontology.predicates_exact(hits, preds).count() == 0
    assert rows(ontology.predicates_ancestor(hits, ontology.closure(sub), preds)) == [(1, "p", 2)]


def test_chunks_cover_and_partition(spark):
    df = spark.createDataFrame([(1, "x" * 17000), (2, ""), (3, "y" * 9000), (4, None)], "doc_id int, text string")
    got = rows(chunks.chunk_chars(df), "doc_id", "o_start", "o_end", "p_start", "p_end")
    assert [g[1] for g in got if g[0] == 1] == [0, 7000, 14000] and [g[1] for g in got if g[0] == 3] == [0, 7000] and [g for g in got if g[0] in (2, 4)] == [(2, 0, 0, 0, 0), (4, 0, 0, 0, 0)]
    one = sorted(g[3:] for g in got if g[0] == 1)
    assert one[0][0] == 0 and one[-1][1] == 17000 and all(a[1] == b[0] for a, b in zip(one, one[1:]))


def test_page_windows(spark):
    df = spark.createDataFrame([(1, p) for p in range(1, 13)], "doc_id int, page_no int")
    got = {}
    for r in chunks.chunk_pages(df).collect():
        got.setdefault(r["chunk_no"], set()).add(r["page"])
    assert got == {0: set(range(1, 7)), 1: set(range(5, 12)), 2: set(range(10, 13))}


def test_sentinel(spark):
    df = spark.createDataFrame([("hello",)], "t string")
    assert rows(df, chunks.limit_text(F.col("t"), 0), chunks.limit_text(F.col("t"), 2), chunks.limit_text_buggy(F.col("t"), 0)) == [("hello", "he", "h")]


def test_json_recovery(spark):
    data = ['x ```json\n{"entities":[1]}\n``` y', '```json\n{"entities":[{"name":"a","type":"T"},{"na', 'prose {"entities":[]} prose', "nothing"]
    got = extract.recover_json(spark.createDataFrame([(d,) for d in data], "answer string")).collect()
    assert [r["stage"] for r in got] == ["closed_fence", "open_fence", "raw", "none"]
    assert [r["json"] for r in got] == ['{"entities":[1]}', '{"entities":[{"name":"a","type":"T"}]}', '{"entities":[]}', None]


def test_ordered_release(spark):
    from kgrefine.streaming.ordered import inversions, ordered_release

    df = spark.createDataFrame([(1, 10), (2, 2), (3, 5), (4, 7)], "seq long, done_ts long")
    assert [r["release_ts"] for r in ordered_release(df, bucket_rows=2).orderBy("seq").collect()] == [10] * 4
    assert inversions(df).where("parked").count() == 3


def test_breaker_does_not_extend(spark):
    at = lambda s: dt.datetime(2024, 1, 1) + dt.timedelta(seconds=s)
    df = spark.createDataFrame([("s", i, at(s), f) for i, (s, f) in enumerate([(0, True), (30, True), (59, False), (60, False), (95, False)])], "source string, req_id int, ts timestamp, failed boolean")
    got = {r["req_id"]: r["state"] for r in ontology.circuit_breaker(df).collect()}
    assert (got[2], got[3], got[4]) == ("unguided", "guided", "guided")


def test_tabular_plan(spark):
    df = spark.createDataFrame([(1, "A", "a; b", "12", "2024-01-05"), (2, None, "c", "12x", "2024-13-01"), (3, "total", "z", "1", None)], "n int, grp string, multi string, num string, day string")
    plan = {"entity_type": "ROW", "name_column": "multi", "columns": {"n": "int", "grp": "string", "multi": "string", "num": "int", "day": "date"}, "relations": [{"column": "grp", "rel_type": "IN", "target_type": "G"}], "split": {"multi": ";"}, "fill": ["grp"], "drop_where": "grp = 'total'"}
    out = tabular.execute_plan(df, plan, "n").orderBy("n", "multi")
    assert rows(out, "n", "grp", "multi", "num", "day__bad") == [(1, "A", "a", 12, False), (1, "A", "b", 12, False), (2, "A", "c", None, True)]
    ents, rels, warn = tabular.map_records(out, plan, "n")
    assert rows(warn) == [("day", 1)] and rels.count() == 3 and ents.count() == 3


def test_retry_and_failures(spark, tmp_path):
    chunks_ = spark.createDataFrame([(1, 0, "Ana Ruiz met Tom Vale"), (2, 0, "x")], "doc_id long, chunk_no int, text string")
    good, left = extract.retry_loop(chunks_, extract.get_provider("replay", answers={(1, 0): '```json\n{"entities":[{"name":"Ana Ruiz","type":"PERSON"}]}'}), 1)
    assert [r["doc_id"] for r in good.collect()] == [1] and [r["doc_id"] for r in left.collect()] == [2]
    extract.append_failures(left.select("doc_id", "chunk_no"), f"file://{tmp_path}/log")
    assert extract.rerun_from_failures(chunks_, spark.read.json(f"file://{tmp_path}/log")).count() == 1
    found = extract.parse_entities(extract.recover_json(extract.run_provider(chunks_, extract.get_provider("rule"))))
    assert {r["name"] for r in found.collect()} == {"Ana Ruiz", "Tom Vale"}


def test_embed_backfill_retries_alone(spark):
    def call(texts):
        if "bad" in texts and len(texts) > 1:
            raise ValueError
        return [None if t == "bad" else [1.0] for t in texts]

    got = resolve.embed_batches(spark.createDataFrame([("a",), ("bad",), ("c",)], "text string").coalesce(1), call).collect()
    assert [r["vec"] for r in got] == [[1.0], None, [1.0]]
