"""The rows of queries that SQL cannot express, against plain loops over the same tables."""

import heapq
import math
import re
from itertools import combinations

import pytest

from kgrefine import workloads
from kgrefine.functions import strings as S
from kgrefine.measures import word_distance
from kgrefine.operators import names, relations, resolve
from kgrefine.sources import views

Q = workloads.queries()


@pytest.fixture(scope="module")
def rows(spark, small):
    kept = {}

    def get(name):
        if name not in kept:
            kept[name] = Q[name](spark, small).collect()
        return kept[name]

    return get


def read(spark, small, name):
    return spark.read.parquet(f"{small}/{name}.parquet").collect()


def test_relation_fold(spark, small, rows):
    from kgrefine.operators.clean import canon_rel_type
    from pyspark.sql import functions as F

    groups = {}
    for r in views.edges(spark, small).withColumn("rel_type", canon_rel_type(F.col("rel_type"))).collect():
        groups.setdefault(tuple(r[k] for k in relations.KEY), []).append((r["ord"], r["quals"]))
    want = {}
    for key, found in groups.items():
        acc = {}
        for _, q in sorted(found, key=lambda x: x[0]):
            if len(q) == len(acc):
                acc = {**q, **acc}
            elif len(q) > len(acc):
                acc = q
        want[key] = ("".join(f"{k}={acc[k]};" for k in sorted(acc)), len(found))
    assert {tuple(r[k] for k in relations.KEY): (r["quals"], r["n_merged"]) for r in rows("relation_dedup_fold")} == want


def test_breaker(spark, small, rows):
    events = sorted(read(spark, small, "events"), key=lambda e: (e["ts"], e["event_id"]))
    until, want = {}, {}
    for e in events:
        us = round((e["ts"] - events[0]["ts"]).total_seconds() * 1e6)
        source = e["user_id"] % 8
        is_open = us < until.get(source, -1)
        want[e["event_id"]] = "unguided" if is_open else "guided"
        if e["event_type"] == "error" and not is_open:
            until[source] = us + 3600 * 10**6
    assert {r["req_id"]: r["state"] for r in rows("breaker_state")} == want and "unguided" in want.values()


def test_workers(spark, small, rows):
    hours = {}
    for e in read(spark, small, "events"):
        hours.setdefault(e["ts"].replace(minute=0, second=0, microsecond=0), []).append((e["event_id"], e["value"] or 0.0))
    for r in rows("worker_simulation"):
        ends, waits = [], []
        for jobs in hours.values():
            free, wait = [0.0] * r["workers"], 0.0
            for _, d in sorted(jobs):
                t = heapq.heappop(free)
                wait += t
                heapq.heappush(free, t + d)
            ends.append(max(free))
            waits.append(wait / len(jobs))
        assert r["jobs"] == sum(map(len, hours.values()))
        assert r["makespan"] == pytest.approx(sum(ends) / len(ends), abs=1e-3) and r["mean_wait"] == pytest.approx(sum(waits) / len(waits), abs=1e-3)


def packed(blocks, size):
    out = []
    for b in blocks:
        if out and len(out[-1]) + len(b) + 1 <= size:
            out[-1] += "\n" + b
        else:
            out.append(b)
    return out


def test_dense_windows(spark, small, rows):
    want = set()
    for d in read(spark, small, "documents"):
        wins = []
        for i, w in enumerate(packed([p for p in re.split("\n+", d["text"] or "") if p], 1500)):
            nouns = sum(len(x) for x in re.findall("[a-z,;] ([A-Z][a-z]+)", w))
            hits = len(re.findall("(?:^|[^a-z])(?:the|und|les|que)(?:$|[^a-z])", w.lower()))
            wins.append((-(nouns + 6 * hits) / len(w), i, len(w)))
        want |= {(d["doc_id"], i, round(-x, 6), n) for x, i, n in sorted(wins)[:4]}
    got = {(r["doc_id"], r["win_no"], r["density"], r["n"]) for r in rows("windows_dense")}
    assert len(got) == len(want) and {(a, b, c) for a, b, _, c in got} == {(a, b, c) for a, b, _, c in want}
    density = {(a, b): x for a, b, x, _ in want}
    assert all(density[a, b] == pytest.approx(x, abs=2e-6) for a, b, x, _ in got)


def test_virtual_pages(spark, small, rows):
    want = set()
    for p in read(spark, small, "pages"):
        h = re.sub("(?i)</(li|p|h1|tr|div|footer)>", "\n", p["html"])
        h = re.sub("<[^>]*>", "", re.sub("(?i)</t[dh]>\\s*<t[dh]>", " | ", h))
        blocks = [b.strip(" ") for b in h.split("\n") if b.strip(" ")]
        want |= {(p["page_id"], i, x, len(x) < 200) for i, x in enumerate(packed(blocks, 3600))}
    assert {tuple(r) for r in rows("virtual_pages")} == want


def planted(spark, small):
    docs, ents = views.planted_text(spark, small)
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    return text, ents.collect()


def mined(spark, small):
    text, ents = planted(spark, small)
    out = {}
    for e in ents:
        first, last = e["name"].lower().split()
        raw = [re.sub(r"^[\W\d_]+|[^\w.]+$", "", w) for w in text[e["doc_id"]].split()]
        raw = [re.sub(r"[\d_]+$", "", w) if w and (w[-1].isdigit() or w[-1] == "_") else w for w in raw]
        raw = [w for w in raw if w]
        for w1, w2 in zip(raw, raw[1:], strict=False):
            l1, l2 = w1.lower(), re.sub(r"\.$", "", w2.lower())
            if l2[:3] != last[:3] or f"{l1} {l2}" == f"{first} {last}":
                continue
            bare = re.sub(r"\.$", "", l1)
            rule = "initial" if bare == first[0] else "spelling" if S.seq_ratio_py(bare, first) >= 0.85 else None
            if rule:
                key = (e["doc_id"], e["ent_id"], f"{w1} {re.sub(r'[.]$', '', w2)}", rule)
                out[key] = out.get(key, 0) + 1
    return out


def test_mined_variants(spark, small, rows):
    want = mined(spark, small)
    assert {(r["doc_id"], r["ent_id"], r["alias"], r["rule"]): r["count"] for r in rows("variant_mining")} == want
    got = rows("variant_discovery")[0]
    assert got["documents"] == len(planted(spark, small)[0])
    assert got["initial_found"] == len({k[0] for k in want if k[3] == "initial"}) and got["spelling_found"] == len({k[0] for k in want if k[3] == "spelling"})
    steps = {r["step"]: r["n"] for r in rows("phase_three_with_text")}
    assert steps["mined initial"] == len({k[1] for k in want if k[3] == "initial"}) and steps["mined spelling"] == len({k[1] for k in want if k[3] == "spelling"})
    assert steps["aliases"] == 5 * got["documents"]


def test_alias_snippets(spark, small, rows):
    text, _ = planted(spark, small)
    want = mined(spark, small)
    got = rows("alias_occurrences")
    assert len(got) == len(want)
    for r in got:
        found = [m.group(0) for m in re.finditer("(?is).{0,30}" + re.escape(r["alias"]) + ".{0,30}", text[r["doc_id"]])][:3]
        assert r["snippets"] == " / ".join(found)


def test_search_recall(spark, small, rows):
    _, ents = planted(spark, small)
    known = {"name": {}, "aliases": {}, "aliases and variants": {}}
    for e in ents:
        a, b = e["name"].split()
        i, j = a[0].upper(), b[0].upper()
        every = {e["name"], f"{i}. {b}", f"{a} {j}.", i + j, f"{i}.{j}."}
        known["name"][e["ent_id"]] = {e["name"].lower()}
        known["aliases"][e["ent_id"]] = {x.lower() for x in every}
        known["aliases and variants"][e["ent_id"]] = {x.lower() for x in every}
    for _, ent, alias, _ in mined(spark, small):
        known["aliases and variants"][ent].add(alias.lower())
    for r in rows("search_recall"):
        hits = 0
        for e in ents:
            a, b = e["name"].split()
            wrong = a[0] + a[2:] if e["doc_id"] % 2 == 0 else a + a[-1]
            forms = [e["name"], f"{a[0]}. {b}", a[0] + b[0], f"{wrong} {b}"]
            hits += sum(f.lower() in known[r["known"]][e["ent_id"]] for f in forms)
        assert (r["queries"], r["hits"]) == (4 * len(ents), hits) and r["recall"] == pytest.approx(hits / (4 * len(ents)), abs=1e-4)


def phonetic(name):
    return [[S.double_metaphone_py(t)[i] for t in name.lower().split()] for i in (0, 1)]


def overlap(a, b):
    (a1, a2), (b1, b2) = phonetic(a), phonetic(b)
    if len(a1) > len(b1):
        a1, a2, b1, b2 = b1, b2, a1, a2
    return sum(p in b1 + b2 or q in b1 + b2 for p, q in zip(a1, a2, strict=True)) / len(b1)


def signals(a, b):
    """Composite signals of two names without initials, gender endings or families among them."""
    x, y = set(a.split()), set(b.split())
    return {"jaro_winkler": S.jaro_winkler_py(a, b), "phonetic": overlap(a, b), "tokens": len(x & y) / len(x | y), "abbreviation": 0.0, "cultural": 0.0}


def composite(a, b, boost=True):
    v = signals(a, b)
    total, top = sum(names.WEIGHTS[k] * v[k] for k in v), max(v.values())
    return max(total, 0.8 * top) if boost and top >= 0.9 else total


def test_name_scores(rows):
    for r in rows("name_scores"):
        a, b = r["name_a"], r["name_b"]
        assert r["composite"] == pytest.approx(composite(a, b), abs=2e-6) and r["no_boost"] == pytest.approx(composite(a, b, False), abs=2e-6)
        assert r["tiered"] == pytest.approx(S.seq_ratio_py(a, b), abs=2e-6)
        v = signals(a, b)
        assert v[r["reason"]] == max(v.values())


def test_phonetic_codes(rows):
    for r in rows("phonetic_codes"):
        one, two = phonetic(r["name"])
        assert (r["primary"], r["secondary"]) == (" ".join(one), " ".join(two)) and re.fullmatch("[A-Z][0-9]{3}", r["soundex"])


def test_rule_layer(spark, small, rows):
    """Candidates, decisions and statuses of the composed rule layer, blocked against all pairs of a document."""
    from collections import Counter

    docs = {}
    for e in views.homonyms(spark, small).collect():
        docs.setdefault(e["doc_id"], []).append(e)
    decided, status, n, missed = Counter(), {}, 0, 0
    rank = {"auto_merge": 3, "manual_review": 2, "different_contexts": 1}
    for ents in docs.values():
        for a, b in combinations(ents, 2):
            score = 1.0 if a["name"] == b["name"] else composite(a["name"], b["name"])
            if score < 0.75:
                continue
            keys = [{"l:" + e["name"].split()[-1][:3], "p:" + "-".join(sorted(phonetic(e["name"])[0]))} for e in (a, b)]
            if not keys[0] & keys[1]:
                missed += 1
                continue
            agree = all(a[k] is None or b[k] is None or a[k].lower() == b[k].lower() for k in ("role", "org", "loc"))
            action = "auto_merge" if agree and score > 0.95 else "manual_review" if agree and score > 0.90 else "different_contexts"
            decided[action] += 1
            n += 1
            for e in (a, b):
                status[e["ent_id"]] = max(status.get(e["ent_id"], 0), rank[action])
    got = Counter()
    for r in rows("phase_three"):
        got[r["action"]] += r["n"]
    assert got == decided
    assert {r["pairs"]: r["n"] for r in rows("blocked_pairs_recall")} == {"all": n + missed, "blocked": n}
    shown = {3: "merged", 2: "review", 1: "candidate", 0: "confirmed_unique"}
    want = Counter(shown[status.get(e["ent_id"], 0)] for ents in docs.values() for e in ents)
    assert {r["dedup_status"]: r["n"] for r in rows("dedup_status")} == want


def parts_as_entities(spark, small):
    from kgrefine.workloads.methods import _parts_as_entities

    return _parts_as_entities(spark, small).collect()


def test_phonetic_blocks_and_resolution(spark, small, rows):
    from collections import Counter

    ents = parts_as_entities(spark, small)
    code = {e["ent_id"]: "-".join(sorted(phonetic(e["name"])[0])) for e in ents}
    sound = {(min(a, b), max(a, b)) for a, b in combinations(code, 2) if code[a] == code[b]}
    assert {tuple(r) for r in rows("phonetic_blocks")} == sound
    unit = {e["ent_id"]: [x / (math.sqrt(sum(y * y for y in e["vec"])) or 1) for x in e["vec"]] for e in ents}
    dot = lambda a, b: sum(x * y for x, y in zip(a, b, strict=True))
    near = set()
    for a in unit:
        best = sorted(((-dot(unit[a], unit[b]), b) for b in unit if b != a))
        edge = best[19][0] if len(best) > 19 else 1
        near |= {((min(a, b), max(a, b)), c < edge - 1e-9) for c, b in best if c <= edge + 1e-9}
    sure, may = sound | {p for p, s in near if s}, sound | {p for p, _ in near}
    by, counts, loose = {e["ent_id"]: e for e in ents}, Counter(), 0

    def score(a, b):
        a, b = by[a], by[b]
        keys = [k for k in a["props"] if k in b["props"]]
        if any(k in resolve.DISCRIMINATORS and a["props"][k].lower() != b["props"][k].lower() for k in keys):
            return None
        agree = sum(a["props"][k].lower() == b["props"][k].lower() for k in keys)
        x, y = set(a["aliases"]), set(b["aliases"])
        v = {"name": S.jaro_winkler_py(a["name"], b["name"]), "cosine": max(0.0, dot(a["vec"], b["vec"])), "properties": min(1.0, max(0.0, (agree - 2 * (len(keys) - agree)) / max(1, len(keys)))),
             "phonetic": overlap(a["name"], b["name"]), "types": 1.0, "aliases": 1.0 if x & y else 0.0, "proximity": 1.0 if a["doc_id"] == b["doc_id"] else 0.0}
        return sum(resolve.RESOLVE_WEIGHTS[k] * v[k] for k in v)

    for p in may:
        z = score(*p)
        action = ("distinct", True) if z is None else ("auto_merge" if z >= 0.85 else "manual_review" if z >= 0.60 else "distinct", False)
        if p in sure and (z is None or min(abs(z - 0.85), abs(z - 0.60)) > 1e-9):
            counts[action] += 1
        else:
            loose += 1
    got = {(r["action"], r["conflict"]): r["n"] for r in rows("resolution_decisions")}
    assert all(counts[k] <= got.get(k, 0) <= counts[k] + loose for k in set(counts) | set(got))
    assert sum(got.values()) <= len(may) and loose <= 0.1 * len(may)
    layers = {r["layer"]: r["n"] for r in rows("resolution_review")}
    assert set(layers) <= {"rule", "embedding"} and layers["embedding"] >= counts["manual_review", False]


def test_cell_blocks(spark, small, rows):
    got = {(r["left_id"], r["right_id"]): r["cos"] for r in rows("vector_ivf")}
    exact = {(r["left_id"], r["right_id"]): r["cos"] for r in rows("vector_topk")}
    copies = {p for p, c in exact.items() if c >= 0.9}
    assert len(copies) >= 40 and len(copies & set(got)) >= 0.9 * len(copies)
    assert all(got[p] == pytest.approx(exact[p], abs=1e-4) for p in set(got) & set(exact))


def test_hashed_blocks(spark, small, rows):
    vecs = {r["vec_id"]: r["vec"] for r in views.near_duplicate_vectors(spark, small).collect()}
    cos = lambda a, b: sum(x * y for x, y in zip(a, b, strict=True)) / math.sqrt(sum(x * x for x in a) * sum(y * y for y in b))
    got = rows("vector_lsh")
    assert all(r["left_id"] < r["right_id"] and r["cos"] == pytest.approx(cos(vecs[r["left_id"]], vecs[r["right_id"]]), abs=1e-4) for r in got)
    copies = {(v - 1_000_000, v) for v in vecs if v >= 1_000_000}
    pairs = {(r["left_id"], r["right_id"]) for r in got}
    by = {r["method"]: r for r in rows("blocking_quality")}
    assert by["lsh"]["candidates"] == len(pairs) and by["lsh"]["kept"] == len(pairs & copies) >= 0.9 * len(copies)
    exact = {(r["left_id"], r["right_id"]) for r in rows("vector_topk")}
    assert by["exact"]["candidates"] == len(exact) and by["exact"]["kept"] == len(copies) and by["union"]["candidates"] == len(exact | pairs)


def test_word_error_rate_and_sketch(spark, small, rows):
    conv = {}
    for c in read(spark, small, "conversations"):
        conv.setdefault(c["conv_id"], []).append((c["turn"], c["role"], c["text"]))
    rates = {}
    for turns in conv.values():
        turns.sort()
        for (_, _, before), (_, role, text) in zip(turns, turns[1:], strict=False):
            if before is not None:
                gold = before.split()
                rates.setdefault(role, []).append(word_distance((text or "").split(), gold) / max(1, len(gold)))
    assert {r["role"]: (r["wer"], r["n"]) for r in rows("udaf_wer")} == {k: (pytest.approx(sum(v) / len(v), abs=1e-6), len(v)) for k, v in rates.items()}
    parts = {}
    for li in read(spark, small, "lineitem"):
        parts.setdefault(li["l_returnflag"], set()).add(li["l_partkey"])
    assert all(abs(r["parts"] - len(parts[r["l_returnflag"]])) <= 0.1 * len(parts[r["l_returnflag"]]) for r in rows("agg_approx_distinct"))


def test_stage_overhead(spark, small, rows):
    got = {r["stage"]: r for r in rows("stage_overhead")}
    assert set(got) == {"extraction", "aliases"} and got["extraction"]["chunks"] == len([r for r in Q["chunk_chars"](spark, small).collect() if r["o_end"] > 0])
    assert all(r["seconds"] > 0 for r in got.values())


def test_closure_has_no_depth_limit(spark):
    from kgrefine.operators.ontology import closure

    chain = spark.createDataFrame([(f"c{i}", f"c{i + 1}") for i in range(40)], "child string, parent string")
    got = {r["ancestor"]: r["hop"] for r in closure(chain).where("child = 'c0'").collect()}
    assert got == {f"c{i}": i for i in range(41)}
    with pytest.raises(RuntimeError):
        closure(chain, max_depth=5)


def test_hubs_are_joined_in_parts(spark):
    from kgrefine.plans.components import connected_components

    edges = spark.createDataFrame([(0, i) for i in range(1, 400)] + [(i, i + 1000) for i in range(1, 50)] + [(5000, 5001)], "u long, v long")
    got = {r["node"]: r["component"] for r in connected_components(edges, hub_rows=20).collect()}
    assert got == {**dict.fromkeys([*range(400), *range(1001, 1050)], 0), 5000: 5000, 5001: 5000}


def test_kafka_options():
    from kgrefine.sources.records import kafka_options

    o = kafka_options("h:9092", "t")
    assert o["kafka.session.timeout.ms"] == "300000" and o["maxOffsetsPerTrigger"] == "16" and o["subscribe"] == "t"
