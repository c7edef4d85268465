"""Aliases, text-mined variants, name similarity, context agreement and the decision surface."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT
from kgrefine.functions import strings as S


def expand_aliases(ents: DataFrame, name_col: str = "name", extra_plain_initial: bool = False) -> DataFrame:
    """Adds ``aliases``: for persons of two or more tokens the name, both initialled forms and both forms of initials; else the name alone."""
    t = F.split(F.trim(F.regexp_replace(name_col, r"\s+", " ")), " ")
    first, last = F.element_at(t, 1), F.element_at(t, -1)
    i, j = F.upper(F.substring(first, 1, 1)), F.upper(F.substring(last, 1, 1))
    more = [F.concat(i, F.lit(". "), last), F.concat(first, F.lit(" "), j, F.lit(".")), F.concat(i, j), F.concat(i, F.lit("."), j, F.lit("."))]
    if extra_plain_initial:
        more.append(F.concat(i, F.lit(" "), last))
    have = F.coalesce(F.col("aliases"), F.array().cast("array<string>")) if "aliases" in ents.columns else F.array().cast("array<string>")
    person = (F.col("type") == "PERSON") & (F.size(t) >= 2)
    every = F.array_union(F.array(F.col(name_col)), have)
    return ents.withColumn("aliases", F.when(person, F.array_union(every, F.array(*more))).otherwise(every))


def word_pairs(docs: DataFrame) -> DataFrame:
    """(doc_id, w1, w2): neighbouring words of each text, punctuation but a stop after an initial dropped."""
    words = F.filter(F.transform(F.split(F.coalesce("text", F.lit("")), r"\s+"), lambda w: F.regexp_replace(w, r"^[^\p{L}]+|[^\p{L}.]+$", "")), lambda w: w != "")
    rows = docs.select("doc_id", F.explode(F.array(words)).alias("w"))  # a generator keeps the array from being computed again for each use
    pairs = F.arrays_zip(F.slice("w", F.lit(1), F.greatest(F.size("w") - 1, F.lit(0))).alias("w1"), F.slice("w", F.lit(2), F.greatest(F.size("w") - 1, F.lit(0))).alias("w2"))
    return rows.select("doc_id", F.inline(pairs))


def mine_variants(ents: DataFrame, docs: DataFrame, tau: float = DEFAULT.variant_ratio) -> DataFrame:
    """(doc_id, ent_id, alias, rule, count): names of persons as they stand in their document's text.

    Two neighbouring words match a name when the second starts with the first three letters of its last
    token and the first is its first token's initial (``initial``) or alike to it at ``tau`` (``spelling``).
    The three letters are an exact block, so text and names meet in an equi-join, and pairs whose letters
    no name has stay out of its shuffle; the ratio is computed once for each distinct pair of words.
    """
    t = F.split(S.norm_name(F.col("name")), " ")
    names = ents.where("type = 'PERSON'").select("doc_id", "ent_id", S.norm_name(F.col("name")).alias("full"), t[0].alias("first"), F.element_at(t, -1).alias("last")).where(F.size(t) >= 2)
    names = names.withColumn("block", F.substring("last", 1, 3))
    pairs = word_pairs(docs).select("doc_id", "w1", "w2", F.lower("w1").alias("l1"), F.regexp_replace(F.lower("w2"), r"\.$", "").alias("l2"))
    blocks = names.select("block").distinct()
    blocks = F.broadcast(blocks) if blocks.count() <= 100_000 else blocks
    pairs = pairs.withColumn("block", F.substring("l2", 1, 3)).join(blocks, "block", "left_semi")
    near = pairs.join(names, ["doc_id", "block"]).where(F.concat_ws(" ", "l1", "l2") != F.col("full"))
    bare = F.regexp_replace("l1", r"\.$", "")
    near = near.withColumn("bare", bare).withColumn("initial", F.col("bare") == F.substring("first", 1, 1))
    ratio = near.where("not initial").select("bare", "first").distinct().withColumn("ratio", S.seq_ratio(F.col("bare"), F.col("first")))
    rows = near.join(ratio, ["bare", "first"], "left")
    rule = F.when(F.col("initial"), "initial").when(F.col("ratio") >= tau, "spelling")
    alias = F.concat_ws(" ", "w1", F.regexp_replace("w2", r"\.$", ""))
    return rows.withColumn("rule", rule).where("rule is not null").groupBy("doc_id", "ent_id", alias.alias("alias"), "rule").agg(F.count("*").alias("count"))


def alias_search(queries: DataFrame, ents: DataFrame) -> DataFrame:
    """(query_id, ent_id): entities with an alias equal to the query, case and white space folded."""
    a = ents.select("ent_id", F.explode("aliases").alias("q")).select("ent_id", S.norm_name(F.col("q")).alias("q")).distinct()
    return queries.select("query_id", S.norm_name(F.col("query")).alias("q")).join(a, "q").select("query_id", "ent_id").distinct()


WEIGHTS = {"jaro_winkler": 0.30, "phonetic": 0.25, "tokens": 0.20, "abbreviation": 0.15, "cultural": 0.10}


def name_similarity(pairs: DataFrame, scorer: str = "composite", weights: dict[str, float] = WEIGHTS, boost: bool = True, abbreviation: str = "fixed") -> DataFrame:
    """Adds ``score``, ``reason`` and (composite) the signals to rows with ``name_a`` and ``name_b``.

    ``composite``: weighted signals; a signal of 0.90 or more lifts a score under 0.8 of it to 0.8 of
    it. ``tiered``: gender pair 0.85, abbreviation 0.92, else the sequence ratio. Equal normalised
    names score 1, reason ``exact``, in both. Expensive kernels run on distinct pairs of names and the
    result is joined back.
    """
    x, y = S.norm_name(F.col("a")), S.norm_name(F.col("b"))
    key = pairs.select(S.norm_name(F.col("name_a")).alias("a"), S.norm_name(F.col("name_b")).alias("b")).distinct()
    if scorer == "tiered":
        score = F.when(S.gender_pair(x, y), 0.85).when(S.abbrev_signal(x, y, abbreviation) == 1, 0.92).otherwise(F.col("ratio"))
        why = F.when(S.gender_pair(x, y), "gender").when(S.abbrev_signal(x, y, abbreviation) == 1, "abbreviation").otherwise("ratio")
        done = key.withColumn("ratio", S.seq_ratio(F.col("a"), F.col("b"))).withColumn("score", score).withColumn("reason", why)
    else:
        done = (key.withColumn("jaro_winkler", S.jaro_winkler(F.col("a"), F.col("b"))).withColumn("a1", S.phonetic(F.col("a"))).withColumn("a2", S.phonetic(F.col("a"), True))
                .withColumn("b1", S.phonetic(F.col("b"))).withColumn("b2", S.phonetic(F.col("b"), True)))
        done = (done.withColumn("phonetic", S.phonetic_overlap(F.col("a1"), F.col("a2"), F.col("b1"), F.col("b2"))).withColumn("tokens", S.token_jaccard(x, y))
                .withColumn("abbreviation", S.abbrev_signal(x, y, abbreviation)).withColumn("cultural", S.cultural_signal(x, y)).drop("a1", "a2", "b1", "b2"))
        total = sum((F.col(k) * w for k, w in weights.items()), F.lit(0.0))
        top = F.greatest(*[F.col(k) for k in weights])
        score = F.when((top >= 0.90) & (total < 0.8 * top), 0.8 * top).otherwise(total) if boost else total
        order = sorted(weights, key=lambda k: -weights[k])
        why = F.array_max(F.array(*[F.struct(F.col(k).alias("v"), F.lit(-i).alias("i"), F.lit(k).alias("k")) for i, k in enumerate(order)]))["k"]
        done = done.withColumn("score", score).withColumn("reason", why)
    same = F.col("a") == F.col("b")
    done = done.withColumn("score", F.when(same, 1.0).otherwise(F.col("score"))).withColumn("reason", F.when(same, "exact").otherwise(F.col("reason")))
    keyed = pairs.withColumn("a", S.norm_name(F.col("name_a"))).withColumn("b", S.norm_name(F.col("name_b")))
    return keyed.join(done, ["a", "b"]).drop("a", "b")


def context_agreement(pairs: DataFrame, keys: tuple[str, ...] = ("role", "org", "loc")) -> DataFrame:
    """Adds ``delta`` (1 unless a shared attribute conflicts), ``n_shared`` and ``conflicts`` to rows with key_a and key_b columns; null never conflicts."""
    a, b = (lambda k: F.lower(F.col(f"{k}_a"))), (lambda k: F.lower(F.col(f"{k}_b")))
    shared = sum((F.when(a(k).isNotNull() & b(k).isNotNull(), 1).otherwise(0) for k in keys), F.lit(0))
    clash = sum((F.when(a(k) != b(k), 1).otherwise(0) for k in keys), F.lit(0))
    return pairs.withColumn("n_shared", shared).withColumn("conflicts", clash).withColumn("delta", F.when(F.col("conflicts") == 0, 1).otherwise(0))


def decide_rule(pairs: DataFrame, auto: float = DEFAULT.name_auto, review: float = DEFAULT.name_review, least: float = DEFAULT.name_candidate,
                require_evidence: bool = False) -> DataFrame:
    """Candidates (score at least ``least``) with ``action``, ``verdict`` and ``confidence``.

    Only the top band with agreeing context merges; the next is reviewed, all else kept apart. Without
    a shared attribute the confidence drops a level, or the merge becomes a review if ``require_evidence``.
    """
    agree, bare = F.col("delta") == 1, F.col("n_shared") == 0
    action = F.when(agree & (F.col("score") > auto), F.when(bare & F.lit(require_evidence), "manual_review").otherwise("auto_merge"))
    action = action.when(agree & (F.col("score") > review), "manual_review").otherwise("different_contexts")
    rows = pairs.where(F.col("score") >= least).withColumn("action", action)
    verdict = F.when(F.col("action") == "auto_merge", "same").when(F.col("action") == "manual_review", "uncertain").otherwise("different")
    level = F.when(F.col("action") == "auto_merge", F.when(bare, "medium").otherwise("high")).when(F.col("action") == "manual_review", F.when(bare, "low").otherwise("medium")).otherwise("high")
    return rows.withColumn("verdict", verdict).withColumn("confidence", level)


def candidate_pairs(ents: DataFrame, strategy: str = "blocked", scope: tuple[str, ...] = ("doc_id", "type"), keep: tuple[str, ...] = ("name",)) -> DataFrame:
    """(left_id, right_id, scope, key_a, key_b): pairs of one scope with left_id < right_id.

    ``all`` joins a scope with itself (a document's entities). ``blocked`` asks for a shared key as well,
    the first three letters of the last token or the phonetic code of the whole name. Both sides are whole
    tables that look small in compressed statistics, so they are sorted and merged, never broadcast.
    """
    def side(rows, i, end, *more):
        return rows.select(*scope, F.col("ent_id").alias(i), *[F.col(k).alias(f"{k}_{end}") for k in keep], *more)

    if strategy == "all":
        return side(ents, "left_id", "a").hint("merge").join(side(ents, "right_id", "b"), list(scope)).where("left_id < right_id")
    t = F.split(S.norm_name(F.col("name")), " ")
    blocks = F.array(F.concat(F.lit("l:"), F.substring(F.element_at(t, -1), 1, 3)), F.concat(F.lit("p:"), F.array_join(F.array_sort(S.phonetic(F.col("name"))), "-")))
    keyed = ents.withColumn("__blocks", blocks).withColumn("__block", F.explode("__blocks"))
    met = side(keyed, "left_id", "a", "__block", F.col("__blocks").alias("__l")).hint("merge").join(side(keyed, "right_id", "b", "__block", F.col("__blocks").alias("__r")), [*scope, "__block"])
    # a pair of several shared blocks counts in the first of them only, so that no distinct is needed
    once = F.col("__block") == F.array_min(F.array_intersect("__l", "__r"))
    return met.where("left_id < right_id").where(once).drop("__block", "__l", "__r")


#: Property names that tell a role, an organisation or a place.
CONTEXT_KEYS = {"role": ("role", "position", "title"), "org": ("org", "organisation", "organization", "employer"), "loc": ("loc", "location", "place", "city")}


def context_attributes(ents: DataFrame, keys: dict[str, tuple[str, ...]] = CONTEXT_KEYS) -> DataFrame:
    """(ent_id, type, value, confidence, source_text): role, organisation and place from the property map; the first synonym with a value counts."""
    parts = [F.struct(F.lit(k).alias("type"), F.coalesce(*[F.col("props")[n] for n in ns]).alias("value"), F.lit(1.0).alias("confidence"), F.coalesce(*[F.when(F.col("props")[n].isNotNull(), n) for n in ns]).alias("source_text")) for k, ns in keys.items()]
    return ents.select("ent_id", F.inline(F.array(*parts))).where("value is not null")


def alias_occurrences(mined: DataFrame, docs: DataFrame, width: int = 30, most: int = 3) -> DataFrame:
    """Adds up to ``most`` snippets, ``width`` characters on each side of the alias, to mined aliases of a document."""
    near = F.regexp_extract_all(F.col("text"), F.concat(F.lit("(?is).{0,%d}" % width), F.regexp_replace("alias", r"([^A-Za-z0-9])", r"\\$1"), F.lit(".{0,%d}" % width)), F.lit(0))
    return mined.join(docs.select("doc_id", "text"), "doc_id").withColumn("snippets", F.slice(near, 1, most)).drop("text")


def fingerprint(ents: DataFrame, core: Column, context: tuple[str, ...] = ("role", "org", "loc")) -> DataFrame:
    """Adds ``fingerprint``: a digest of type, core name and the context in a fixed order."""
    parts = [F.coalesce(F.lower(F.col(k)), F.lit("")) for k in context]
    return ents.withColumn("fingerprint", F.sha2(F.concat_ws("|", F.col("type"), F.lower(core), *parts), 256))


def dedup_status(ents: DataFrame, decided: DataFrame) -> DataFrame:
    """Adds ``dedup_status``: the strongest action that an entity's pairs met, ``confirmed_unique`` without any."""
    rank = F.when(F.col("action") == "auto_merge", 3).when(F.col("action") == "manual_review", 2).otherwise(1)
    ends = decided.select("doc_id", F.explode(F.array("left_id", "right_id")).alias("ent_id"), rank.alias("r")).groupBy("doc_id", "ent_id").agg(F.max("r").alias("r"))
    name = F.when(F.col("r") == 3, "merged").when(F.col("r") == 2, "review").when(F.col("r") == 1, "candidate").otherwise("confirmed_unique")
    return ents.join(ends, ["doc_id", "ent_id"], "left").withColumn("dedup_status", name).drop("r")


def enhance(ents: DataFrame, docs: DataFrame | None = None) -> tuple[DataFrame, DataFrame | None, DataFrame]:
    """(entities with aliases, mined variants or None, decided pairs): expansion, mining, detection; mining is left out without text."""
    with_aliases = expand_aliases(ents)
    mined = mine_variants(ents, docs) if docs is not None else None
    keep = tuple(k for k in ("name", "role", "org", "loc") if k in ents.columns)
    pairs = candidate_pairs(ents.where("type = 'PERSON'"), keep=keep)
    decided = decide_rule(context_agreement(name_similarity(pairs), tuple(k for k in keep if k != "name")))
    return with_aliases, mined, decided
