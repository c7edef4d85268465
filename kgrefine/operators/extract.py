"""The boundary to extraction models: providers, recovery of their answers, retries, failures, second pass."""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ANSWER = "doc_id long, chunk_no int, answer string"


def rule_provider(limit: int = 0) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """A deterministic stand-in: capitalised two-word names of a chunk, at most ``limit`` (0: all), as a fenced JSON answer."""

    def run(batches):
        for pdf in batches:
            out = []
            for text in pdf["text"]:
                names = list(dict.fromkeys(re.findall(r"[A-Z][a-z]+ [A-Z][a-z]+", text or "")))
                names = names[:limit] if limit else names
                out.append("```json\n" + json.dumps({"entities": [{"name": n, "type": "PERSON"} for n in names]}) + "\n```")
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "chunk_no": pdf["chunk_no"], "answer": out})

    return run


def replay_provider(answers: dict[tuple[int, int], str]) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Recorded answers by (doc_id, chunk_no); others are null."""

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "chunk_no": pdf["chunk_no"], "answer": [answers.get((int(d), int(c))) for d, c in zip(pdf["doc_id"], pdf["chunk_no"], strict=True)]})

    return run


STATEMENT = re.compile(r"^(?P<src>.+?) -- (?P<type>.+?) -- (?P<dst>.+?) \((?P<year>[^)]*)\)\.$", re.MULTILINE)


def statement_provider(limit: int = 0) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """A deterministic stand-in for text of lines ``name -- label -- name (year).``: both names with their places and the relation; an answer ends after ``limit`` lines (0: all), as a model's does at its token limit."""

    def run(batches):
        for pdf in batches:
            out = []
            for text in pdf["text"]:
                found = list(STATEMENT.finditer(text or ""))
                found = found[:limit] if limit else found
                ents = [{"name": m[end], "type": "PERSON", "start": m.start(end)} for m in found for end in ("src", "dst")]
                out.append("```json\n" + json.dumps({"entities": ents, "relations": [m.groupdict() for m in found]}) + "\n```")
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "chunk_no": pdf["chunk_no"], "answer": out})

    return run


PROVIDERS = {"rule": rule_provider, "replay": replay_provider, "statement": statement_provider}


def get_provider(name: str, **opts):
    """A provider by name; a served model registers its own maker in ``PROVIDERS`` with time-outs and retry budget as options."""
    return PROVIDERS[name](**opts)


def run_provider(chunks: DataFrame, provider) -> DataFrame:
    """(doc_id, chunk_no, answer) for chunks (doc_id, chunk_no, text)."""
    return chunks.select(F.col("doc_id").cast("long"), F.col("chunk_no").cast("int"), "text").mapInPandas(provider, ANSWER)


def complete_json(text: str | None) -> str | None:
    """The longest JSON value that a cut-off answer still holds: complete members stay, open brackets are closed."""
    if not text:
        return None
    start = min((i for i in (text.find("{"), text.find("[")) if i >= 0), default=-1)
    if start < 0:
        return None
    stack, quoted, escaped, cuts = [], False, False, []
    for i in range(start, len(text)):
        c = text[i]
        if quoted:
            escaped, quoted = (not escaped and c == "\\"), not (c == '"' and not escaped)
            continue
        if c == '"':
            quoted = True
        elif c in "{[":
            stack.append("}" if c == "{" else "]")
            if c == "[" or len(stack) == 1:  # an object without a complete member is left out
                cuts.append((i + 1, tuple(stack)))
        elif c in "}]":
            if not stack or stack[-1] != c:
                break
            stack.pop()
            cuts.append((i + 1, tuple(stack)))
            if not stack:
                break
        elif c == ",":
            cuts.append((i, tuple(stack)))
    for end, open_ in reversed(cuts):
        whole = text[start:end] + "".join(reversed(open_))
        try:
            json.loads(whole)
            return whole
        except ValueError:
            continue
    return None


def fenced(answer: Column) -> tuple[Column, Column]:
    """(body, stage) of an answer: a closed fence, an open fence, or raw JSON within prose."""
    closed = F.regexp_extract(answer, r"(?s)```(?:json)?\s*(.*?)```", 1)
    opened = F.regexp_extract(answer, r"(?s)```(?:json)?\s*(.*)$", 1)
    raw = F.regexp_extract(answer, r"(?s)([\{\[].*)$", 1)
    body = F.when(closed != "", closed).when(opened != "", opened).otherwise(F.nullif(raw, F.lit("")))
    return body, F.when(closed != "", "closed_fence").when(opened != "", "open_fence").when(raw != "", "raw").otherwise("none")


def recover_json(answers: DataFrame, col: str = "answer") -> DataFrame:
    """Adds ``json`` (complete, or null) and ``stage``; only bodies that need it are closed by hand in Arrow batches."""
    import pyarrow as pa

    mend = F.arrow_udf(lambda a: pa.array([complete_json(x) for x in a.to_pylist()], pa.string()), "string")
    body, stage = fenced(F.col(col))
    return answers.withColumn("stage", stage).withColumn("json", mend(body))


def parse_entities(recovered: DataFrame) -> DataFrame:
    """(doc_id, chunk_no, name, type) from recovered answers."""
    kind = "struct<entities:array<struct<name:string,type:string>>>"
    rows = recovered.select("doc_id", "chunk_no", F.from_json("json", kind).alias("j"))
    return rows.select("doc_id", "chunk_no", F.explode("j.entities").alias("e")).select("doc_id", "chunk_no", "e.name", "e.type")


def parse_spans(recovered: DataFrame) -> DataFrame:
    """(doc_id, chunk_no, name, type, start) of every mention, repeats kept."""
    rows = recovered.select("doc_id", "chunk_no", F.from_json("json", "struct<entities:array<struct<name:string,type:string,start:int>>>").alias("j"))
    return rows.select("doc_id", "chunk_no", F.inline("j.entities"))


def parse_relations(recovered: DataFrame) -> DataFrame:
    """(doc_id, chunk_no, src, dst, rel_type, quals, ord) from recovered answers; ``ord`` is the place in the document."""
    rows = recovered.select("doc_id", "chunk_no", F.from_json("json", "struct<relations:array<struct<src:string,type:string,dst:string,year:string>>>").alias("j"))
    rows = rows.select("doc_id", "chunk_no", F.posexplode("j.relations").alias("at", "r"))
    return rows.select("doc_id", "chunk_no", "r.src", "r.dst", F.col("r.type").alias("rel_type"), F.create_map(F.lit("year"), F.col("r.year")).alias("quals"), (F.col("chunk_no").cast("long") * 1_000_000 + F.col("at")).alias("ord"))


def validate(recovered: DataFrame, required: str = "entities") -> tuple[DataFrame, DataFrame]:
    """(rows whose JSON has the required member, the others)."""
    ok = F.coalesce(F.get_json_object("json", f"$.{required}").isNotNull(), F.lit(False))
    return recovered.where(ok), recovered.where(~ok)


def retry_loop(chunks: DataFrame, provider, budget: int = 2, required: str = "entities") -> tuple[DataFrame, DataFrame]:
    """(good answers, failed chunks): chunks without a valid answer are asked again, at most ``budget`` times; each round is written, so a model is called once for each try."""
    from kgrefine.plans.scratch import written

    good, left = None, chunks
    for attempt in range(1, budget + 2):
        got = written(recover_json(run_provider(left, provider)).withColumn("attempt", F.lit(attempt)), "answers")
        ok, bad = validate(got, required)
        good = ok if good is None else good.unionByName(ok)
        left = written(left.join(bad.select("doc_id", "chunk_no"), ["doc_id", "chunk_no"], "left_semi"), "retry")
        if not left.limit(1).count():
            break
    return good, left


def second_pass(catalog: DataFrame, chunks: DataFrame) -> DataFrame:
    """(doc_id, chunk_no, src, dst): catalogue names of a document that stand together in a chunk, the offline stand-in for the second model pass."""
    found = chunks.select("doc_id", "chunk_no", "text").join(catalog.select("doc_id", "ent_id", "name"), "doc_id").where(F.contains(F.lower("text"), F.lower("name"))).select("doc_id", "chunk_no", "ent_id")
    return found.withColumnRenamed("ent_id", "src").join(found.withColumnRenamed("ent_id", "dst"), ["doc_id", "chunk_no"]).where("src < dst")


def append_failures(failures: DataFrame, path: str) -> None:
    """Failed chunks as JSON lines, appended; a task's file appears whole or not at all."""
    failures.write.mode("append").json(path)


def rerun_from_failures(corpus: DataFrame, log: DataFrame, keys: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The corpus rows that the log names."""
    return corpus.join(log.select(*keys).distinct(), list(keys), "left_semi")


def empty_results(ids: DataFrame, results: DataFrame) -> DataFrame:
    """A result for every id: documents without one get empty arrays."""
    arrays = [c for c, t in results.dtypes if t.startswith("array")]
    out = ids.join(results, "doc_id", "left")
    return out.withColumns({c: F.coalesce(F.col(c), F.array().cast(dict(results.dtypes)[c])) for c in arrays})
