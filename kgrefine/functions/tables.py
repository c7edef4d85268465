"""Functions registered for SQL: table functions and name functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="chunk_no int, chunk string")
class Chunks:
    """Fixed chunks of a text; an empty text has one."""

    def eval(self, text: str, size: int):
        text = text or ""
        for n, at in enumerate(range(0, max(1, len(text)), size)):
            yield n, text[at : at + size]


@udtf(returnType="term string")
class Terms:
    """Capitalised phrases and abbreviations of a text."""

    def eval(self, text: str):
        import re

        for term in dict.fromkeys(re.findall(r"[A-Z][a-z]+(?: [A-Z][a-z]+)+|[A-Z]{2,}", text or "")):
            yield (term,)


@udtf(returnType="body string")
class LenientJson:
    """The longest complete JSON value of a text, if any."""

    def eval(self, text: str):
        from kgrefine.operators.extract import complete_json

        body = complete_json(text)
        if body is not None:
            yield (body,)


def register(spark: SparkSession) -> None:
    """kg_chunks, kg_terms and kg_json as table functions; kg_seq_ratio, kg_jaro_winkler and kg_metaphone as scalar ones."""
    from . import strings

    for name, cls in (("kg_chunks", Chunks), ("kg_terms", Terms), ("kg_json", LenientJson)):
        spark.udtf.register(name, cls)
    spark.udf.register("kg_seq_ratio", strings.seq_ratio_py, "double")
    spark.udf.register("kg_jaro_winkler", strings.jaro_winkler_py, "double")
    spark.udf.register("kg_metaphone", lambda w: strings.double_metaphone_py(w or "")[0], "string")
