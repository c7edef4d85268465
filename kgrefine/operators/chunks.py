"""Chunks and windows of long texts; primary and overlap ranges are kept apart."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT

from .pages import pack_pages


def limit_text(text: Column, most: int) -> Column:
    """The first ``most`` characters; 0 means no limit."""
    return text if most == 0 else F.substring(text, 1, most)


def limit_text_buggy(text: Column, most: int) -> Column:
    """The regression: the unlimited sentinel raised to 1 leaves one character."""
    return F.substring(text, 1, max(1, most))


def chunk_chars(docs: DataFrame, size: int = DEFAULT.chunk_chars, overlap: int = DEFAULT.chunk_overlap, annotate: bool = True,
                id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, chunk_no, p_start, p_end, o_start, o_end, header, text): fixed chunks, no shuffle.

    The overlap range [o_start, o_end) is what the chunk shows; the primary ranges [p_start, p_end)
    partition the text, so an item belongs to the chunk whose primary range holds it. A chunk that
    would show only what the last one shows is not made; an empty text has one empty chunk.
    """
    step = size - overlap
    n = F.length(F.coalesce(text_col, F.lit("")))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(text_col, F.lit("")).alias("body"), n.alias("n"))
    last = F.greatest(F.ceil((F.col("n") - overlap) / step).cast("int") - 1, F.lit(0))
    rows = rows.withColumn("last", last).withColumn("chunk_no", F.explode(F.sequence(F.lit(0), F.col("last"))))
    start = F.col("chunk_no") * step
    rows = rows.withColumn("o_start", start).withColumn("o_end", F.least(start + size, F.col("n")))
    rows = rows.withColumn("p_end", F.when(F.col("chunk_no") == F.col("last"), F.col("n")).otherwise(start + step))
    header = F.format_string("characters %d to %d, own part %d to %d", "o_start", "o_end", "o_start", "p_end") if annotate else F.lit(None).cast("string")
    return rows.select("doc_id", "chunk_no", F.col("o_start").alias("p_start"), "p_end", "o_start", "o_end", header.alias("header"),
                       F.substring("body", F.col("o_start") + 1, F.lit(size)).alias("text"))


def chunk_pages(pages: DataFrame, size: int = DEFAULT.chunk_pages, neighbour: int = DEFAULT.chunk_neighbours, id_col: str = "doc_id", page_col: str = "page_no") -> DataFrame:
    """(doc_id, chunk_no, page, primary): each chunk's own pages and its neighbours; pages count from 1, neighbours at most ``size``."""
    p = F.col(page_col).cast("int")
    rows = pages.select(F.col(id_col).alias("doc_id"), p.alias("page"))
    low = F.greatest(F.floor((F.col("page") - 1 - neighbour) / size), F.lit(0)).cast("int")
    high = F.floor((F.col("page") - 1 + neighbour) / size).cast("int")
    rows = rows.withColumn("chunk_no", F.explode(F.sequence(low, high)))
    rows = rows.withColumn("primary", F.floor((F.col("page") - 1) / size) == F.col("chunk_no"))
    own = rows.where("primary").select("doc_id", "chunk_no").distinct()
    return rows.join(own, ["doc_id", "chunk_no"], "left_semi").select("doc_id", "chunk_no", "page", "primary")


def windows_fixed(docs: DataFrame, size: int = DEFAULT.window_chars, overlap: int = DEFAULT.window_overlap, top: int = DEFAULT.window_count,
                  id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, win_no, w_start, w_end, text): at most ``top`` windows by position; top=1 with a large size is the single-vector variant."""
    chunks = chunk_chars(docs, size, overlap, False, id_col, text_col).where(F.col("chunk_no") < top)
    return chunks.select("doc_id", F.col("chunk_no").alias("win_no"), F.col("o_start").alias("w_start"), F.col("o_end").alias("w_end"), "text")


#: A capitalised word that does not open a sentence or line, after white space.
PROPER = r"[a-z,;] ([A-Z][a-z]+)"


def density(text: Column, lexicon: tuple[str, ...], weight: int = DEFAULT.density_weight) -> Column:
    """(characters of proper nouns + weight * hits of lexicon words) / length."""
    nouns = F.aggregate(F.regexp_extract_all(text, F.lit(PROPER), F.lit(1)), F.lit(0), lambda s, w: s + F.length(w))
    hits = F.regexp_count(F.lower(text), F.lit(r"(^|[^a-z])(" + "|".join(lexicon) + r")($|[^a-z])"))
    return F.when(F.length(text) > 0, (nouns + weight * hits) / F.length(text)).otherwise(F.lit(0.0))


def windows_dense(docs: DataFrame, lexicon: tuple[str, ...], size: int = DEFAULT.window_chars, top: int = DEFAULT.window_count,
                  id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, win_no, density, text): paragraphs packed to ``size``, the ``top`` densest of each document; ranking stays inside an array, no shuffle."""
    paragraphs = F.filter(F.split(F.coalesce(text_col, F.lit("")), "\n+"), lambda p: p != "")
    windows = F.transform(pack_pages(paragraphs, size), lambda w, i: F.struct((-density(w, lexicon)).alias("d"), i.alias("win_no"), w.alias("text")))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.explode(F.slice(F.array_sort(windows), 1, top)).alias("w"))
    return rows.select("doc_id", "w.win_no", (-F.col("w.d")).alias("density"), "w.text")
