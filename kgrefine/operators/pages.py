"""Page classification from structural signals, document routing, and virtual pages."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgrefine.config import DEFAULT


def html_signals(pages: DataFrame) -> DataFrame:
    """(page_id, chars, tags, list_items, markup_share) from real markup, without a shuffle."""
    bare = F.regexp_replace("html", "<[^>]*>", "")
    return pages.select("page_id", F.length(bare).cast("long").alias("chars"), F.regexp_count("html", F.lit("<[^>]+>")).cast("long").alias("tags"),
                        F.regexp_count("html", F.lit("<li>")).cast("long").alias("list_items"),
                        F.round(1 - F.length(bare) / F.length("html"), 6).alias("markup_share"))


def classify_page(signals: DataFrame, cover: float = DEFAULT.page_cover, chars: int = DEFAULT.page_chars, drawings: int = DEFAULT.page_drawings,
                  disable: frozenset | set = frozenset()) -> DataFrame:
    """Adds ``label`` (text, ocr, skip) and ``deciding``; the first rule that holds decides.

    Signals: area, img_block, img_xref, n_xref, chars, drawings. The second image cover counts only
    where the page refers to images at all. ``disable`` drops the rules ``draw`` or ``xref``.
    """
    xref = F.when(F.col("n_xref") > 0, F.col("img_xref")).otherwise(F.lit(0.0))
    rules: list[tuple[str, Column, str]] = [("area", F.col("area") == 0, "skip"), ("image_block", F.col("img_block") > cover, "ocr")]
    if "xref" not in disable:
        rules.append(("image_xref", xref > cover, "ocr"))
    rules.append(("chars", F.col("chars") > chars, "text"))
    if "draw" not in disable:
        rules.append(("drawings", F.col("drawings") > drawings, "ocr"))
    rules.append(("few_chars", F.col("chars") > 0, "text"))
    label, why = F.lit("skip"), F.lit("empty")
    for name, holds, value in reversed(rules):
        label, why = F.when(holds, value).otherwise(label), F.when(holds, name).otherwise(why)
    return signals.withColumn("label", label).withColumn("deciding", why)


def legacy_route(pages: DataFrame, filled: float = 0.5, mean_chars: int = DEFAULT.page_chars) -> DataFrame:
    """(doc_id, legacy): the whole-document guess from the share of pages with characters and their mean number."""
    good = (F.avg((F.col("chars") > 0).cast("double")) >= filled) & (F.avg("chars") >= mean_chars)
    return pages.groupBy("doc_id").agg(F.when(good, "text").otherwise("ocr").alias("legacy"))


def route_document(labelled: DataFrame, hi: float = DEFAULT.route_text, lo: float = DEFAULT.route_ocr, filled: float = 0.5, mean_chars: int = DEFAULT.page_chars) -> DataFrame:
    """(doc_id, n_text, n_ocr, n_skip, route, fallback): by the share of text pages among usable ones, bounds inclusive.

    Without a usable page the legacy guess of the same aggregate decides. One hash aggregate by document.
    """
    count = lambda v: F.count_if(F.col("label") == v)
    good = (F.avg((F.col("chars") > 0).cast("double")) >= filled) & (F.avg("chars") >= mean_chars)
    rows = labelled.groupBy("doc_id").agg(count("text").alias("n_text"), count("ocr").alias("n_ocr"), count("skip").alias("n_skip"), good.alias("good"))
    usable = F.col("n_text") + F.col("n_ocr")
    share = F.when(usable > 0, F.col("n_text") / usable)
    route = F.when(usable == 0, F.when(F.col("good"), "text").otherwise("ocr")).when(share >= hi, "text").when(share <= lo, "ocr").otherwise("mixed")
    return rows.select("doc_id", "n_text", "n_ocr", "n_skip", route.alias("route"), (usable == 0).alias("fallback"))


def split_mixed(labelled: DataFrame, text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(pages with text kept and the others blanked, pages to be read by vision); skipped pages keep their place."""
    kept = labelled.withColumn(text_col, F.when(F.col("label") == "text", F.col(text_col)).otherwise(F.lit("")))
    return kept, labelled.where("label = 'ocr'")


def merge_paths(kept: DataFrame, seen: DataFrame, text_col: str = "text") -> DataFrame:
    """Pages in their places with the vision text where there is one; ``seen`` holds (doc_id, page_no, vision_text)."""
    both = kept.join(seen.select("doc_id", "page_no", "vision_text"), ["doc_id", "page_no"], "left")
    return both.withColumn(text_col, F.coalesce("vision_text", text_col)).drop("vision_text")


def pack_pages(blocks: Column, size: int) -> Column:
    """Packs an array of strings, in order, into an array of pages of at most ``size`` characters (one longer block is a page)."""
    empty = F.struct(F.array().cast("array<string>").alias("done"), F.lit("").alias("open"))

    def add(acc: Column, block: Column) -> Column:
        fits = (acc["open"] == "") | (F.length(acc["open"]) + F.length(block) + 1 <= size)
        joined = F.when(acc["open"] == "", block).otherwise(F.concat(acc["open"], F.lit("\n"), block))
        return F.when(fits, F.struct(acc["done"].alias("done"), joined.alias("open"))).otherwise(
            F.struct(F.concat(acc["done"], F.array(acc["open"])).alias("done"), block.alias("open")))

    return F.aggregate(blocks, empty, add, lambda acc: F.when(acc["open"] == "", acc["done"]).otherwise(F.concat(acc["done"], F.array(acc["open"]))))


def virtual_pages(pages: DataFrame, size: int = DEFAULT.virtual_page_chars, floor: int = DEFAULT.virtual_page_floor) -> DataFrame:
    """(page_id, virtual_no, text, image_only): flowing markup cut into pages; list items and cells become rows of their own.

    A page under ``floor`` characters is flagged for OCR.
    """
    rows = F.regexp_replace("html", r"(?i)</(li|p|h1|tr|div|footer)>", "\n")
    bare = F.regexp_replace(F.regexp_replace(rows, r"(?i)</t[dh]>\s*<t[dh]>", " | "), "<[^>]*>", "")
    blocks = F.filter(F.transform(F.split(bare, "\n+"), lambda b: F.trim(b)), lambda b: b != "")
    out = pages.select("page_id", F.posexplode(pack_pages(blocks, size)).alias("virtual_no", "text"))
    return out.withColumn("image_only", F.length("text") < floor)


def slide_pages(slides: DataFrame) -> DataFrame:
    """(doc_id, page_no, text) from slides (doc_id, slide_no, title, body array, tables array, notes): one page each, title first, notes last."""
    parts = F.array(F.col("title"), F.array_join("body", "\n"), F.array_join("tables", "\n"), F.col("notes"))
    return slides.select("doc_id", F.col("slide_no").alias("page_no"), F.array_join(F.filter(parts, lambda p: p.isNotNull() & (p != "")), "\n").alias("text"))


def union_transcripts(passes: DataFrame) -> DataFrame:
    """(page_id, tokens): the union of token sets of several passes (page_id, pass, text) over a page."""
    token = F.explode(F.split(F.lower("text"), r"\s+")).alias("token")
    return passes.select("page_id", token).where("token <> ''").distinct().groupBy("page_id").agg(F.count("*").alias("tokens"))
