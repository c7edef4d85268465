"""Document fingerprints by winnowing word grams. DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.plans.scratch import written

#: Low half of a packed gram: places count down from here, so that the smaller value is the place further right.
_PLACES = 0x7FFFFFFF
#: The polynomial's modulus, a prime under 2**30, and its base. Grams of characters have 2**30 added.
PRIME, BASE, CHARS = 1_073_741_789, 1_000_003, 1 << 30


def let(value: Column, use) -> Column:
    """``use(value)`` with ``value`` computed once, however often ``use`` names it."""
    return F.element_at(F.transform(F.array(value), use), 1)


def rolled(units: Column, k: int) -> Column:
    """array<long>: the polynomial hash of every run of ``k`` units (an array of strings) next to each other.

    Each unit is hashed once. The hash of a run is that of the run one shorter, times the base, plus the
    next unit, modulo a prime; this is the value that a hash rolled along the text takes at each place.
    """
    def longer(w: Column, run: Column, n: int) -> Column:
        step = F.zip_with(run, F.slice(w, F.lit(n + 1), F.greatest(F.size(w), F.lit(1))), lambda a, b: (a * BASE + b) % PRIME)
        return run if n == k else let(step, lambda r: longer(w, r, n + 1))

    once = F.transform(units, lambda u: F.pmod(F.xxhash64(u), F.lit(PRIME)))
    return let(once, lambda w: F.slice(longer(w, w, 1), F.lit(1), F.greatest(F.size(w) - (k - 1), F.lit(0))))


def chosen_of(hashed: Column, window: int) -> Column:
    """The smallest hash of every ``window`` grams next to each other, the rightmost of equal ones, packed with its place; each gram once."""
    steps = int(math.log2(window))
    if 2**steps != window:
        raise ValueError("window must be a power of two")
    packed = F.transform(hashed, lambda h, i: F.shiftleft(h, 32) + (F.lit(_PLACES) - i))

    def halved(mins: Column, s: int) -> Column:
        return F.zip_with(mins, F.slice(mins, F.lit(2**s + 1), F.greatest(F.size(mins), F.lit(1))), lambda a, b: F.least(a, b))

    def doubled(mins: Column, s: int) -> Column:
        return mins if s == steps else let(halved(mins, s), lambda m: doubled(m, s + 1))

    return let(packed, lambda p: let(doubled(p, 0), lambda m: F.array_distinct(F.slice(m, F.lit(1), F.greatest(F.size(p) - (window - 1), F.lit(1))))))


def winnow(text: Column, k: int = 3, window: int = 4, few: int = 16, char_k: int = 8, char_window: int = 8) -> Column:
    """array<long>: the chosen grams, each packed as 31 bits of hash over its mirrored place.

    Units are lower-case words, so white space does not matter. Every ``window`` runs of ``k`` words next
    to each other give their smallest hash, the rightmost of equal ones; a gram chosen by several windows
    stands once. Packing makes "smallest, then rightmost" one ``least``, and doubling builds the window
    minimum in log2(window) passes over the array. Two texts that share window + k - 1 words in a row
    share a chosen gram. A text of fewer than ``few`` words gets grams of ``char_k`` characters of its
    words joined by one space as well (the whole, if it is shorter), with hashes from 2**30 on and places
    counted in characters: text without spaces has few words however long it is. Windows must be powers
    of two. A null or blank text has none.
    """
    none = F.array().cast("array<long>")

    def of_words(w: Column) -> Column:
        return F.when(F.size(w) >= k, chosen_of(rolled(w, k), window)).otherwise(none)

    def of_chars(w: Column) -> Column:
        def grams(line: Column) -> Column:
            short = F.array(F.pmod(F.xxhash64(line), F.lit(PRIME)))
            return F.when(F.length(line) < char_k, short).otherwise(rolled(F.filter(F.split(line, ""), lambda c: c != ""), char_k))

        hashed = let(F.array_join(w, " "), grams)
        return chosen_of(F.transform(hashed, lambda h: h + CHARS), char_window)

    def both(w: Column) -> Column:
        return F.when(F.size(w) == 0, none).when(F.size(w) < few, F.concat(of_words(w), of_chars(w))).otherwise(of_words(w))

    return let(F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"\S+"), F.lit(0)), both)


def hashes(chosen: Column) -> Column:
    return F.array_distinct(F.transform(chosen, lambda p: F.shiftright(p, 32)))


def places(chosen: Column) -> Column:
    """Place of each chosen gram, counted from 0 in words or, for a gram of characters, in characters."""
    return F.transform(chosen, lambda p: F.lit(_PLACES) - p.bitwiseAND(F.lit(0xFFFFFFFF)))


def likeness(a: Column, b: Column) -> Column:
    """Shared over all hashes of two hash sets; 1 for two empty ones."""
    def share(x: Column, y: Column) -> Column:
        return let(F.size(F.array_intersect(x, y)), lambda n: F.when(F.size(x) + F.size(y) == 0, F.lit(1.0)).otherwise(n / (F.size(x) + F.size(y) - n)))

    return let(a, lambda x: let(b, lambda y: share(x, y)))


def digest(chosen: Column) -> Column:
    return F.md5(F.concat_ws(",", F.transform(chosen, lambda p: p.cast("string"))))


def id_cells(ids: DataFrame, rows_per_cell: int) -> tuple[int, int, list[DataFrame]]:
    """(low, width, splits) that cut (half long) into ranges of about ``rows_per_cell`` rows.

    The whole range is cut into equal parts; a part with over four times the rows is cut again between
    its own ends, until none is left that can be cut. ``splits`` are tables (cell, least, wide), one for
    each such turn; a cell is named by its lower end. Ids far from the others cost a turn, not balance.
    """
    low, high, n = ids.agg(F.min("half"), F.max("half"), F.count("*")).first()
    low, high = low or 0, high or 0
    width, splits = max(1, (high - low) // max(1, math.ceil(n / rows_per_cell)) + 1), []
    while n > 4 * rows_per_cell:
        cells = celled(ids, low, width, splits).groupBy("cell").agg(F.count("*").alias("n"), F.min("half").alias("least"), F.max("half").alias("most"))
        cells = cells.where((F.col("n") > 4 * rows_per_cell) & (F.col("most") > F.col("least")))
        wide = F.expr(f"(most - least) div cast(ceil(n / {rows_per_cell}) as long) + 1")
        over = written(cells.select("cell", "least", wide.alias("wide")), "cells")
        if not over.count():
            break
        splits = [*splits, over]
    return low, width, splits


def celled(rows: DataFrame, low: int, width: int, splits: list[DataFrame], broadcast_rows: int = 1_000_000) -> DataFrame:
    """Adds ``cell`` to rows with ``half``; a table of splits is broadcast only if counted at ``broadcast_rows`` rows or fewer."""
    rows = rows.withColumn("cell", F.expr(f"(half - ({low}L)) div {width}L * {width}L + ({low}L)"))
    for over in splits:
        small = F.broadcast(over) if over.count() <= broadcast_rows else over
        cell = F.coalesce(F.expr("(half - least) div wide * wide + least"), "cell")
        rows = rows.join(small.withColumnRenamed("cell", "whole"), F.col("cell") == F.col("whole"), "left").withColumn("cell", cell).drop("whole", "least", "wide")
    return rows


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rows_per_cell: int = 1_500) -> DataFrame:
    """(doc_id, text, cell, ghost): rows dealt out by id range, with the row after each range's last as a ghost in it.

    ``id_cells`` cuts the ids into ranges of about ``rows_per_cell`` rows, whatever their spread over the
    range of long. The first row of every range is sent also to the filled range before it (that of the
    first range to the last), so that a window over one range finds each row's successor and no window
    covers the table. Rows of one id stay together. Rows with a null id take no part; null text is empty.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(text_col, F.lit("")).alias("text")).where("doc_id is not null")
    rows = rows.withColumn("half", F.shiftright("doc_id", 1))  # differences of halves stay in the range of long
    low, width, splits = id_cells(rows.select("half"), rows_per_cell)
    ids = celled(rows.select("doc_id", "half"), low, width, splits)
    rows = celled(rows, low, width, splits).drop("half")
    firsts = written(ids.groupBy("cell").agg(F.min("doc_id").alias("first_id")), "cells")
    around = Window.orderBy("first_id")  # one narrow row for each range
    before = F.coalesce(F.lag("cell").over(around), F.max_by("cell", "first_id").over(Window.partitionBy()))
    ends = firsts.withColumn("to_cell", before).withColumn("last_of_all", F.lag("cell").over(around).isNull()).withColumnRenamed("cell", "of_cell")
    if firsts.count() <= 100_000:
        ends = F.broadcast(ends)
    ghosts = rows.join(ends, (rows["cell"] == F.col("of_cell")) & (rows["doc_id"] == F.col("first_id"))).select(
        "doc_id", "text", F.col("to_cell").alias("cell"), F.when(F.col("last_of_all"), 2).otherwise(1).alias("ghost"))
    return rows.withColumn("ghost", F.lit(0)).unionByName(ghosts)


def edited_pairs(docs: DataFrame, k: int = 3, window: int = 4, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """(doc_id, n_chars, edited_sha256, chosen, edited_chosen, near_edited, near_next) of every whole text.

    The edited text keeps the first half of the code points (the larger half, where odd) and takes as
    many as it lost from the start of the next text by (doc_id, text), the first one's after the last;
    a shorter next text is taken whole. ``chosen`` arrays are as ``winnow`` gives them, with places. A
    null text counts as empty; empty texts have no grams and likeness 1 to each other. One row alone is
    its own next. Rows with a null doc_id take no part; repeated rows repeat; an empty table gives none.
    One shuffle of the texts; the successor's text and grams come from windows over one id range.
    """
    order = Window.partitionBy("cell").orderBy("ghost_last", "doc_id", "text")
    rows = with_next(docs, id_col, text_col, **how).withColumn("ghost_last", (F.col("ghost") > 0).cast("int"))
    rows = rows.withColumn("chosen", winnow(F.col("text"), k, window)).withColumn("n_chars", F.length("text").cast("long"))
    rows = rows.withColumn("next_text", F.lead("text").over(order)).withColumn("next_chosen", F.lead("chosen").over(order)).where("ghost = 0")
    half = F.expr("cast(n_chars div 2 as int)")
    kept = F.substring(F.col("text"), F.lit(1), F.col("n_chars").cast("int") - half)
    edited = F.concat(kept, F.substring(F.col("next_text"), F.lit(1), half))
    rows = rows.select("doc_id", "n_chars", "chosen", "next_chosen", edited.alias("edited"))
    rows = rows.withColumn("edited_chosen", winnow(F.col("edited"), k, window))
    own = hashes(F.col("chosen"))
    return rows.select("doc_id", "n_chars", F.sha2(F.encode("edited", "UTF-8"), 256).alias("edited_sha256"), "chosen", "edited_chosen",
                       likeness(own, hashes(F.col("edited_chosen"))).alias("near_edited"), likeness(own, hashes(F.col("next_chosen"))).alias("near_next"))
