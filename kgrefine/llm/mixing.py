"""Mixing sources to target weights by a low-discrepancy schedule of equal-token blocks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgrefine.plans.scratch import written

from .vocabulary import free_name

#: Fractional part of the golden ratio; its multiples modulo 1 fill the unit interval evenly.
GOLDEN = 0.6180339887498949


def word_count(text: Column) -> Column:
    """Number of maximal runs of characters outside space and control white space; 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")).cast("long"), F.lit(0).cast("long"))


def source_targets(totals: DataFrame, weights: tuple[float, ...] = (5, 2, 1), most_epochs: int = 3) -> DataFrame:
    """Adds ``target`` (words) and the target's place [low, high) in the cumulative sum to (source, source_size) rows.

    Sources in code point order, null last, take ``weights`` in turn. Shares of the total are cut at
    ``most_epochs`` times a source's size and the excess goes to the others by weight: with sources in
    falling order of weight over limit, the cut ones are a prefix, so one ordered pass over the source
    table finds the level. The table has a row per source, never per document.
    """
    everything = Window.orderBy(F.col("source").isNull(), "source")
    n = (F.row_number().over(everything) - 1) % len(weights)
    rows = totals.withColumn("w", F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (n + 1).cast("int")))
    rows = rows.withColumn("limit", F.col("source_size").cast("double") * most_epochs).withColumn("ratio", F.col("limit") / F.col("w"))
    fill = Window.orderBy("ratio", F.col("source").isNull(), "source")
    whole = Window.partitionBy()
    rows = rows.withColumn("total", F.sum("source_size").over(whole).cast("double"))
    ahead = F.coalesce(F.sum("limit").over(fill.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    left = F.sum("w").over(fill.rowsBetween(0, Window.unboundedFollowing))
    rows = rows.withColumn("level", (F.col("total") - ahead) / left)
    # the first source, in order of ratio, that its level does not fill
    rows = rows.withColumn("nth", F.row_number().over(fill))
    rows = rows.withColumn("rise", F.min(F.when(F.col("level") <= F.col("ratio"), F.struct("nth", "level"))).over(whole)["level"])
    rows = rows.withColumn("target", F.least(F.col("limit"), F.col("w") * F.coalesce("rise", F.col("ratio"))))
    high = F.sum("target").over(everything.rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("high", high).withColumn("low", F.col("high") - F.col("target")).select("source", "source_size", "target", "low", "high", "total")


def schedule(spark, targets: DataFrame, slots: int, sequence: str = "golden", cells: int = 4096) -> DataFrame:
    """(slot, source): each slot's point, mapped through the cumulative targets.

    ``golden`` takes multiples of the golden ratio modulo 1, ``van_der_corput`` the slot number's bits
    mirrored behind the point. A source's interval is cut at a grid of ``cells`` and joined on the cell,
    so neither the number of sources nor a source with most of the weight limits the join.
    """
    j = spark.range(slots).withColumnRenamed("id", "slot")
    if sequence == "golden":
        point = F.pmod((F.col("slot") + 0.5) * F.lit(GOLDEN), F.lit(1.0))
    elif sequence == "van_der_corput":
        point = F.conv(F.reverse(F.lpad(F.bin("slot"), 48, "0")), 2, 10).cast("double") / float(2**48)
    else:
        raise ValueError(sequence)
    j = j.withColumn("point", point).withColumn("cell", F.floor(F.col("point") * cells).cast("int"))
    whole = F.max("high").over(Window.partitionBy())
    part = (targets.where("target > 0").withColumn("all", whole).withColumn("a", F.col("low") / F.col("all")).withColumn("b", F.col("high") / F.col("all"))
            .withColumn("cell", F.explode(F.sequence(F.floor(F.col("a") * cells).cast("int"), F.least(F.floor(F.col("b") * cells), F.lit(cells - 1)).cast("int"))))
            .select("source", "a", "b", "cell"))
    return j.join(part, "cell").where("point >= a and point < b").select("slot", "source")


def _small(per_source: DataFrame, most: int = 100_000) -> DataFrame:
    """A table with a row for each source, broadcast if it is counted at ``most`` rows or fewer."""
    kept = written(per_source, "mix")
    return F.broadcast(kept) if kept.count() <= most else kept


def ranked_slots(dealt: DataFrame, slots_per_part: int = 65_536) -> DataFrame:
    """(slot, source, rank): each slot's rank, from 0, among its source's slots; ranks come from parts of the slots and the parts' counts."""
    dealt = dealt.withColumn("part", F.expr(f"slot div {slots_per_part}"))
    parts = dealt.groupBy("source", "part").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("source").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    parts = parts.withColumn("before", before)
    inside = F.row_number().over(Window.partitionBy("source", "part").orderBy("slot")) - 1
    rows = dealt.withColumn("inside", inside).alias("s").join(parts.alias("p"), (F.col("s.part") == F.col("p.part")) & F.col("s.source").eqNullSafe(F.col("p.source")))
    return rows.select("slot", "s.source", (F.col("before") + F.col("inside")).alias("rank"))


def mix_blocks(docs: DataFrame, weights: tuple[float, ...] = (5, 2, 1), most_epochs: int = 3, block: int = 32, sequence: str = "golden",
               seed: int = 17, rows_per_bucket: int = 5_000, row_col: str | None = None) -> tuple[DataFrame, DataFrame]:
    """Rows (row, row_key, doc_id, source, size, source_size, target) and pieces (slot, source, block, row, offset, length).

    Every source's documents, in the order of a seeded hash, form one stream of words, read round and
    round (at most ``most_epochs`` rounds) and cut into blocks of ``block`` words. ``schedule`` deals
    slots to sources, and the slot of rank r in its source takes block r: a piece is the words from
    ``offset`` on of one document that stand in a slot's block. Pieces by (slot, position), where position
    is the piece's place in its block, are the mixed stream. Stream places come from two levels of sums,
    hash buckets of about ``rows_per_bucket`` rows, as many as its rows ask for in each source, and the
    buckets' totals, so that a source with a third of all rows is still many tasks of the common size.
    ``row`` is ``row_col`` of the given rows or a number of its own.
    """
    key = F.xxhash64(F.lit(seed), "doc_id", "text")
    row = F.col(row_col) if row_col else F.monotonically_increasing_id()
    base = docs.select(row.alias("row"), "doc_id", "source", word_count(F.col("text")).alias("size"), key.alias("row_key"))
    base = written(base, "mix")
    spark = docs.sparkSession
    bits = F.greatest(F.ceil(F.log2(F.count("*") / rows_per_bucket)), F.lit(0)).cast("int")
    per_source = base.groupBy(F.col("source").alias("of")).agg(bits.alias("bits"))
    base = base.join(_small(per_source), F.col("source").eqNullSafe(F.col("of")))
    base = base.withColumn("bucket", F.when(F.col("bits") == 0, 0).otherwise(F.expr("shiftrightunsigned(row_key, 64 - bits)")).cast("long")).drop("of", "bits")
    per_bucket = written(base.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size")), "mix")
    before = F.coalesce(F.sum("bucket_size").over(Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    targets = written(source_targets(per_bucket.groupBy("source").agg(F.sum("bucket_size").alias("source_size")), weights, most_epochs), "mix")
    total = targets.agg(F.max("total")).first()[0] or 0.0
    slots = int(round(total / block)) if total else 0
    dealt = written(schedule(spark, targets, slots, sequence), "mix")
    n_slots = dealt.groupBy("source").agg(F.count("*").alias("n_slots"))
    same = F.col("t.source").eqNullSafe(F.col("d.source"))
    words = F.least(F.coalesce(F.col("n_slots"), F.lit(0)) * block, F.col("source_size") * most_epochs)
    plan = targets.alias("t").join(n_slots.alias("d"), same, "left").select("t.source", "source_size", "target", words.alias("words"))
    places = per_bucket.withColumn("before", before).alias("p").join(plan.alias("q"), F.col("p.source").eqNullSafe(F.col("q.source"))).select(
        "p.source", "bucket", "before", "source_size", "target", "words")
    rows = base.alias("b").join(places.alias("p"), (F.col("b.bucket") == F.col("p.bucket")) & F.col("b.source").eqNullSafe(F.col("p.source"))).select(
        "row", "row_key", "doc_id", "b.source", "size", "b.bucket", "before", "source_size", "target", "words")
    inside = F.sum("size").over(Window.partitionBy("source", "bucket").orderBy("row_key", "doc_id", "row").rowsBetween(Window.unboundedPreceding, 0))
    rows = written(rows.withColumn("start", F.col("before") + inside - F.col("size")), "mix")
    # each round's words of a document, [from, to) in the source's repeated stream, and the blocks they fall in
    read = rows.where("size > 0 and start < words").withColumn("round", F.explode(F.expr("sequence(0L, (words - 1 - start) div source_size)")))
    read = read.withColumn("from", F.col("round") * F.col("source_size") + F.col("start")).withColumn("to", F.least(F.col("from") + F.col("size"), "words"))
    cut = read.select("row", "source", "from", "to", F.explode(F.expr(f"sequence(from div {block}, (to - 1) div {block})")).alias("block"))
    first = F.greatest(F.col("block") * block, "from")
    cut = cut.select("row", "source", "block", (first - F.col("from")).alias("offset"), (first - F.col("block") * block).alias("position"),
                     (F.least((F.col("block") + 1) * block, "to") - first).alias("length"))
    taken = ranked_slots(dealt).alias("s").join(cut.alias("c"), (F.col("s.rank") == F.col("c.block")) & F.col("s.source").eqNullSafe(F.col("c.source")))
    return rows.drop("bucket", "before", "words", "start"), taken.select("slot", "c.source", "block", "position", "row", "offset", "length")


def mix_sources(docs: DataFrame, **how) -> DataFrame:
    """(row_key, doc_id, source, size, source_size, target, taken, copies) for each document; parameters as ``mix_blocks``.

    ``taken`` counts the words of a document in the blocks that slots take, repeats counted; ``copies``
    counts the rounds in which the document's first word is taken, which is how often it stands in a
    mixed corpus of whole documents. Null text has size 0 and is never taken; null doc_id and null source
    are kept (sources: one group, last); repeated rows are documents of their own; an empty table gives none.
    """
    rows, pieces = mix_blocks(docs, **how)
    sums = pieces.groupBy("row").agg(F.sum("length").alias("taken"), F.count(F.when(F.col("offset") == 0, 1)).alias("copies"))
    return rows.join(sums, "row", "left").select("row_key", "doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"),
                                                 F.coalesce("copies", F.lit(0)).cast("int").alias("copies"))


def mixed_documents(docs: DataFrame, **how) -> DataFrame:
    """The documents themselves, in the mixed order, columns as given: a copy stands where the slot of its first word does (none, where the mix takes none)."""
    row_col, slot, position = (free_name(docs, n) for n in ("row_no", "slot_no", "position_no"))
    rows = written(docs.select(F.monotonically_increasing_id().alias(row_col), *docs.columns), "rows")
    _, pieces = mix_blocks(rows, row_col=row_col, **how)
    plan = pieces.where("offset = 0").select(F.col("row").alias(row_col), F.col("slot").alias(slot), F.col("position").alias(position))
    return rows.join(plan, row_col).orderBy(slot, position).select(*docs.columns)
