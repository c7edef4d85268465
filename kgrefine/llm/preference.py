"""Preference formatting: shared prompt once, paired masked completions. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def regenerated_pairs(turns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(chosen, rejected) turn tables from plain conversations, one pair for each conversation with an assistant turn.

    Chosen: the turns up to the last assistant turn. Rejected: the same, with the last answer replaced by
    the answer before it, or by an echo of the turn in front where there is only one answer. Turns are
    ordered by (turn, role, text), nulls first; rows with a null conv_id take no part.
    """
    by = Window.partitionBy("pair_id").orderBy("turn", "role", "text")
    rows = (turns.select(F.col("conv_id").cast("long").alias("pair_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
            .where("pair_id is not null").withColumn("pos", F.row_number().over(by).cast("long")))
    answer = F.col("role") == "assistant"
    rows = rows.withColumn("last_pos", F.max(F.when(answer, F.col("pos"))).over(Window.partitionBy("pair_id")))
    rows = rows.withColumn("earlier", F.last(F.when(answer, F.col("text")), True).over(by.rowsBetween(Window.unboundedPreceding, -1)))
    rows = rows.withColumn("echo", F.lag("text").over(by)).where("pos <= last_pos")
    chosen = rows.select("pair_id", "pos", "role", "text")
    other = F.when(F.col("pos") == F.col("last_pos"), F.coalesce("earlier", "echo")).otherwise(F.col("text"))
    return chosen, rows.select("pair_id", "pos", "role", other.alias("text"))


def format_preferences(chosen: DataFrame, rejected: DataFrame, open_tag: str = "<|", close_tag: str = "|>\n", end_tag: str = "\n",
                       loss_role: str = "assistant") -> DataFrame:
    """(pair_id, part, seq, role, rendered, char_start, char_end, loss): the segments of each pair.

    ``chosen`` and ``rejected`` hold (pair_id, pos, role, text), pos numbering a conversation's turns
    from 1. Part ``prompt`` is the longest common turn prefix, rendered once; parts ``chosen`` and
    ``rejected`` hold the turns after it. Offsets count characters within the part. ``loss`` is true
    only for completion turns of ``loss_role``; prompt characters are always masked. Turns compare
    null-safe; a null role or text renders as empty. A side without further turns has no completion
    rows, so equal conversations give a prompt alone; a pair missing on one side has an empty prompt.
    Segments stay rows: no conversation is gathered into one value, so a very long one is only sorted.
    """
    def side(df, name):
        return df.select("pair_id", "pos", F.col("role").alias(f"{name}_role"), F.col("text").alias(f"{name}_text"), F.lit(True).alias(f"in_{name}"))

    both = side(chosen, "c").join(side(rejected, "r"), ["pair_id", "pos"], "full")
    same = (F.col("in_c") & F.col("in_r") & F.col("c_role").eqNullSafe(F.col("r_role")) & F.col("c_text").eqNullSafe(F.col("r_text")))
    split = Window.partitionBy("pair_id")
    cut = F.min(F.when(~F.coalesce(same, F.lit(False)), F.col("pos"))).over(split)
    marked = both.withColumn("shared", F.coalesce(F.col("pos") < cut, F.lit(True)))

    def segment(name, part, role, text, when):
        return F.when(when, F.struct(F.lit(part).alias("part"), role.alias("role"), text.alias("text")))

    c, r = (F.col("c_role"), F.col("c_text")), (F.col("r_role"), F.col("r_text"))
    parts = F.array_compact(F.array(
        segment("c", "prompt", *c, F.col("shared")),
        segment("c", "chosen", *c, ~F.col("shared") & F.col("in_c")),
        segment("r", "rejected", *r, ~F.col("shared") & F.col("in_r"))))
    rows = marked.select("pair_id", "pos", F.explode(parts).alias("s")).select("pair_id", "pos", "s.*")
    shown = F.concat(F.lit(open_tag), F.coalesce("role", F.lit("")), F.lit(close_tag), F.coalesce("text", F.lit("")), F.lit(end_tag))
    order = Window.partitionBy("pair_id", "part").orderBy("pos")
    rows = rows.withColumn("rendered", shown).withColumn("seq", F.row_number().over(order))
    rows = rows.withColumn("char_end", F.sum(F.length("rendered").cast("long")).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    loss = (F.col("part") != "prompt") & F.coalesce(F.col("role") == loss_role, F.lit(False))
    return rows.select("pair_id", "part", "seq", "role", "rendered", (F.col("char_end") - F.length("rendered")).alias("char_start"), "char_end", loss.alias("loss"))
