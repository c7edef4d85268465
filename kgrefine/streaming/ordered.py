"""Sequence-ordered release of items that complete in parallel."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def ordered_release(done: DataFrame, seq_col: str = "seq", done_col: str = "done_ts", bucket_rows: int = 100_000) -> DataFrame:
    """Adds ``release_ts``: item n is released once it and all before it are done, the running maximum of completion in the order of ``seq``.

    Two levels, ranges of sequence numbers and their maxima, so that no task orders the whole stream.
    """
    low = F.floor(F.col(seq_col) / bucket_rows)
    rows = done.withColumn("__b", low)
    tops = rows.groupBy("__b").agg(F.max(done_col).alias("top"))
    before = F.max("top").over(Window.orderBy("__b").rowsBetween(Window.unboundedPreceding, -1))
    inside = F.max(done_col).over(Window.partitionBy("__b").orderBy(seq_col).rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("__in", inside).join(tops.select("__b", before.alias("__before")), "__b").withColumn("release_ts", F.greatest("__in", "__before")).drop("__b", "__in", "__before")


def inversions(done: DataFrame, seq_col: str = "seq", done_col: str = "done_ts") -> DataFrame:
    """(seq, parked, delay) of the unordered baseline: whether an item completes before one ahead of it, and how long order makes it wait."""
    rel = ordered_release(done, seq_col, done_col)
    return rel.select(seq_col, (F.col("release_ts") > F.col(done_col)).alias("parked"), (F.col("release_ts") - F.col(done_col)).alias("delay"))


def ordered_emitter(first: int = 0, gap_after: int | None = None):
    """The state function of ``ordered_sink``: parks items until their turn; a gap is skipped once ``gap_after`` items wait behind it."""

    def step(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        nxt, parked = (state.get if state.exists else (first, []))
        waiting = {int(s): v for s, v in (p.split("\x1f", 1) for p in parked)}
        for pdf in frames:
            waiting.update(zip(pdf["seq"].astype(int), pdf["payload"].astype(str), strict=True))
        out = []
        while waiting:
            if nxt not in waiting:
                if gap_after is None or len(waiting) <= gap_after:
                    break
                nxt = min(waiting)
            out.append((key[0], nxt, waiting.pop(nxt)))
            nxt += 1
        state.update((nxt, [f"{s}\x1f{v}" for s, v in sorted(waiting.items())]))
        yield pd.DataFrame(out, columns=["channel", "seq", "payload"])

    return step


def ordered_sink(stream: DataFrame, first: int = 0, gap_after: int | None = None) -> DataFrame:
    """A stream of (channel, seq long, payload string) in the order of ``seq`` for each channel, by keyed state."""
    out = "channel string, seq long, payload string"
    return stream.select(F.col("channel").cast("string").alias("channel"), F.col("seq").cast("long").alias("seq"), F.col("payload").cast("string").alias("payload")).groupBy("channel").applyInPandasWithState(
        ordered_emitter(first, gap_after), out, "next long, parked array<string>", "append", "NoTimeout")
