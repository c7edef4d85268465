"""Token counts of fields or sections from one encoding of the whole document."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .vocabulary import byte_bpe, default_path, slices

RULES = ("start", "end", "majority", "fraction")


def byte_places(text: str, chars: np.ndarray) -> np.ndarray:
    """Byte offset of each character offset."""
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    if len(raw) == len(text):
        return np.clip(chars, 0, len(text))
    first = np.append(np.flatnonzero((raw & 0xC0) != 0x80), len(raw))
    return first[np.clip(chars, 0, len(text))]


def allocate(ends: np.ndarray, low: np.ndarray, high: np.ndarray, rule: str) -> np.ndarray:
    """Tokens of each span [low, high); tokens end at ``ends`` and join up, spans are sorted and disjoint.

    ``start`` gives a token to the span of its first byte, ``end`` to that of its last, ``majority`` to
    the span with most of its bytes (the first on a tie), ``fraction`` splits it by bytes. Tokens or
    parts outside all spans are given to none.
    """
    starts = np.concatenate([[0], ends[:-1]]) if len(ends) else ends
    out = np.zeros(len(low), dtype=np.float64)
    if not len(ends) or not len(low):
        return out
    if rule in ("start", "end"):
        at = starts if rule == "start" else ends - 1
        span = np.searchsorted(low, at, side="right") - 1
        ok = (span >= 0) & (at < high[np.maximum(span, 0)])
        return np.bincount(span[ok], minlength=len(low)).astype(np.float64)
    first = np.searchsorted(high, starts, side="right")
    last = np.searchsorted(low, ends, side="left") - 1
    inside = (first == last) & (first < len(low))
    full = inside & (low[np.minimum(first, len(low) - 1)] <= starts) & (high[np.minimum(first, len(low) - 1)] >= ends)
    out += np.bincount(first[full], minlength=len(low))
    for t in np.flatnonzero(~full & (first <= last)):
        spans = np.arange(first[t], last[t] + 1)
        share = np.minimum(high[spans], ends[t]) - np.maximum(low[spans], starts[t])
        if rule == "fraction":
            out[spans] += share / (ends[t] - starts[t])
        elif rule == "majority":
            out[spans[np.argmax(share)]] += 1
        else:
            raise ValueError(rule)
    return out


def attribute_tokens(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spans_col: str | None = None, rule: str = "start",
                     tokenizer_path: str | None = None) -> DataFrame:
    """(doc_id, section, char_start, char_end, tokens): each document is encoded once, its tokens joined to spans by place.

    ``spans_col`` names an array of (start, end) character spans, sorted and disjoint; without it the
    sections are the text's lines, each with its line feed. ``rule`` says who gets a token that crosses
    a boundary (see ``allocate``). Offsets come from the lengths of the byte-level tokens. One pass, no
    shuffle; texts are encoded whole whatever their length. Null text counts as empty, an empty text
    has one empty section with 0 tokens; an empty or null span array gives no rows; repeated rows
    repeat; an empty table gives none. Further columns are not carried.
    """
    if rule not in RULES:
        raise ValueError(rule)
    path = tokenizer_path or default_path("byte_bpe_50k.tiktoken")
    kind = dict(docs.select(id_col).dtypes)[id_col]
    cols = [F.col(id_col).alias("doc_id"), F.coalesce(text_col, F.lit("")).alias("text")]
    if spans_col:
        cols += [F.transform(spans_col, lambda s: s[docs.schema[spans_col].dataType.elementType.names[0]].cast("long")).alias("lo"),
                 F.transform(spans_col, lambda s: s[docs.schema[spans_col].dataType.elementType.names[1]].cast("long")).alias("hi")]

    def count(batches):
        bpe = byte_bpe(path)
        for batch in slices(batches):
            ids, texts = batch.column(0), batch.column(1)
            rows, section, lo_all, hi_all, got = [], [], [], [], []
            for i in range(batch.num_rows):
                text = texts[i].as_py()
                if spans_col:
                    lo, hi = (np.asarray(batch.column(c)[i].as_py() or [], dtype=np.int64) for c in (2, 3))
                else:
                    cut = np.flatnonzero(np.frombuffer(text.encode("utf-32-le"), dtype="<u4") == 10) + 1
                    cut = np.append(cut, len(text)) if not len(cut) or cut[-1] < len(text) else cut
                    lo, hi = np.concatenate([[0], cut[:-1]]), cut
                rows.append(np.full(len(lo), i))
                section.append(np.arange(len(lo)))
                lo_all.append(lo)
                hi_all.append(hi)
                got.append(allocate(bpe.ends(text), byte_places(text, lo), byte_places(text, hi), rule))
            if rows:
                yield pa.RecordBatch.from_arrays(
                    [ids.take(pa.array(np.concatenate(rows), pa.int64())), pa.array(np.concatenate(section), pa.int32()), pa.array(np.concatenate(lo_all), pa.int64()),
                     pa.array(np.concatenate(hi_all), pa.int64()), pa.array(np.concatenate(got), pa.float64())], ["doc_id", "section", "char_start", "char_end", "tokens"])

    return docs.select(*cols).mapInArrow(count, f"doc_id {kind}, section int, char_start long, char_end long, tokens double")
