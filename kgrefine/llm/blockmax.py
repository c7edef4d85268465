"""Exact top-k search with block-at-a-time pruning."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window


def integer_terms(vector: Column, scale: int = 64) -> Column:
    """Each component x as floor(scale * x), x as double; null for a vector that is null or has null or non-finite components."""
    wide = F.transform(vector, lambda x: x.cast("double"))
    bad = F.exists(wide, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.when(vector.isNotNull() & ~F.coalesce(bad, F.lit(True)), F.transform(wide, lambda x: F.floor(x * scale)))


def search_tile(ids: np.ndarray, docs: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, k: int, block_rows: int, stats: dict | None = None):
    """The k best (score, smaller id first) of ``docs`` for each query, its own id left out: arrays (q, k) of scores and ids.

    Documents are sorted by their heaviest term, then id, and cut into ranges of ``block_rows``, so that
    a block's vectors lean the same way where the vectors allow it. A dimension counts as two terms,
    its positive and its negative part, so a block's bound is the sum over terms of query weight times
    the block's largest (or, for negative weights, smallest) value. Each query visits blocks in falling
    bound order and stops when the next bound is under its kth score; an equal bound is still visited,
    as it may hold a tie with a smaller id. A visited block is scored from its forward rows.
    """
    heavy = np.abs(docs).argmax(axis=1)
    order = np.lexsort((ids, docs[np.arange(len(ids)), heavy] < 0, heavy))
    ids, docs = ids[order], docs[order]
    starts = np.arange(0, len(ids), block_rows)
    top, low = np.maximum.reduceat(docs, starts, axis=0), np.minimum.reduceat(docs, starts, axis=0)
    bound = np.maximum(queries, 0) @ top.T + np.minimum(queries, 0) @ low.T
    visit = np.argsort(-bound, axis=1, kind="stable")
    best = np.full((len(queries), k), -np.inf)
    best_id = np.full((len(queries), k), np.iinfo(np.int64).max)
    active, scored = np.arange(len(queries)), 0
    for t in range(len(starts)):
        block = visit[active, t]
        go = bound[active, block] >= best[active, -1]
        active, block = active[go], block[go]
        if not len(active):
            break
        for b in np.unique(block):
            who = active[block == b]
            rows = slice(starts[b], starts[b] + block_rows)
            score = (queries[who] @ docs[rows].T).astype(np.float64)
            scored += score.size
            score[ids[rows][None, :] == query_ids[who][:, None]] = -np.inf
            better = score.max(axis=1) >= best[who, -1]
            who, score = who[better], score[better]
            if len(who):
                all_s = np.hstack([best[who], score])
                all_i = np.hstack([best_id[who], np.broadcast_to(ids[rows], score.shape)])
                take = np.lexsort((all_i, -all_s), axis=1)[:, :k]
                best[who], best_id[who] = np.take_along_axis(all_s, take, 1), np.take_along_axis(all_i, take, 1)
    if stats is not None:
        stats["scored"], stats["pairs"] = scored, len(ids) * len(queries)
    return best, best_id


def _matrix(rows: list, width: int) -> np.ndarray:
    out = np.zeros((len(rows), width), dtype=np.int64)
    for i, row in enumerate(rows):
        out[i, : len(row)] = row
    return out


def wide_products(docs: np.ndarray, queries: np.ndarray) -> np.ndarray:
    """Exact (q, d) inner products of long vectors, held to the range of long.

    Sums modulo 2**64 are exact wherever the true value fits; floating-point sums with an error bound
    tell where it does, and the few products too near the limit to tell are taken in whole numbers.
    """
    low, high = np.iinfo(np.int64).min, np.iinfo(np.int64).max
    with np.errstate(over="ignore"):
        out = queries @ docs.T
    a, b = queries.astype(np.float64), docs.astype(np.float64)
    about, slack = a @ b.T, (np.abs(a) @ np.abs(b).T) * 1e-12 + 1
    out[about - slack >= 2.0**63] = high
    out[about + slack < -(2.0**63)] = low
    for i, j in np.argwhere(np.abs(np.abs(about) - 2.0**63) < slack):
        out[i, j] = min(max(sum(int(x) * int(y) for x, y in zip(queries[i], docs[j], strict=True)), low), high)
    return out


def search_wide(ids: np.ndarray, docs: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, k: int, step: int = 256) -> list[tuple]:
    """(query, id, score) of the k best without bounds, for vectors whose products leave the range that floating point holds exactly."""
    out = []
    for at in range(0, len(queries), step):
        for q, row in zip(query_ids[at : at + step], wide_products(docs, queries[at : at + step]), strict=True):
            take = np.lexsort((ids, ~row))  # ~ turns the order round without leaving the range
            take = take[ids[take] != q][:k]
            out += zip([int(q)] * len(take), ids[take].tolist(), row[take].tolist(), strict=True)
    return out


def topk_search(corpus: DataFrame, queries: DataFrame, k: int = 20, id_col: str = "vec_id", vec_col: str = "terms",
                block_rows: int = 128, slab_rows: int = 16_384, batch_rows: int = 2_048) -> DataFrame:
    """(query_id, rank, vec_id, score): the k corpus rows with the highest integer inner product of each query row.

    The query set is met by all rows in blocks: corpus rows are hashed into slabs of about ``slab_rows``
    and queries into batches of about ``batch_rows``; each (slab, batch) tile is one bounded group whose
    k best per query are merged by a window limit. Vectors must hold whole numbers of type long, of any
    size: scores are exact, and held to the range of long where they leave it. Null vectors take no part, a shorter vector counts as padded with zeros, ids are compared as long and null ids take no
    part. A repeated query id is searched once (its smallest vector); repeated corpus rows each count;
    rows with the query's own id never answer it. Fewer than k candidates give fewer rows; empty tables
    give none. Further columns are not carried.
    """
    docs = corpus.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("terms")).where("vec_id is not null and terms is not null")
    asks = (queries.select(F.col(id_col).cast("long").alias("query_id"), F.col(vec_col).alias("terms")).where("query_id is not null and terms is not null")
            .groupBy("query_id").agg(F.min("terms").alias("terms")))
    slabs = max(1, math.ceil(docs.count() / slab_rows))
    batches = max(1, math.ceil(asks.count() / batch_rows))
    left = (docs.withColumn("slab", F.pmod(F.xxhash64("vec_id"), F.lit(slabs)).cast("int"))
            .withColumn("batch", F.explode(F.sequence(F.lit(0), F.lit(batches - 1)))))
    right = (asks.withColumn("batch", F.pmod(F.xxhash64("query_id"), F.lit(batches)).cast("int"))
             .withColumn("slab", F.explode(F.sequence(F.lit(0), F.lit(slabs - 1)))))

    def tile(d: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        if d.empty or q.empty:
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype("int64")
        width = max(d["terms"].map(len).max(), q["terms"].map(len).max(), 1)
        a, b = _matrix(d["terms"].tolist(), width), _matrix(q["terms"].tolist(), width)
        ids, asks = d["vec_id"].to_numpy(np.int64), q["query_id"].to_numpy(np.int64)
        edge = int(math.isqrt(2**53 // width))  # products of vectors within it are whole numbers under 2**53
        big_a, big_b = (((m > edge) | (m < -edge)).any(axis=1) for m in (a, b))
        rows = search_wide(ids, a, asks[big_b], b[big_b], k) + search_wide(ids[big_a], a[big_a], asks[~big_b], b[~big_b], k)
        out = [pd.DataFrame(rows, columns=["query_id", "vec_id", "score"]).astype("int64")]
        if (~big_a).any() and (~big_b).any():
            ids, asks, a, b = ids[~big_a], asks[~big_b], a[~big_a], b[~big_b]
            kind = np.float32 if int(np.abs(a).max()) * int(np.abs(b).max()) * width < 2**24 else np.float64
            score, got = search_tile(ids, a.astype(kind), asks, b.astype(kind), k, block_rows)
            ok = np.isfinite(score)
            who = np.repeat(asks, k).reshape(score.shape)
            out.append(pd.DataFrame({"query_id": who[ok], "vec_id": got[ok], "score": score[ok].astype(np.int64)}))
        return pd.concat(out)

    found = left.groupBy("slab", "batch").cogroup(right.groupBy("slab", "batch")).applyInPandas(
        tile, T.StructType([T.StructField(c, T.LongType()) for c in ("query_id", "vec_id", "score")]))
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
