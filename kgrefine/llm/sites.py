"""Quality by hierarchical empirical Bayes: document evidence with host and path posteriors."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kgrefine.plans.scratch import written

from .vocabulary import slices

FEATURES = ("distinct_words", "repeated_next", "pipes", "symbols", "shouts", "upper", "stops", "word_length", "distinct_lines", "log_words", "length_by_distinct")

_DIGIT, _NUMBERS = re.compile("[0-9]"), re.compile(r"(?<!\S)[^\s0-9]*+[0-9]\S*")


def evidence(text: str) -> list[float]:
    """Shape of one whole text, in the order of ``FEATURES``; zeros for an empty one. Words with digits (numbers, keys, addresses) say nothing of quality and are left out."""
    if _DIGIT.search(text):
        text = _NUMBERS.sub(" ", text)
    words, n = text.split(), len(text)
    if not words:
        return [0.0] * len(FEATURES)
    raw, w = np.frombuffer(text.encode(), dtype=np.uint8), len(words)
    tally = np.bincount(raw, minlength=256)
    lines = text.split("\n")
    distinct = len(set(words)) / w
    log_words = float(np.log1p(w))
    return [distinct, sum(map(str.__eq__, words, words[1:])) / w, tally[124] / w, sum(int(tally[c]) for c in b"#$%&*^~<>{}\\") / n, tally[33] / w,
            int(tally[65:91].sum()) / n, int(tally[44] + tally[46]) / w, n / w, len(set(lines)) / len(lines), log_words, log_words * distinct]


def document_features(docs: DataFrame, host: Column, path: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, host, path, x array<double>) in one pass over whole texts."""

    def go(batches):
        for b in slices(batches):
            x = [evidence(t or "") for t in b.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(x, pa.list_(pa.float64()))], ["doc_id", "host", "path", "x"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(host, F.lit("")).alias("host"), F.coalesce(path, F.lit("")).alias("path"), text_col).mapInArrow(
        go, "doc_id long, host string, path string, x array<double>")


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 40) -> tuple[np.ndarray, float]:
    """Weights and bias on raw features by Newton steps on standardised ones."""
    mean, dev = x.mean(axis=0), x.std(axis=0) + 1e-9
    z = np.hstack([(x - mean) / dev, np.ones((len(x), 1))])
    w, pull = np.zeros(z.shape[1]), np.append(np.full(x.shape[1], ridge * len(x) / 100), 1e-9)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        g = z.T @ (p - y) + pull * w
        h = (z * (p * (1 - p))[:, None]).T @ z + np.diag(pull + 1e-6)
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w[:-1] / dev, float(w[-1] - (w[:-1] * mean / dev).sum())


def _logit(p: Column) -> Column:
    return F.ln(p / (1 - p))


def _sigmoid(x: Column) -> Column:
    return 1 / (1 + F.exp(-F.greatest(F.least(x, F.lit(40.0)), F.lit(-40.0))))


def strength(groups: DataFrame, s: str, n: str) -> tuple[float, float]:
    """(mean, pseudo-count) of a beta prior over groups' rates by the method of moments; one small aggregate row."""
    rate = F.col(s) / F.col(n)
    got = groups.where(F.col(n) > 0).agg(F.sum(s).alias("s"), F.sum(n).alias("n"), F.count("*").alias("g"), F.sum(F.col(n) * rate * rate).alias("q")).first()
    if not got["n"]:
        return 0.5, 2.0
    mean = min(max(got["s"] / got["n"], 1e-3), 1 - 1e-3)
    between = got["q"] / got["n"] - mean**2 - mean * (1 - mean) * got["g"] / got["n"]
    return mean, min(max(mean * (1 - mean) / between - 1, 2.0), 1e4) if between > 1e-9 else 1e4


def quality_scores(docs: DataFrame, labels: DataFrame, host: Column | None = None, path: Column | None = None, id_col: str = "doc_id", text_col: str = "text",
                   sample_rows: int = 20_000, broadcast_rows: int = 50_000) -> DataFrame:
    """(doc_id, host, path, doc_score, host_posterior, path_posterior, score, keep) of every document.

    The host defaults to the column ``source`` and the path to ``lang``, the stand-ins for a URL's parts in
    a table without URLs. A logistic model of the text's shape, fitted on about ``sample_rows`` labelled
    rows (those whose id's hash is under a threshold), gives each document evidence. Its probabilities, and labels where there are
    some, are summed by path and host over all documents; a path's rate is shrunk to its host's and a
    host's to the global one by pseudo-counts estimated from the spread between groups, so a sparse site
    says little. A document's own share is taken out of its site before the site's log odds are added to
    its own log likelihood ratio. ``labels`` holds (doc_id, quality); null ids or labels take no part and
    of repeated ones the largest counts. Sums are partial aggregates; the site table is broadcast only if
    counted at ``broadcast_rows`` rows or fewer. Null host or path is the group ""; a null text counts as
    empty. Without labels of both kinds every score is 0.5 and kept. Repeated rows repeat; an empty table
    gives none. Further columns are not carried.
    """
    host = F.col("source") if host is None else host
    path = F.col("lang") if path is None else path
    rows = written(document_features(docs, host.cast("string"), path.cast("string"), id_col, text_col), "quality")
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("y")).where("doc_id is not null and y is not null").groupBy("doc_id").agg(F.max("y").alias("y"))
    rows = rows.join(known, "doc_id", "left")
    judged = rows.where("y is not null")
    chance = F.shiftrightunsigned(F.xxhash64("doc_id"), 11) / float(2**53)
    sample = judged.where(chance < sample_rows / max(judged.count(), 1)).select("x", "y").limit(2 * sample_rows).collect()
    y = np.array([r["y"] for r in sample], dtype=np.float64)
    if not len(y) or y.min() == y.max():
        one = F.lit(0.5)
        return rows.select("doc_id", "host", "path", *[one.alias(c) for c in ("doc_score", "host_posterior", "path_posterior", "score")], F.lit(1).alias("keep"))
    w, bias = fit_logistic(np.array([r["x"] for r in sample], dtype=np.float64), y)
    base = float(np.log(y.mean() / (1 - y.mean())))
    terms = [F.element_at("x", i + 1) * float(v) for i, v in enumerate(w)]
    rows = rows.withColumn("logit", sum(terms, F.lit(bias))).withColumn("doc_score", _sigmoid(F.col("logit")))
    rows = rows.withColumn("p", F.coalesce(F.col("y").cast("double"), "doc_score")).select("doc_id", "host", "path", "logit", "doc_score", "p")
    paths = written(rows.groupBy("host", "path").agg(F.sum("p").alias("path_s"), F.count("*").alias("path_n")), "quality")
    hosts = paths.groupBy("host").agg(F.sum("path_s").alias("host_s"), F.sum("path_n").alias("host_n"))
    mean, k_host = strength(hosts, "host_s", "host_n")
    _, k_path = strength(paths, "path_s", "path_n")
    sites = paths.join(hosts, "host")
    if sites.count() <= broadcast_rows:
        sites = F.broadcast(sites)
    rows = rows.join(sites, ["host", "path"])
    others = lambda s, n, m, k: (F.greatest(F.col(s) - F.col("p"), F.lit(0.0)) + k * m) / (F.col(n) - 1 + k)
    rows = rows.withColumn("host_posterior", others("host_s", "host_n", F.lit(mean), k_host))
    rows = rows.withColumn("path_posterior", F.greatest(F.least(others("path_s", "path_n", F.col("host_posterior"), k_path), F.lit(1 - 1e-6)), F.lit(1e-6)))
    score = _sigmoid(F.col("logit") - base + _logit(F.col("path_posterior")))
    return rows.withColumn("score", score).select("doc_id", "host", "path", "doc_score", "host_posterior", "path_posterior", "score", (F.col("score") >= 0.5).cast("int").alias("keep"))
