"""Toxicity by a subsequence string kernel, Nyström landmarks and a linear support vector machine."""

from __future__ import annotations

import re
import unicodedata
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .vocabulary import free_name, slices

#: 0: any other character, 1-26: letters without case or marks, 27: a word's border.
LETTERS = 28
WIDTH, GAP, DECAY = 24, 3, 0.6
_FOLD = np.zeros(0x250, dtype=np.int32)
for _c in range(0x250):
    _b = unicodedata.normalize("NFKD", chr(_c).lower())[:1]
    _FOLD[_c] = ord(_b) - 96 if "a" <= _b <= "z" else 0
_SPELLED = re.compile(r"(?<!\S)(\S)(?: (?=\S(?!\S)))")


def words_of(text: str) -> list[str]:
    """Words of a whole text, lowered; letters spelled out one by one are joined up as well; a word over the width gives overlapping parts."""
    low = text.lower()
    found = low.split()
    if _SPELLED.search(low):
        found += _SPELLED.sub(r"\1", low).split()
    if any(len(w) > WIDTH for w in found):
        found = [w[i : i + WIDTH] for w in found for i in range(0, max(1, len(w) - WIDTH // 2), WIDTH // 2)]
    return found


def letters(words: list[str]) -> np.ndarray:
    """(n, WIDTH + 2) letter numbers with borders; 0 fills."""
    raw = np.array(words, dtype=f"U{WIDTH}").view(np.uint32).reshape(len(words), WIDTH)
    size = (raw != 0).sum(axis=1)
    out = np.zeros((len(words), WIDTH + 2), dtype=np.int32)
    out[:, 1:-1] = _FOLD[np.where(raw < len(_FOLD), raw, 0)]
    out[:, 0] = 27
    out[np.arange(len(words)), size + 1] = 27
    return out[:, : int(size.max(initial=0)) + 2]


def subsequences(seq: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes and weights of every three letters in order, each up to GAP after the last, DECAY for each place left out; code 0 for none."""
    n, m = seq.shape
    codes, weights = [], []
    wide, mid = seq * (LETTERS * LETTERS), seq * LETTERS
    for a in range(1, GAP + 1):
        for b in range(1, GAP + 1):
            if (k := m - a - b) > 0:
                x, y, z = wide[:, :k], mid[:, a : a + k], seq[:, a + b : a + b + k]
                code = x + y + z
                code[(x == 0) | (y == 0) | (z == 0)] = 0
                codes.append(code)
                weights.append(np.full(k, DECAY ** (a + b - 2), dtype=np.float32))
    if not codes:
        return np.zeros((n, 1), dtype=np.int32), np.zeros(1, dtype=np.float32)
    return np.hstack(codes), np.concatenate(weights)


def _scale(codes: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """One over the length of each word's vector, its subsequences counted one by one."""
    size = np.sqrt((codes > 0).astype(np.float32) @ (weights * weights))
    return 1 / np.where(size == 0, 1, size)


def features(words: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
    """Per word: distinct codes and their values, scaled, so that the kernel is their dot product."""
    out = []
    codes, weights = subsequences(letters(words))
    for row, scale in zip(codes, _scale(codes, weights), strict=True):
        ok = row > 0
        u, inv = np.unique(row[ok], return_inverse=True)
        out.append((u, np.bincount(inv, weights[ok], minlength=len(u)) * scale))
    return out


def project(words: list[str], table: np.ndarray) -> np.ndarray:
    """For each word the product of its scaled vector with ``table``, whose code 0 must be 0."""
    out = np.zeros(len(words))
    order = np.argsort(np.fromiter(map(len, words), dtype=np.int64, count=len(words)), kind="stable")
    for part in np.array_split(order, max(1, len(words) // 4096)):
        if len(part):
            codes, weights = subsequences(letters([words[i] for i in part]))
            out[part] = (table[codes] @ weights) * _scale(codes, weights)
    return out


@dataclass
class ToxicityModel:
    """``table`` folds landmarks, Nyström map and support vector weights into one value per code; ``weights`` and ``shift`` map a text's ``summary`` to log odds."""

    table: np.ndarray
    bias: float
    weights: np.ndarray
    shift: float

    def margins(self, words: list[str]) -> np.ndarray:
        return project(words, self.table) + self.bias

    def log_odds(self, margins: np.ndarray) -> float:
        return float(summary(margins) @ self.weights) + self.shift


def bag(text: str) -> list[str]:
    """The distinct words of a whole text without the punctuation around them, in order of appearance."""
    bare = (w.strip(".,;:!?\"'()[]|") for w in dict.fromkeys(words_of(text)))
    return [w for w in dict.fromkeys(bare) if w]


def summary(margins: np.ndarray) -> np.ndarray:
    """What a text's score looks at: its three largest word margins, how many are over 0, and how many words it has."""
    best = np.full(3, -2.0)
    top = np.sort(margins)[::-1][:3]
    best[: len(top)] = np.clip(top, -2, 2)
    return np.array([*best, np.log1p((margins > 0).sum()), np.log1p(len(margins))])


def _marks(words: list[str]) -> list[int]:
    """A text's smallest shingle hash under each of four seeds; texts that share one are copies, which teach the same words again."""
    parts = {" ".join(words[j : j + 5]) for j in range(max(1, len(words) - 4))}
    return [min(xxhash.xxh3_64_intdigest(p, s) for p in parts) for s in range(4)]


def train(texts: list[str], toxic: list[int], **how) -> ToxicityModel | None:
    """A model from labelled texts, see ``train_bags``."""
    return train_bags(((_marks(words_of(t)), bag(t), y) for t, y in zip(texts, toxic, strict=True)), **how)


def train_bags(examples, landmarks: int = 384, rounds: int = 3, most: int = 20_000, seed: int = 3) -> ToxicityModel | None:
    """A model from (``_marks``, ``bag``, label) of texts in order; None without both kinds among those that are no copies.

    The labelled texts are the examples: a toxic one is a bag of words of which some are to blame, all
    words of a clean one are not (multiple-instance learning). At first a toxic text shares its label
    among all its words; after each round among those on the toxic side of the machine, by margin, while
    clean words that the machine takes for toxic join the negative side. Words are seen through the
    kernel alone, so a word with letters put between or left out, or another ending, falls beside its
    kin. Every fourth text is kept apart from the machine: on these a logistic curve is fitted from a
    text's ``summary`` to its label. A round uses at most ``most`` words of toxic texts (by their share
    of the label) and 10,000 of clean ones (common, drawn, and hard).
    """
    one: dict[str, int] = {}
    bags, labels, seen = [], [], set()
    for mark, held, label in examples:
        marks = set(enumerate(mark))
        if not marks & seen:
            bags.append(np.array([one.setdefault(w, len(one)) for w in held], dtype=np.int64))
            labels.append(int(label == 1))
        seen |= marks
    y, words = np.array(labels, dtype=np.int64), list(one)
    apart = np.arange(len(y)) % 4 == 0
    taught = [(b, t) for b, t, out in zip(bags, y, apart, strict=True) if len(b) and not out]
    if not any(t for _, t in taught) or all(t for _, t in taught):
        return None
    share, clean = np.zeros(len(words)), np.zeros(len(words))
    for b, t in taught:
        if t:
            share[b] += 1 / len(b)
        else:
            clean[b] += 1
    rng, negative, hard = np.random.default_rng(seed), np.flatnonzero(clean), np.zeros(0, dtype=np.int64)
    common = negative[np.argsort(-clean[negative], kind="stable")[:2000]]
    for turn in range(rounds + 1):
        pos = np.argsort(-share, kind="stable")[:most]
        pos = pos[share[pos] > 0]
        neg = np.unique(np.concatenate([common, rng.choice(negative, min(len(negative), 6000), replace=False), hard]))
        weight = np.ones(len(neg)) if turn else np.sqrt(clean[neg])
        marks = np.concatenate([pos[: landmarks // 2], hard[: landmarks // 4], rng.choice(neg, min(len(neg), landmarks // 2), replace=False)])
        model = _fit([words[i] for i in pos], share[pos], [words[i] for i in neg], weight, [words[i] for i in list(dict.fromkeys(marks.tolist()))[:landmarks]])
        margin = model.margins(words)
        hard = negative[np.argsort(-margin[negative], kind="stable")[:2000]]
        hard = hard[margin[hard] > -0.9]
        share[:] = 0
        for b, t in taught:
            blame = np.maximum(margin[b], 0) / (1 + clean[b])
            if t and blame.any():
                share[b] += blame / blame.sum()
        if not share.any():
            break
    model.weights, model.shift = _logistic(np.array([summary(margin[b]) for b, out in zip(bags, apart, strict=True) if out]), y[apart])
    return model


def _fit(pos: list[str], pos_weight: np.ndarray, neg: list[str], neg_weight: np.ndarray, marks: list[str]) -> ToxicityModel:
    """A linear machine with squared hinge loss on Nyström features, folded into one value per code; both sides weigh the same in all."""
    basis = np.zeros((LETTERS**3, len(marks)), dtype=np.float32)
    for j, (u, v) in enumerate(features(marks)):
        basis[u, j] = v
    val, vec = np.linalg.eigh((basis.T @ basis).astype(np.float64))
    half = vec @ np.diag(1 / np.sqrt(np.maximum(val, 1e-4))) @ vec.T
    words = pos + neg
    x = np.ones((len(words), len(marks) + 1), dtype=np.float32)
    for at in range(0, len(words), 1000):
        x[at : at + 1000, :-1] = [v @ basis[u] for u, v in features(words[at : at + 1000])]
    x[:, :-1] = x[:, :-1] @ half.astype(np.float32)
    t = np.array([1.0] * len(pos) + [-1.0] * len(neg))
    c = np.concatenate([0.5 * pos_weight / pos_weight.sum(), 0.5 * neg_weight / neg_weight.sum()])
    w, reg = np.zeros(x.shape[1]), np.diag([1e-4] * len(marks) + [1e-9])
    for _ in range(30):  # Newton steps on the active rows
        act = t * (x @ w) < 1
        xa, ca = x[act], c[act]
        new = np.linalg.solve((xa * ca[:, None].astype(np.float32)).T @ xa + reg, (xa * (ca * t[act])[:, None]).sum(axis=0))
        done = np.abs(new - w).max() < 1e-6
        w = new
        if done:
            break
    table = (basis @ (half @ w[:-1])).astype(np.float32)
    table[0] = 0
    return ToxicityModel(table, float(w[-1]), np.zeros(5), 0.0)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.1, rounds: int = 100) -> tuple[np.ndarray, float]:
    """Weights and shift of a ridge logistic fit on standardised columns; targets are drawn in from 0 and 1 as the counts allow."""
    bad, good = y.sum(), (1 - y).sum()
    target = np.where(y == 1, (bad + 1) / (bad + 2), 1 / (good + 2))
    mean, dev = x.mean(axis=0), x.std(axis=0) + 1e-6
    z, pull = np.hstack([(x - mean) / dev, np.ones((len(x), 1))]), np.append(np.full(x.shape[1], ridge), 1e-6)
    w = np.zeros(z.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(pull + 1e-9), z.T @ (p - target) + pull * w)
        w -= step
        if np.abs(step).max() < 1e-7:
            break
    return w[:-1] / dev, float(w[-1] - (w[:-1] * mean / dev).sum())


def training_texts(docs: DataFrame, labels: DataFrame, toxic_rows: int, clean_rows: int, most_chars: int = 200_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """About ``toxic_rows`` and ``clean_rows`` labelled (doc_id, text, y) rows whose crc32(id) mod 5 is not 0: those whose id's hash is under a threshold set by the counts.

    At most twice as many can come back, and no text over ``most_chars`` characters, so what the task that trains holds is bounded.
    """
    known = (labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("y")).where("doc_id is not null and y is not null")
             .where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0).groupBy("doc_id").agg(F.max(F.when(F.col("y") == 1, 1).otherwise(0)).alias("y")))
    count = known.agg(F.count_if(F.col("y") == 1).alias("bad"), F.count_if(F.col("y") == 0).alias("good")).first()
    chance = F.shiftrightunsigned(F.xxhash64("doc_id"), 11) / float(2**53)
    side = lambda y, most, n: known.where((F.col("y") == y) & (chance < most / max(n, 1))).limit(2 * most)
    pick = side(1, toxic_rows, count["bad"]).unionByName(side(0, clean_rows, count["good"]))
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(text_col, F.lit("")).alias("text")).where(F.length("text") <= most_chars)
    return texts.join(F.broadcast(pick), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("y").alias("y"))


def training_rows(docs: DataFrame, labels: DataFrame, toxic_rows: int, clean_rows: int, most_chars: int = 200_000, id_col: str = "doc_id", text_col: str = "text") -> list:
    """The rows of ``training_texts`` by doc_id, to look at a small sample; ``fit`` leaves them where they are."""
    return training_texts(docs, labels, toxic_rows, clean_rows, most_chars, id_col, text_col).orderBy("doc_id").collect()


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", toxic_rows: int = 2000, clean_rows: int = 2500, most_chars: int = 200_000) -> ToxicityModel | None:
    """The model of a bounded labelled sample; None without labels of both kinds.

    Tasks turn the texts into bags and one task trains on all bags, so neither texts nor the machine's
    matrices are ever in the driver, which gets the model alone (about 90 kB).
    """
    def bags(batches):
        for b in slices(batches):
            texts = b.column(1).to_pylist()
            marks = np.array([_marks(words_of(t)) for t in texts], dtype=np.uint64).view(np.int64).tolist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(marks, pa.list_(pa.int64())), pa.array(map(bag, texts), pa.list_(pa.string())), b.column(2)], ["doc_id", "marks", "bag", "y"])

    def teach(batches):
        model = train_bags(row for b in slices(batches) for row in zip(*(b.column(c).to_pylist() for c in (1, 2, 3)), strict=True))
        if model is not None:
            cols = ([model.table.tobytes()], pa.binary()), ([model.bias], pa.float64()), ([model.weights.tolist()], pa.list_(pa.float64())), ([model.shift], pa.float64())
            yield pa.RecordBatch.from_arrays([pa.array(*c) for c in cols], ["table", "bias", "weights", "shift"])

    texts = training_texts(docs, labels, toxic_rows, clean_rows, most_chars, id_col, text_col)
    held = texts.mapInArrow(bags, "doc_id long, marks array<long>, bag array<string>, y int").repartition(1).sortWithinPartitions("doc_id")
    got = held.mapInArrow(teach, "table binary, bias double, weights array<double>, shift double").collect()
    return ToxicityModel(np.frombuffer(got[0]["table"], dtype=np.float32), got[0]["bias"], np.array(got[0]["weights"]), got[0]["shift"]) if got else None


def with_scores(docs: DataFrame, model: ToxicityModel | None, text_col: str = "text", out_col: str = "toxicity_score", keep_words: int = 200_000) -> DataFrame:
    """``docs`` with a last column of scores, named ``out_col`` or, where that is taken, the like with more underscores. See ``toxicity_scores``."""
    out_col = free_name(docs, out_col)
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text_col)

    def go(batches):
        model, known = shared.value, {}
        for b in slices(batches):
            score = np.zeros(b.num_rows)
            if model is not None:
                bags = [bag(t or "") for t in b.column(at).to_pylist()]
                every = dict.fromkeys(w for words in bags for w in words)
                new = [w for w in every if w not in known]
                if len(known) + len(new) > keep_words:
                    known.clear()
                    new = list(every)
                if new:
                    known.update(zip(new, model.margins(new).tolist(), strict=True))
                odds = np.array([model.log_odds(np.fromiter(map(known.__getitem__, words), np.float64, len(words))) for words in bags])
                score = 1 / (1 + np.exp(-np.clip(odds, -40, 40)))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score, pa.float64())], [*b.schema.names, out_col])

    return docs.mapInArrow(go, T.StructType([*docs.schema.fields, T.StructField(out_col, T.DoubleType())]))


def toxicity_scores(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", **bounds) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every whole text.

    The model is fitted on about 2000 toxic and 2500 clean labelled rows (parameters of ``fit``); only
    texts and their labels reach it. A text's score is a logistic curve over the largest margins of its
    words, so length does not wash an insult out. Each distinct word is scored once per task, in a table
    of bounded size. One pass, no shuffle of texts. Null and empty texts score like a text without words;
    a null id is never held out; repeated rows repeat; without labels of both kinds every score is 0. An
    empty table gives none. Further columns are not carried.
    """
    model = fit(docs, labels, id_col, text_col, **bounds)
    rows = with_scores(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")), model, "text", "score")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    return rows.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
