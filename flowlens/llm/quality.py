"""Ordinal quality: a cumulative-link regression on graded ratings with hashed-text weights shared by all thresholds."""

from __future__ import annotations

import math
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

DIM = 1 << 17
#: Training sample: rated documents at most for each grade. Their whole texts are used, in training and in scoring.
SAMPLE_PER_GRADE = 1500
EPOCHS, STEP, L2 = 60, 0.05, 2e-3
CACHE = 400_000


def slots(word: str) -> list[int]:
    return [zlib.crc32(f.encode("utf-8", "surrogatepass")) % DIM for f in ("w" + word, "p" + word[:4], "e" + word[-3:])]


def words_of(text: str | None) -> tuple[list[str], list[str]]:
    """(distinct words in sorted order, summary words). Summary words say in eighths how far words repeat, how often the same word
    follows itself and how many words hold no letter, and the length in powers of two; they are hashed like any other word."""
    ws = (text or "").lower().split()
    n = max(1, len(ws))
    seen = sorted(set(ws))
    again = sum(map(str.__eq__, ws, ws[1:]))
    bare = sum(not w.isalpha() and not any(c.isalpha() for c in w) for w in seen)
    eighths = (("rep", len(seen) / n), ("again", again / n), ("bare", bare / max(1, len(seen))))
    return seen, [f"\x00{k}{-int(-8 * v // 1)}" for k, v in eighths] + ["\x00len%d" % len(ws).bit_length()]


@dataclass
class Cumulative:
    """P(grade <= k) = logistic(cuts[k] - w.x) with increasing cuts."""

    weights: np.ndarray
    cuts: np.ndarray

    def tails(self, z: np.ndarray) -> np.ndarray:
        """P(grade > k) for every k."""
        return 1 / (1 + np.exp(np.clip(self.cuts[None, :] - z[:, None], -30, 30)))


def fit(texts: list[str], grades: list[int], n_grades: int) -> Cumulative:
    """Penalised maximum likelihood by Adam over the whole sample; cuts are a first cut and positive steps, so they stay ordered."""
    y = np.array(grades, int)
    if not len(y):
        return Cumulative(np.zeros(DIM, np.float32), np.linspace(-1, 1, n_grades - 1))
    docs = [words_of(t) for t in texts]
    vocab = {w: i for i, w in enumerate(sorted({w for d in docs for part in d for w in part}))}
    of = np.array([slots(w) for w in vocab])
    sizes = [len(a) + len(b) for a, b in docs]
    row = np.repeat(np.arange(len(docs)), sizes)
    col = np.fromiter((vocab[w] for d in docs for part in d for w in part), np.int64, len(row))
    # words count by one over the root of their number, summary words in full
    value = np.concatenate([np.concatenate([np.full(len(a), 1 / math.sqrt(max(1, len(a)))), np.ones(len(b))]) for a, b in docs])
    weight = (len(y) / (n_grades * np.maximum(1, np.bincount(y, minlength=n_grades))))[y]
    w, raw = np.zeros(DIM), np.concatenate([[-1.0], np.zeros(n_grades - 2)])
    m1, m2 = [np.zeros_like(w), np.zeros_like(raw)], [np.zeros_like(w), np.zeros_like(raw)]
    for step in range(1, EPOCHS + 1):
        z = np.bincount(row, weights=w[of].sum(1)[col] * value, minlength=len(y))
        _, gz, gr = loss_and_gradients(z, raw, y, weight)
        per_word = np.bincount(col, weights=gz[row] * value, minlength=len(of))
        gw = L2 * w / len(y)
        for j in range(of.shape[1]):
            gw = gw + np.bincount(of[:, j], weights=per_word, minlength=DIM)
        for param, g, a, b in ((w, gw, m1[0], m2[0]), (raw, gr, m1[1], m2[1])):
            a += 0.1 * (g - a)
            b += 0.01 * (g * g - b)
            param -= STEP * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.99**step)) + 1e-10)
    return Cumulative(w.astype(np.float32), ordered_cuts(raw))


def ordered_cuts(raw: np.ndarray) -> np.ndarray:
    """A first cut and the logarithms of the steps to the next ones, as increasing cuts."""
    return np.cumsum(np.concatenate([raw[:1], np.exp(raw[1:])]))


def loss_and_gradients(z: np.ndarray, raw: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Weighted mean of -log P(grade y | z), its gradient by z and by raw (see ordered_cuts)."""
    top, n, cuts = len(raw), len(y), ordered_cuts(raw)
    upper = 1 / (1 + np.exp(-np.clip(np.append(cuts, 60.0)[y] - z, -60, 60)))
    lower = np.where(y > 0, 1 / (1 + np.exp(-np.clip(np.append(-60.0, cuts)[y] - z, -60, 60))), 0.0)
    upper = np.where(y < top, upper, 1.0)
    p = np.maximum(upper - lower, 1e-9)
    du, dl = upper * (1 - upper) / p, lower * (1 - lower) / p
    by_cut = np.bincount(np.minimum(y, top - 1), weights=np.where(y < top, -weight * du / n, 0), minlength=top)
    by_cut = by_cut + np.bincount(np.maximum(y - 1, 0), weights=np.where(y > 0, weight * dl / n, 0), minlength=top)
    later = np.cumsum(by_cut[::-1])[::-1]
    return float(-(weight * np.log(p)).sum() / n), weight * (du - dl) / n, np.concatenate([later[:1], later[1:] * np.exp(raw[1:])])


def grade() -> Column:
    """0 poor, 1 good but toxic, 2 good.

    The table rates by two binary columns; what training wants orders their combinations: poor text is of no use whatever its tone,
    good text that is toxic is of use after its spans are cut, good text as it is. Any other column of whole grades from 0 does as well.
    """
    return F.when(F.col("quality") == 0, 0).when(F.col("toxic") == 1, 1).otherwise(2)


def sample(docs: DataFrame, rated: DataFrame, n_grades: int, id_col: str = "doc_id", text_col: str = "text") -> tuple[list[str], list[int]]:
    """Texts and grades of at most SAMPLE_PER_GRADE documents a grade, those of least hash. rated: (id, grade). Only the
    number of rows is bounded; null texts and rows without an id teach nothing."""
    parts = [rated.where(F.col("grade") == g).select(F.col(id_col).alias("_id"), "grade").distinct().orderBy(F.xxhash64("_id"), "_id").limit(SAMPLE_PER_GRADE) for g in range(n_grades)]
    ids = parts[0]
    for p in parts[1:]:
        ids = ids.unionByName(p)
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_t")).join(F.broadcast(ids), "_id").where("_t is not null").collect()
    rows = sorted((r["_id"], r["_t"], r["grade"]) for r in rows)
    return [t for _, t, _ in rows], [g for _, _, g in rows]


def quality_scores(docs: DataFrame, model: Cumulative, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, expected_grade, tails (P(grade > k) for every k). Whole texts, row by row; null texts count as empty, repeated rows
    repeat their result, null ids stay null, an empty table gives an empty result."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weights, model.cuts))

    def run(batches):
        model, cache = Cumulative(*shared.value), {}
        for b in batches:
            z = np.zeros(b.num_rows)
            for i, t in enumerate(b.column(1)):
                words, summary = words_of(t.as_py())
                for ws, scale in ((words, math.sqrt(max(1, len(words)))), (summary, 1.0)):
                    total = 0.0
                    for w in ws:
                        s = cache.get(w)
                        if s is None:
                            if len(cache) >= CACHE:
                                cache.clear()
                            s = cache[w] = float(model.weights[slots(w)].sum())
                        total += s
                    z[i] += total / scale
            tails = model.tails(z)
            yield pa.record_batch([b.column(0), pa.array(tails.sum(1)), pa.array(tails.tolist(), pa.list_(pa.float64()))], ["doc_id", "expected_grade", "tails"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, "doc_id long, expected_grade double, tails array<double>")


def trained(docs: DataFrame, labels: DataFrame) -> Cumulative:
    rated = labels.where("quality is not null and toxic is not null and doc_id is not null").withColumn("grade", grade())
    return fit(*sample(docs, rated, 3), 3)


def op4_ordinal_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with its expected grade, the probabilities of at least grade 1 and 2, and whether selection keeps it."""
    docs = table(spark, sf_dir, "documents")
    scored = quality_scores(docs, trained(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", "expected_grade", F.col("tails")[0].alias("p_grade_1"), F.col("tails")[1].alias("p_grade_2"), (F.col("tails")[0] >= 0.5).alias("kept"))
