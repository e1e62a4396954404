"""Toxicity grades by cumulative-link ordinal regression on sparse text features.

Grades 0 (clean), 1 and 2 are ordered; one weight vector serves both thresholds: P(grade > k) = s(x.w - cut_k) with
cut_0 < cut_1. The output is the expected severity, P(grade > 0) + P(grade > 1). Features are the hashed distinct words
and word starts of three and five letters of a text. Only features whose
share differs between clean and toxic rows beyond chance (chi-square) get a weight, at most ``MOST_FEATURES``.

Labels tell toxic from clean only; the second grade is therefore a convention and not a measured quality: toxic rows are
split into grades 1 and 2 at the median number of distinct features that the labelled rows themselves mark as toxic
(seen mostly in toxic rows). What is held against labels is the rejection at ``REJECT_AT``.

Parameters that bound the fit: at most ``FIT_ROWS`` labelled rows, the ones with the least hash of their id, and at most
``MOST_FEATURES`` weights, those with the highest chi-square; everything is scored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavefront.llm.workers import give_back, let_go, small_batches

BITS = 18
FIT_ROWS = 6000
REJECT_AT = 0.3
MOST_FEATURES = 512
LEAST_CHI = 30.0
STARTS = (3, 5)
_TRIM = ".,;:!?\"'()[]<>*#%&-_"


def features(text: str) -> tuple[np.ndarray, np.ndarray]:
    """(buckets, how often) of the words and word starts of a whole text."""
    seen: dict[str, int] = {}
    for w in text.lower().split():
        w = w.strip(_TRIM)
        if w:
            seen[w] = seen.get(w, 0) + 1
    found: dict[int, int] = {}
    for w, n in seen.items():
        for key in (w, *(w[:k] + "*" for k in STARTS if len(w) > k)):
            h = xxhash.xxh32_intdigest(key) >> (32 - BITS)
            found[h] = found.get(h, 0) + n
    return np.fromiter(found, np.int64, len(found)), np.fromiter(found.values(), np.float64, len(found))


class Ordinal:
    """Weights and cuts of a proportional-odds model, fitted by full-batch scaled gradient steps."""

    def __init__(self, weights: np.ndarray, cuts: np.ndarray):
        self.weights, self.cuts = weights, cuts

    @classmethod
    def fit(cls, rows: list[np.ndarray], grade: np.ndarray, rounds: int = 25, l2: float = 1e-4) -> Ordinal:
        """Newton steps on the features whose share among graded rows differs beyond chance.

        Both thresholds are binary questions with the same weights; their log-likelihoods are summed, which is convex
        in weights and cuts, and at the optimum the cuts are in order because the questions are nested.
        """
        size, n = 1 << BITS, max(1, len(rows))
        full = np.zeros(size)
        if not len(rows) or grade.max() == 0:
            return cls(full, np.array([20.0, 21.0]))
        at = np.repeat(np.arange(len(rows)), [len(c) for c in rows])
        column = np.concatenate(rows)
        seen = np.bincount(column, minlength=size).astype(float)
        with_grade = np.bincount(column, weights=(grade[at] > 0).astype(float), minlength=size)
        base = float((grade > 0).mean())
        chi = (with_grade - seen * base) ** 2 / np.maximum(seen * base * (1 - base), 1e-9)
        used = np.sort(np.argsort(-np.where(chi >= LEAST_CHI, chi, 0), kind="stable")[:MOST_FEATURES])
        used = used[chi[used] >= LEAST_CHI]
        place = np.full(size, -1)
        place[used] = np.arange(len(used))
        x = np.zeros((len(rows), len(used)))
        inside = place[column] >= 0
        x[at[inside], place[column[inside]]] = 1.0
        above = (grade[:, None] > np.arange(2)[None, :]).astype(float)
        d = len(used)
        t = np.zeros(d + 2)
        ridge = np.append(np.full(d, l2), [1e-9, 1e-9])
        for _ in range(rounds):
            slope, curve = ridge * t, np.diag(ridge)
            z = x @ t[:d]
            for k in range(2):
                p = 1 / (1 + np.exp(-(z - t[d + k])))
                g, h = (p - above[:, k]) / n, p * (1 - p) / n
                slope[:d] += x.T @ g
                slope[d + k] -= g.sum()
                weighted = x.T * h
                curve[:d, :d] += weighted @ x
                curve[:d, d + k] -= weighted.sum(axis=1)
                curve[d + k, :d] -= weighted.sum(axis=1)
                curve[d + k, d + k] += h.sum()
            move = np.linalg.solve(curve + np.eye(d + 2) * 1e-8, slope)
            t -= move * min(1.0, 4.0 / max(np.abs(move).max(), 1e-12))
            if np.abs(move).max() < 1e-4:
                break
        full[used] = t[:d]
        return cls(full, t[d:])

    def severity(self, column: np.ndarray) -> tuple[float, int]:
        """Expected severity and the likeliest grade."""
        z = float(self.weights[column].sum())
        above = 1 / (1 + np.exp(-(z - self.cuts)))
        share = -np.diff(np.concatenate(([1.0], above, [0.0])))
        return float(above.sum()), int(np.argmax(share))


    def least_to_reject(self, reject_at: float) -> float:
        """``reject_at``, but above the severity of a text without any feature: no evidence is no reason to reject."""
        return max(reject_at, float(np.nextafter(self.severity(np.empty(0, np.int64))[0], 2)))


def graded(rows: list[tuple[np.ndarray, np.ndarray]], toxic: np.ndarray) -> np.ndarray:
    """Grades 0, 1, 2 from 0/1 labels: toxic rows with more marked features than their median get 2."""
    size = 1 << BITS
    seen = [np.zeros(size), np.zeros(size)]
    for (c, _), t in zip(rows, toxic, strict=True):
        seen[int(t)][c] += 1
    clean, bad = max(1, int((toxic == 0).sum())), max(1, int(toxic.sum()))
    marked = (seen[1] + 0.5) / bad > 8 * (seen[0] + 0.5) / clean
    marked &= seen[1] >= 3
    many = np.array([int(marked[c].sum()) for c, _ in rows])
    middle = np.median(many[toxic == 1]) if (toxic == 1).any() else 0
    return np.where(toxic == 1, 1 + (many > middle), 0)


def _featured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    let_go()
    for batch in batches:
        rows = [features(t or "") for t in batch.column(0).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(1), pa.array([c.tolist() for c, _ in rows], pa.list_(pa.int32())), pa.array([v.tolist() for _, v in rows], pa.list_(pa.int32()))], names=["toxic", "f", "n"])


def fit_on(docs: DataFrame, labels: DataFrame, rows: int = FIT_ROWS) -> Ordinal:
    known = labels.where("toxic in (0, 1) and doc_id is not null").groupBy(F.col("doc_id").alias("_id")).agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = known.orderBy(F.xxhash64(F.lit(5), "_id"), "_id").limit(rows)
    texts = small_batches(docs).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    joined = texts.join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).where("text is not null")
    # of several texts of one id the one with the least digest, so reruns agree
    joined = joined.groupBy("doc_id").agg(F.min_by("text", F.struct(F.sha2("text", 256), "text")).alias("text"), F.max("toxic").alias("toxic"))
    sample = joined.select("text", "toxic").mapInArrow(_featured, "toxic int, f array<int>, n array<int>").toArrow()
    flat = lambda name, kind: [np.asarray(x.values, kind) for x in sample.column(name)]
    found = list(zip(flat("f", np.int64), flat("n", np.float64), strict=True))
    toxic = np.asarray(sample.column("toxic"), np.int64)
    order = sorted(range(len(found)), key=lambda k: (xxhash.xxh64_intdigest(found[k][0].tobytes()), toxic[k]))
    found, toxic = [found[k] for k in order], toxic[order]
    return Ordinal.fit([c for c, _ in found], graded(found, toxic))


def _scored(model: Ordinal):
    weights, cuts = model.weights.astype(np.float32), model.cuts

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        own = Ordinal(weights.astype(np.float64), cuts)
        for batch in batches:
            found = [own.severity(features(t or "")[0]) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s for s, _ in found], pa.float64()), pa.array([g for _, g in found], pa.int32())], names=["doc_id", "severity", "grade"])
            give_back()

    return run


def grade_documents(docs: DataFrame, labels: DataFrame, reject_at: float = REJECT_AT, fit_rows: int = FIT_ROWS) -> DataFrame:
    """Expected severity of every whole text of ``docs(doc_id, text, ...)``, by a model fitted on ``labels(doc_id, toxic)``.

    Returns ``doc_id, severity (0..2), grade, toxic``, a row for each input row; ``toxic`` is severity >= reject_at. A null or empty text
    has no features, gets the model's base severity and is not toxic. Null or repeated doc_ids are rows like any other; other
    columns are ignored; an empty table gives an empty result. Without any labelled row the model knows nothing and
    calls nothing toxic.
    """
    model = fit_on(docs, labels, fit_rows)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    scored = texts.mapInArrow(_scored(model), "doc_id long, severity double, grade int")
    return scored.withColumn("toxic", F.col("severity") >= model.least_to_reject(reject_at))


def drop_toxic(docs: DataFrame, labels: DataFrame, reject_at: float = REJECT_AT, fit_rows: int = FIT_ROWS) -> DataFrame:
    """The rows of ``docs`` below ``reject_at``, with their own columns; see ``grade_documents`` for odd rows."""
    model = fit_on(docs, labels, fit_rows)
    weights, cuts, place, reject_at = model.weights.astype(np.float32), model.cuts, docs.columns.index("text"), model.least_to_reject(reject_at)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        let_go()
        own = Ordinal(weights.astype(np.float64), cuts)
        for whole in batches:
            for at in range(0, whole.num_rows, 1000):
                batch = whole.slice(at, 1000)
                low = [own.severity(features(str(t) if t is not None else "")[0])[0] < reject_at for t in batch.column(place).to_pylist()]
                yield batch.filter(pa.array(low, pa.bool_()))
            give_back()

    return docs.mapInArrow(run, docs.schema)
