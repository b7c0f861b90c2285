"""Toxicity by multiple-instance learning.

A document is a bag of sentences. A logistic model scores each sentence and the document's score
is their noisy-or, ``1 - prod(1 - p)``. Only documents carry labels; the gradient of the noisy-or
moves the blame to the sentences that explain a label, which are then reported as offending.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupflow.llm.worker_memory import tidy
from groupflow.storage import materialize

_SENTENCE = re.compile(r"[^.!?\n]+[.!?]*")
_WORD = re.compile(r"[^\W_]+")


@dataclass(frozen=True)
class ToxicityParams:
    """The model is fitted on ``sample_docs`` labelled rows at most (smallest hashes of doc_id, in equal
    parts for each label), which have ``sample_chars`` characters at most together. Of their features the
    ``vocabulary`` ones with the most evidence are kept, if their document shares in the two labels differ by so many
    standard errors as makes the fewest errors in cross-validation inside the sample; ``evidence`` lists the choices, and
    equal texts are in one of the ``folds``. Only the features kept reach the driver: less than one number for every two
    characters of the sample for each fold."""

    vocabulary: int = 1200
    evidence: tuple[float, ...] = (3.0, 4.0)
    folds: int = 3
    sample_docs: int = 12000
    sample_chars: int = 60_000_000
    prefix: int = 5
    min_docs: int = 3
    epochs: int = 600
    rate: float = 0.1
    ridge: float = 1e-6
    offending: float = 0.5


@dataclass(frozen=True)
class ToxicityModel:
    features: dict[str, float]
    bias: float
    prefix: int


def sentences(text: str | None) -> list[tuple[int, int]]:
    """Spans of the sentences of a whole text, in code points; white-space ones are left out."""
    return [m.span() for m in _SENTENCE.finditer(text) if not m.group().isspace()] if text else []


def _features(sentence: str, prefix: int) -> set[str]:
    words = _WORD.findall(sentence.lower())
    return {*words, *("^" + w[:prefix] for w in words if len(w) > prefix)}


def _count_features(prefix: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts: dict[tuple[str, int], list[int]] = {}

        def flush() -> pa.RecordBatch:
            out = pa.RecordBatch.from_arrays(
                [
                    pa.array([f for f, _ in counts], pa.string()),
                    pa.array([k for _, k in counts], pa.int32()),
                    pa.array([c[0] for c in counts.values()], pa.int64()),
                    pa.array([c[1] for c in counts.values()], pa.int64()),
                ],
                ["feature", "fold", "n0", "n1"],
            )
            counts.clear()
            return out

        for batch in batches:
            for text, toxic, fold in zip(batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                for f in _features(text.as_py() or "", prefix):
                    counts.setdefault((f, fold), [0, 0])[toxic] += 1
                if len(counts) > 200_000:
                    yield flush()
        if counts:
            yield flush()

    return run


def _bag_rows(features: list[str], prefix: int):
    """For each document its number of sentences, and sentence and feature of each feature found."""
    index = {f: i for i, f in enumerate(features)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, at, what = [], [], []
            for text in batch.column(1):
                t = text.as_py() or ""
                spans = sentences(t)
                found = [(k, index[f]) for k, (a, b) in enumerate(spans) for f in _features(t[a:b], prefix) if f in index]
                found.sort()
                sizes.append(len(spans))
                at.append([k for k, _ in found])
                what.append([f for _, f in found])
            numbers = pa.list_(pa.int32())
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(c) for c in (0, 2, 3)), pa.array(sizes, pa.int32()), pa.array(at, numbers), pa.array(what, numbers)],
                ["doc_id", "toxic", "fold", "n", "at", "what"],
            )

    return run


@dataclass(frozen=True)
class _Bags:
    """Labels of documents, the document of each sentence with features, and sentence and feature of each feature found.

    Sentences without features all score alike; ``blank`` counts them for each document."""

    labels: np.ndarray
    blank: np.ndarray
    owner: np.ndarray
    rows: np.ndarray
    cols: np.ndarray

    @staticmethod
    def of(table: pa.Table) -> _Bags:
        labels, sizes = (table.column(c).to_numpy().astype(np.int64) for c in ("toxic", "n"))
        at, what = (table.column(c).combine_chunks() for c in ("at", "what"))
        first = np.repeat(np.cumsum(sizes) - sizes, at.value_lengths().to_numpy())
        owner = np.repeat(np.arange(len(labels)), sizes)
        return _Bags(labels, np.zeros(len(labels)), owner, at.flatten().to_numpy() + first, what.flatten().to_numpy())

    def part(self, docs: np.ndarray, features: np.ndarray) -> _Bags:
        """The documents of the mask ``docs``; features are renumbered in the order of ``features``, others go."""
        number = np.full(max(self.cols.max(initial=-1), features.max(initial=-1)) + 1, -1)
        number[features] = np.arange(len(features))
        cols = number[self.cols]
        kept = docs[self.owner][self.rows] & (cols >= 0)
        sentence = np.zeros(len(self.owner), bool)
        sentence[self.rows[kept]] = True
        blank = self.blank + np.bincount(self.owner[~sentence], minlength=len(docs))
        rank = lambda mask: np.cumsum(mask) - 1
        return _Bags(self.labels[docs], blank[docs], rank(docs)[self.owner[sentence]], rank(sentence)[self.rows[kept]], cols[kept])

    def scores(self, w: np.ndarray, b: float) -> tuple[np.ndarray, float, np.ndarray]:
        """Scores of sentences with features, of one without, and the noisy-or of documents."""
        z = np.append(b + np.bincount(self.rows, w[self.cols], len(self.owner)), b)
        q = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        each = np.log1p(-np.minimum(q, 1 - 1e-12))
        clean = np.bincount(self.owner, each[:-1], len(self.labels)) + self.blank * each[-1]
        return q[:-1], float(q[-1]), -np.expm1(np.clip(clean, -30, -1e-12))


def _fit(bags: _Bags, n: int, p: ToxicityParams) -> tuple[np.ndarray, float]:
    """Gradient ascent (Adam) on the noisy-or log-likelihood, classes weighted alike."""
    labels = bags.labels
    weight = np.where(labels == 1, 0.5 / max(labels.sum(), 1), 0.5 / max((labels == 0).sum(), 1)) * len(labels)
    w, b = np.zeros(n), -4.0
    m, v = np.zeros(n + 1), np.zeros(n + 1)
    for step in range(1, p.epochs + 1):
        q, q0, prob = bags.scores(w, b)
        # d loglik / d z_s = q_s * (y * (1-P)/P - (1-y))
        pull = weight * np.where(labels == 1, (1 - prob) / prob, -1.0)
        g = q * pull[bags.owner]
        grad = np.append(np.bincount(bags.cols, g[bags.rows], n) / len(labels) - p.ridge * w, (g.sum() + q0 * (bags.blank @ pull)) / len(labels))
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        move = p.rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        w, b = w + move[:-1], b + move[-1]
    return w, float(b)


def _sampled(docs: DataFrame, labels: DataFrame, p: ToxicityParams) -> DataFrame:
    """``doc_id, text, toxic`` of the bounded sample. It is drawn from ids alone and broadcast, so texts are not shuffled."""
    known = (
        labels.filter("toxic in (0, 1) and doc_id is not null")
        .groupBy(F.col("doc_id").cast("long").alias("doc_id"))
        .agg(F.max("toxic").cast("int").alias("toxic"))
    )
    parts = [
        known.filter(F.col("toxic") == label).orderBy(F.xxhash64("doc_id"), "doc_id").limit(p.sample_docs // 2)
        for label in (0, 1)
    ]
    chosen = materialize(parts[0].unionByName(parts[1]), "sample")
    rows = materialize(docs.select(F.col("doc_id").cast("long"), "text").join(F.broadcast(chosen), "doc_id"), "sampled")
    # as many whole texts as the bound allows, in the order of the sample; the window holds the sample only
    order = Window.partitionBy("toxic").orderBy(F.xxhash64("doc_id"), "doc_id", F.xxhash64("text"))
    if (rows.agg(F.sum(F.length("text")).alias("n")).first()["n"] or 0) <= p.sample_chars:
        return rows
    chars = F.sum(F.coalesce(F.length("text"), F.lit(0)).cast("long")).over(order)
    return rows.withColumn("all", chars).filter(F.col("all") <= p.sample_chars // 2).drop("all")


def train(docs: DataFrame, labels: DataFrame, p: ToxicityParams = ToxicityParams()) -> ToxicityModel:
    """Fit on ``docs(doc_id, text)`` and ``labels(doc_id, toxic)``; null labels and ids count for nothing.

    A doc_id with both labels counts as toxic. Without rows of both labels the model knows no
    feature and scores every text alike, near 0.
    """
    fold = F.pmod(F.xxhash64("text"), F.lit(p.folds)).cast("int").alias("fold")
    rows = _sampled(docs, labels, p).select("doc_id", "text", "toxic", fold)
    totals = {(r["toxic"], r["fold"]): r["n"] for r in rows.groupBy("toxic", "fold").agg(F.count("*").alias("n")).collect()}
    if len({label for label, _ in totals}) < 2:
        return ToxicityModel({}, -30.0, p.prefix)
    each = [F.sum(F.when(F.col("fold") == k, F.col(f"n{label}")).otherwise(0)).alias(f"n{label}_{k}") for label in (0, 1) for k in range(p.folds)]
    counts = rows.select("text", "toxic", "fold").mapInArrow(tidy(_count_features(p.prefix)), "feature string, fold int, n0 long, n1 long")
    counts = materialize(counts.groupBy("feature").agg(F.sum(F.col("n0") + F.col("n1")).alias("n"), *each).filter(F.col("n") >= p.min_docs), "features")
    whole, *others = [_selected(counts, totals, left_out, p) for left_out in (None, *range(p.folds))]
    features = sorted({f for found in (whole, *others) for f in found})
    schema = "doc_id long, toxic int, fold int, n int, at array<int>, what array<int>"
    table = rows.mapInArrow(tidy(_bag_rows(features, p.prefix)), schema).toArrow().sort_by([("doc_id", "ascending"), ("n", "ascending")])
    bags, folds, index = _Bags.of(table), table.column("fold").to_numpy(), {f: i for i, f in enumerate(features)}

    def fitted(found: dict[str, float], least: float, docs: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        of = np.array(sorted(index[f] for f, x in found.items() if x >= least), np.int64)
        return of, *_fit(bags.part(docs, of), len(of), p)

    def errors(least: float) -> int:
        wrong = 0
        for k, found in enumerate(others):
            of, w, b = fitted(found, least, folds != k)
            held = bags.part(folds == k, of)
            wrong += int(((held.scores(w, b)[2] >= 0.5) != held.labels).sum())
        return wrong

    # of equal ones the strictest
    least = min(p.evidence, key=lambda e: (errors(e), -e)) if len(p.evidence) > 1 else p.evidence[0]
    of, w, b = fitted(whole, least, np.ones(len(folds), bool))
    return ToxicityModel({features[i]: float(x) for i, x in zip(of, w) if x}, b, p.prefix)


def _selected(counts: DataFrame, totals: dict, left_out: int | None, p: ToxicityParams) -> dict[str, float]:
    """Evidence of the features with the most of it, from all folds but ``left_out``; none if these lack a label."""
    used = [k for k in range(p.folds) if k != left_out]
    n0, n1 = (sum(totals.get((label, k), 0) for k in used) for label in (0, 1))
    if not n0 or not n1:
        return {}
    c, a = (sum((F.col(f"n{label}_{k}") for k in used), F.lit(0)) for label in (0, 1))
    # difference of the two document shares in units of its standard error
    share = (a + c) / (n0 + n1)
    evidence = F.abs(a / n1 - c / n0) / F.sqrt(share * (1 - share) + 1e-12) * math.sqrt(n0 * n1 / (n0 + n1))
    top = counts.filter(a + c >= p.min_docs).select("feature", evidence.alias("evidence")).filter(F.col("evidence") >= min(p.evidence))
    return {r["feature"]: r["evidence"] for r in top.orderBy(F.desc("evidence"), "feature").limit(p.vocabulary).collect()}


def score_text(text: str | None, model: ToxicityModel, offending: float = 0.5) -> tuple[float, list[tuple[int, int]]]:
    """Noisy-or score of one whole text and the spans of its offending sentences."""
    if not text:
        return 0.0, []
    get, prefix = model.features.get, model.prefix
    log_clean, spans = 0.0, []
    base = float(np.log1p(-1 / (1 + np.exp(-model.bias)))) if model.bias > -30 else 0.0
    low = text.lower()
    aligned = len(low) == len(text)
    for a, b in sentences(text):
        words = _WORD.findall(low, a, b) if aligned else _WORD.findall(text[a:b].lower())
        seen: set[str] = set(words)
        seen.update(["^" + w[:prefix] for w in seen if len(w) > prefix])
        z = sum(x for f in seen if (x := get(f)) is not None)
        if z == 0:
            log_clean += base
            continue
        z = min(max(z + model.bias, -30.0), 30.0)
        q = 1 / (1 + np.exp(-z))
        log_clean += float(np.log1p(-min(q, 1 - 1e-12)))
        if q >= offending:
            spans.append((a, b))
    return float(-np.expm1(log_clean)), spans


def score(docs: DataFrame, model: ToxicityModel, p: ToxicityParams = ToxicityParams()) -> DataFrame:
    """``doc_id, score, predicted, offending`` for each row; ``offending`` lists sentence spans.

    A null or empty text has no sentence: score 0. Rows are independent; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [score_text(t.as_py(), shared.value, p.offending) for t in batch.column(1)]
            scores = np.asarray([s for s, _ in out], np.float64)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    pa.array(scores),
                    pa.array((scores >= 0.5).astype(np.int32)),
                    pa.array([[f"{a}:{b}" for a, b in x] for _, x in out], pa.list_(pa.string())),
                ],
                ["doc_id", "score", "predicted", "offending"],
            )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        run, "doc_id long, score double, predicted int, offending array<string>"
    )


def keep_clean(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """The rows of ``docs`` whose text scores below 0.5, in one pass and with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = [score_text(t.as_py(), shared.value)[0] < 0.5 for t in batch.column(at)]
            yield batch.filter(pa.array(clean, pa.bool_()))

    return docs.mapInArrow(tidy(run), docs.schema)
