"""Counterfactual-regularised toxicity classifier.

A logistic model over the distinct words of a text and their first letters (hashed) learns from labelled documents. A feature's value is its
smoothed log ratio between the classes, and features that the classes don't tell apart beyond chance have none; so rare words that a class has by
accident weigh little. For every labelled document that names a group,
copies are made with each identity term swapped for another of its kind, and the squared change of the score's log-odds between document and copy is
added to the loss. Group terms so lose the weight they would take from texts in which they happen to occur, and neutral mentions
of a group are not punished.

The model is fitted on a bounded sample: at most about `sample_rows` labelled documents of each class, chosen by hash, outside the held-out
fold; weights make up for the sampling. Features are counted on the cluster, and only those with a value come to the driver with the documents that
hold them: no more than the hashed features there are, whatever the texts' length. Every text is scored whole.

Few toxic labels prove little, so a ridge of 1 / (toxic labels)^2 is added: with fewer than about 25 of them scores stay near the share of toxic labels, and
no text is predicted toxic.

Defined results: null and empty texts, and texts without letters, get the score of the intercept alone; repeated rows score alike; rows that repeat a doc_id
teach once, with the least of their texts; rows of `labels` without
doc_id or label don't count, and a document labelled twice counts as toxic if one label says so; without any label of one class
all scores are the share of toxic labels, or 0 without labels; an empty table gives an empty result. Further columns may have any name.
"""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, held_out, pieces, sampled, table, texts

SAMPLE_ROWS, BITS, BALANCE, RIDGE, STEPS = 4_000, 20, 1.0, 1e-4, 150
#: A feature needs so many documents and standard deviations; pseudo-count of its ratio; letters of the heads; weight of toxic documents.
LEAST_ROWS, LEAST_Z, SMOOTH, HEADS, TOXIC_WEIGHT = 3, 2.5, 2.0, (4, 5), 1.5

#: Identity terms by kind; a term is swapped for the others of its kind.
IDENTITY = {
    "gender": "women men woman man female male girls boys trans nonbinary frauen männer femmes hommes mujeres hombres",
    "religion": "muslim muslims christian christians jewish jews hindu hindus buddhist buddhists sikh catholic protestant atheist islam judaism christianity",
    "origin": "african asian european american mexican chinese indian arab turkish polish french german spanish latino immigrant immigrants refugee refugees native foreigner foreigners",
    "colour": "black white brown",
    "orientation": "gay lesbian bisexual straight queer heterosexual homosexual",
    "age": "old young elderly teenagers",
    "ability": "disabled deaf blind autistic",
}

#: ASCII: letters in lower case, all else but later bytes of UTF-8 a blank.
_LETTERS = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))


def words_of(text: bytes | None) -> set[bytes]:
    return set(text.translate(_LETTERS).split()) if text else set()


def buckets(word: bytes, bits: int = BITS) -> list[int]:
    """Features of a word: the whole, and its first letters if it has more."""
    return [xxhash.xxh3_64_intdigest(word) >> (64 - bits)] + [xxhash.xxh3_64_intdigest(word[:n], n) >> (64 - bits) for n in HEADS if len(word) > n]


def swaps(words: set[bytes], identity: dict[str, str] = IDENTITY) -> list[set[bytes]]:
    """Copies of a text's words: the k-th copy has every identity term replaced by the k-th next term of its kind."""
    kinds = [terms.encode().split() for terms in identity.values()]
    present = [(kind, [t for t in kind if t in words]) for kind in kinds]
    if not any(own for _, own in present):
        return []
    copies = []
    for step in (1, 2, 3):
        new = set(words)
        for kind, own in present:
            new -= set(own)
            new |= {kind[(kind.index(t) + step) % len(kind)] for t in own}
        copies.append(new)
    return copies


@dataclass
class Model:
    """weights: those features that have one; few, as most are dropped when learning."""

    intercept: float
    weights: dict[int, float] = field(default_factory=dict)

    def score(self, words: set[bytes], look: Scorer) -> float:
        z = self.intercept + math.fsum(map(look.__getitem__, words))
        return 1 / (1 + math.exp(-z)) if z >= 0 else math.exp(z) / (1 + math.exp(z))


class Scorer(dict):
    """Weights of words, kept between texts."""

    def __init__(self, model: Model, most: int = 200_000):
        super().__init__()
        self.weights, self.most = model.weights, most

    def __missing__(self, word: bytes) -> float:
        if len(self) >= self.most:
            self.clear()
        value = self[word] = math.fsum(self.weights.get(b, 0.0) for b in buckets(word))
        return value


def _sparse(rows: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
    size = np.asarray([len(r) for r in rows], dtype=np.int64)
    return np.repeat(np.arange(len(rows), dtype=np.int32), size), np.asarray([b for r in rows for b in r], dtype=np.int32)


def feature_values(with_it: np.ndarray, without: np.ndarray, toxic: float, clean: float) -> np.ndarray:
    """Each feature's smoothed log ratio from the toxic and clean documents that hold it; 0 where chance may have made it."""
    expected = without * toxic / clean
    z = (with_it - expected) / np.sqrt(with_it + expected * toxic / clean + 1e-9)
    return np.where((np.abs(z) < LEAST_Z) | (with_it + without < LEAST_ROWS), 0.0, np.log((with_it + SMOOTH) / (expected + SMOOTH)))


def train(row: np.ndarray, col: np.ndarray, labels: np.ndarray, weight: np.ndarray, changes: list[tuple[int, list[int], list[int]]], value: np.ndarray, balance: float = BALANCE, ridge: float = RIDGE, steps: int = STEPS) -> Model:
    """Fit by accelerated gradient steps of the loss: log loss, the ridge, and `balance` times the squared changes of the copies' log-odds.

    row, col: document and feature of every word's features. changes: (document, features lost, features won) of each swapped copy. value: of each feature; only features with one
    have a part in anything. The step follows from the largest curvature of the whole loss, penalty included, so the fit settles at any `balance`.
    """
    n, d = len(labels), len(value)
    keep = value[col] != 0
    row, col = row[keep], col[keep]
    x = value[col]
    # Copies as rows of one sparse matrix: features won count up, features lost down.
    lost_row, lost = _sparse([c[1] for c in changes])
    won_row, won = _sparse([c[2] for c in changes])
    c_row, c_col = np.concatenate([won_row, lost_row]), np.concatenate([won, lost])
    c_x = np.concatenate([value[won], -value[lost]])
    weight = weight / weight.sum()
    swap_weight = 2 * balance * weight[[c[0] for c in changes]] if changes else np.zeros(0)
    toxic = float(labels.sum())
    ridge = ridge + 1 / toxic**2

    def curved(u: np.ndarray, b: float) -> tuple[np.ndarray, float]:
        """The loss's largest possible second derivative, times (u, b)."""
        told = 0.25 * weight * (b + np.bincount(row, weights=u[col] * x, minlength=n))
        out = np.bincount(col, weights=told[row] * x, minlength=d) + ridge * u
        if changes:
            out += np.bincount(c_col, weights=(swap_weight * np.bincount(c_row, weights=u[c_col] * c_x, minlength=len(changes)))[c_row] * c_x, minlength=d)
        return out, float(told.sum())

    u, b, top = np.abs(value) / max(1e-12, float(np.linalg.norm(value))), 0.1, 1.0
    for _ in range(30):
        u, b = curved(u, b)
        top = math.sqrt(float(u @ u) + b * b) or 1.0
        u, b = u / top, b / top
    rate = 1 / (1.1 * top)
    u, b = np.zeros(d), math.log((weight @ labels) / (weight @ (1 - labels)))
    last_u, last_b = u, b
    for step in range(steps):
        part = step / (step + 3)
        ahead, ahead_b = u + part * (u - last_u), b + part * (b - last_b)
        odds = ahead_b + np.bincount(row, weights=ahead[col] * x, minlength=n)
        error = weight * (1 / (1 + np.exp(-np.clip(odds, -30, 30))) - labels)
        grad = np.bincount(col, weights=error[row] * x, minlength=d) + ridge * ahead
        if changes:
            change = np.bincount(c_row, weights=ahead[c_col] * c_x, minlength=len(changes))
            grad += np.bincount(c_col, weights=(swap_weight * change)[c_row] * c_x, minlength=d)
        last_u, last_b, u, b = u, b, ahead - rate * grad, ahead_b - rate * float(error.sum())
    kept = np.flatnonzero(u * value)
    return Model(float(b), dict(zip(kept.tolist(), (u * value)[kept].tolist(), strict=True)))


def fit(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, balance: float = BALANCE) -> Model:
    """Learn from `docs` (doc_id, text) and `labels` (doc_id, toxic); the caller leaves the held-out fold out of `labels`."""
    known = labels.where("doc_id IS NOT NULL AND toxic IS NOT NULL").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max((F.col("toxic") > 0).cast("int")).alias("toxic"))
    counts = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if len(counts) < 2:
        rate = float(counts.get(1, 0) > 0)
        return Model(40.0 if rate else -40.0)
    chosen = sampled(known.where("toxic = 0"), F.col("doc_id"), sample_rows, counts[0]).unionByName(sampled(known.where("toxic = 1"), F.col("doc_id"), sample_rows, counts[1]))

    def features(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in pieces(batches):
            out: dict[str, list] = {"row": [], "lost": [], "won": []}
            for text in texts(piece.column("text")):
                words = words_of(text)
                copies = swaps(words)
                out["row"].append(sorted(b for w in words for b in buckets(w)))
                out["lost"].append([sorted(b for w in words - c for b in buckets(w)) for c in copies])
                out["won"].append([sorted(b for w in c - words for b in buckets(w)) for c in copies])
            kinds = [pa.list_(pa.int32()), pa.list_(pa.list_(pa.int32())), pa.list_(pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("toxic"), *[pa.array(v, k) for v, k in zip(out.values(), kinds, strict=True)]], names=["doc_id", "toxic", *out])

    # The chosen labels are as many as the sample bound allows, so they may be sent to all tasks; the texts stay where they are.
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen), "doc_id")
    once = named.groupBy("doc_id").agg(F.max("toxic").alias("toxic"), F.min("text").alias("text"))
    schema = "doc_id long, toxic int, row array<int>, lost array<array<int>>, won array<array<int>>"
    found = cut(once.mapInArrow(features, schema))
    seen = {r["toxic"]: r["n"] for r in found.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if len(seen) < 2:
        return Model(40.0 if seen.get(1) else -40.0)
    by_feature = found.select("toxic", F.explode(F.array_distinct("row")).alias("b")).groupBy("b").agg(F.sum("toxic").alias("toxic"), F.count("*").alias("n")).where(F.col("n") >= LEAST_ROWS).toArrow()
    with_it, held = np.zeros(1 << BITS), np.zeros(1 << BITS)
    at = by_feature.column("b").to_numpy()
    with_it[at], held[at] = by_feature.column("toxic").to_numpy(), by_feature.column("n").to_numpy()
    value = feature_values(with_it, held - with_it, float(seen[1]), float(seen[0]))
    index = np.full(1 << BITS, -1, dtype=np.int32)
    used = np.flatnonzero(value)
    index[used] = np.arange(len(used))
    sent = docs.sparkSession.sparkContext.broadcast(index)

    def valued(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        look = sent.value
        own = lambda bs: [int(k) for k in look[np.asarray(bs, dtype=np.int64)] if k >= 0]
        for batch in batches:
            rows = [own(bs) for bs in batch.column("row").to_pylist()]
            both = [[[own(bs) for bs in copies] for copies in batch.column(c).to_pylist()] for c in ("lost", "won")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("toxic"), pa.array(rows, pa.list_(pa.int32())), *[pa.array(v, pa.list_(pa.list_(pa.int32()))) for v in both]], names=["doc_id", "toxic", "row", "lost", "won"])

    found = found.mapInArrow(valued, schema).toArrow()
    found = found.take(pc.sort_indices(found, sort_keys=[("doc_id", "ascending")]))
    y = found.column("toxic").to_numpy().astype(np.float64)
    weight = np.where(y > 0, TOXIC_WEIGHT * counts[1] / y.sum(), counts[0] / (1 - y).sum())
    size = pc.list_value_length(found.column("row")).to_numpy()
    row, col = np.repeat(np.arange(len(y), dtype=np.int32), size), pc.list_flatten(found.column("row")).to_numpy()
    changes = [(i, a, b) for i, pair in enumerate(zip(found.column("lost").to_pylist(), found.column("won").to_pylist(), strict=True)) for a, b in zip(*pair, strict=True)]
    model = train(row, col, y, weight, changes, value[used], balance=balance)
    return Model(model.intercept, {int(used[k]): w for k, w in model.weights.items()})


def score(docs: DataFrame, model: Model, *keep: str) -> DataFrame:
    """The columns `keep` of `docs`, and score and predicted."""
    return _scored(docs.select(F.struct(*keep).alias("row"), "text"), model).select(*[F.col(f"row.`{c}`").alias(c) for c in keep], "score", "predicted")


def _scored(rows: DataFrame, model: Model) -> DataFrame:
    """(row, score, predicted) of (row, text): what a row carries is handed through, whatever its names."""
    sent = rows.sparkSession.sparkContext.broadcast(model)

    def blocks(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        look = Scorer(m)
        for batch in batches:
            found = [m.score(words_of(t), look) for t in texts(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("row"), pa.array(found, pa.float64()), pa.array([int(s >= 0.5) for s in found], pa.int32())], names=["row", "score", "predicted"])

    return rows.mapInArrow(blocks, f"row {rows.schema['row'].dataType.simpleString()}, score double, predicted int")


def learned(spark: SparkSession, docs: DataFrame, sf_dir: str) -> Model:
    """The model that `docs` and the labels of `sf_dir` give, the held-out fold left out."""
    return fit(docs.select("doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic").where(~held_out(F.col("doc_id"))))


def reject(docs: DataFrame, model: Model) -> DataFrame:
    """`docs`, all columns, without texts that are predicted toxic."""
    scored = _scored(docs.select(F.struct("*").alias("row"), "text"), model)
    return scored.where("predicted = 0").select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    scored = score(docs, learned(spark, docs, sf_dir), "doc_id")
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", "predicted")
