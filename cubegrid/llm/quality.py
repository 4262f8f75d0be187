"""Quality classifier: naive Bayes support vectors over hashed n-gram indicators.

Word uni- and bigrams, and a few shape marks of the whole text, are hashed to indicators. Class
log-count ratios of the training rows scale them; a linear hinge-loss model is then fitted by dual
coordinate descent on the driver over a bounded sample of labelled rows (``fit_rows``, a documented
parameter). Every text is scored whole by an Arrow function that holds only the weight vector.

Defined results: null and empty texts are scored from their shape marks alone. Labels that are
null, or whose document is missing, are not learnt from; a document labelled twice counts twice.
Without labels of both classes every score is 0.5. Only the named columns are used.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import WordIds, fresh, id_crc, mix64, slices, starts_of, tame_arrow, texts

BITS = 18
TOKEN = re.compile(r"\w+|[^\w\s]+")
_UPPER = re.compile(r"[A-Z]")
#: Tokens are hashed in runs of so many characters of text, whatever the length of the text.
PIECE = 1 << 20


@dataclass
class HingeModel:
    weights: np.ndarray  # 2^BITS float32, ratio times hinge weight
    bias: float


def _marks(text: str, n_tokens: int, n_distinct: int) -> list[str]:
    """Names of shape indicators: repetition, capitals, punctuation, length."""
    if not n_tokens:
        return ["\0none"]
    size = len(text)
    upper = len(_UPPER.findall(text)) / size
    return [
        f"\0rep{int(10 * n_distinct / n_tokens)}|{min(12, n_tokens.bit_length())}",
        f"\0up{int(min(9, 20 * upper))}",
        f"\0len{min(16, size.bit_length())}",
        f"\0wl{min(12, int(size / n_tokens))}",
    ]


def features(text: str | None, ids: WordIds) -> np.ndarray:
    """Sorted distinct indicator numbers of a text."""
    text = text or ""
    found = []
    tail = np.zeros(0, np.uint64)
    n = 0
    words = np.zeros(0, np.uint64)
    lo = 0
    while lo < len(text):
        hi = min(len(text), lo + PIECE)
        while hi < len(text) and not text[hi].isspace():  # cut between tokens only
            hi += 1
        h = ids.array(TOKEN.findall(text, lo, hi))
        lo = hi
        n += len(h)
        run = np.concatenate([tail, h])
        tail = h[-1:] if len(h) else tail
        words = np.unique(np.concatenate([words, h]))
        found.append(np.unique(mix64(run[:-1] * np.uint64(0x9E3779B97F4A7C15) + run[1:]) >> np.uint64(64 - BITS)))
    found.append(mix64(words.copy()) >> np.uint64(64 - BITS))
    found.append(mix64(ids.array(_marks(text, n, len(words)))) >> np.uint64(64 - BITS))
    return np.unique(np.concatenate(found)).astype(np.int32)


def log_count_ratio(rows: list[np.ndarray], y: np.ndarray, smooth: float = 1.0) -> np.ndarray:
    def share(part: list[np.ndarray]) -> np.ndarray:
        sums = smooth + np.bincount(np.concatenate(part), minlength=1 << BITS)
        return sums / sums.sum()

    return np.log(share([r for r, k in zip(rows, y, strict=True) if k > 0])) - np.log(share([r for r, k in zip(rows, y, strict=True) if k < 0]))


def dual_coordinate_descent(rows: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, c: float = 1.0, epochs: int = 12, seed: int = 5) -> tuple[np.ndarray, float]:
    """L2-regularised hinge loss: each step solves one sample's dual variable exactly within [0, c]."""
    w = np.zeros(1 << BITS)
    bias = 0.0
    alpha = np.zeros(len(y))
    diag = np.asarray([v @ v + 1.0 for v in values])
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(y)):
            gradient = y[i] * (w[rows[i]] @ values[i] + bias) - 1.0
            new = min(max(alpha[i] - gradient / diag[i], 0.0), c)
            step = new - alpha[i]
            if step:
                alpha[i] = new
                w[rows[i]] += step * y[i] * values[i]
                bias += step * y[i]
                moved = max(moved, abs(step))
        if moved < 1e-3:
            break
    return w, bias


def fit_rows_model(rows: list[np.ndarray], y: np.ndarray) -> HingeModel:
    if not (len(y) and (y > 0).any() and (y < 0).any()):
        return HingeModel(np.zeros(1 << BITS, np.float32), 0.0)
    ratio = log_count_ratio(rows, y)
    values = [ratio[r] for r in rows]
    values = [v / max(1e-9, np.sqrt(v @ v)) for v in values]
    w, bias = dual_coordinate_descent(rows, values, y)
    return HingeModel(np.stack([w * ratio, ratio]).astype(np.float32), bias)


def _indicators(docs: DataFrame, keep: tuple[str, ...], text: str) -> DataFrame:
    own = fresh(list(keep), "text")[0]
    narrow = docs.select(*[F.col(f"`{k}`") for k in keep], F.col(text).alias(own))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = WordIds()
        for part in slices(batches, own):
            rows = [features(t, ids) for t in texts(part, own)]
            held = [part.column(i) for i in range(len(keep))]
            yield pa.RecordBatch.from_arrays([*held, pa.array([r.tobytes() for r in rows], pa.binary())], names=[*keep, "f"])

    return narrow.mapInArrow(run, narrow.drop(own).schema.add("f", "binary"))


def fit(docs: DataFrame, labels: DataFrame, where: Column, label: str = "quality", doc_id: str = "doc_id", text: str = "text", fit_rows: int = 9000) -> HingeModel:
    """Fit on about ``fit_rows`` labelled rows at most, thinned by a hash of the id where there are more."""
    tame_arrow(docs.sparkSession)
    known = labels.where(F.col(label).isin(0, 1) & F.col(doc_id).isNotNull() & where).select(F.col(doc_id).alias("__id"), F.col(label).alias("__y"))
    n = known.count()
    dice = F.pmod(F.xxhash64(F.col("__id").cast("string"), F.lit(23)), F.lit(1 << 20)) / F.lit(float(1 << 20))
    # the sample is bounded by fit_rows, so it may be broadcast
    sample = F.broadcast(known.where(dice < min(1.0, fit_rows / max(1, n))))
    rows = docs.select(F.col(doc_id).alias("__doc"), F.col(text).alias("__body")).join(sample, F.col("__doc") == F.col("__id"))
    got = _indicators(rows, ("__doc", "__y"), "__body").toPandas().sort_values(["__doc", "__y"])
    return fit_rows_model([np.frombuffer(b, np.int32) for b in got["f"]], np.where(got["__y"].to_numpy() == 1, 1.0, -1.0) if len(got) else np.zeros(0))


def score_one(f: np.ndarray, m: HingeModel) -> float:
    if m.weights.ndim == 1:
        return 0.5
    ratio = m.weights[1][f]
    margin = float(m.weights[0][f].sum(dtype=np.float64)) / max(1e-9, float(np.sqrt((ratio * ratio).sum(dtype=np.float64)))) + m.bias
    return float(1.0 / (1.0 + np.exp(-3.0 * np.clip(margin, -100, 100))))


def predict(docs: DataFrame, model: HingeModel, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` plus score (0 to 1) and predicted; no shuffle."""
    spark = docs.sparkSession
    tame_arrow(spark)
    shared = spark.sparkContext.broadcast(model)
    own = fresh(list(keep), "text")[0]
    narrow = docs.select(*[F.col(f"`{k}`") for k in keep], F.col(text).alias(own))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, ids = shared.value, WordIds()
        for part in slices(batches, own):
            score = np.asarray([score_one(features(t, ids), m) for t in texts(part, own)])
            held = [part.column(i) for i in range(len(keep))]
            yield pa.RecordBatch.from_arrays([*held, pa.array(score, pa.float64()), pa.array((score >= 0.5).astype(np.int32))], names=[*keep, "score", "predicted"])

    return narrow.mapInArrow(run, narrow.drop(own).schema.add("score", "double").add("predicted", "integer"))


def is_held_out(doc_id: Column) -> Column:
    return id_crc(doc_id) % 3 == 1


def op9_quality(spark, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    from cubegrid.llm.common import table

    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels"), ~is_held_out(F.col("doc_id")))
    return predict(docs, model).select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
