"""Document quality by Bradley-Terry pairwise ranking.

Preference pairs put a document marked good before one marked bad. The logistic loss on the
difference of their features gives the weights; a quantile of the learned scores is the threshold.
Features are shape statistics of the whole text (characters, words, repetition), so no label,
language, source or id enters a score.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import first_columns, map_arrow, slices, text_bytes

THRESHOLD = 0.3
FEATURES = (
    "log_words", "log_mean_word", "upper", "digit", "symbol", "pipe", "bang", "end_mark", "comma", "quote", "bracket", "other_ascii", "high", "distinct_words", "same_as_previous", "distinct_pairs", "longest_word", "short_words", "log_lines", "distinct_lines", "symbol_words", "upper_words", "top_word", "empty",
)
_GROUPS = [b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"#*$%&<>@^~=+_\\/", b"|", b"!", b".?", b",;:", b"\"'`", b"()[]{}"]


def _class_counts(text: bytes, table: np.ndarray) -> np.ndarray:
    return np.bincount(table[np.frombuffer(text, dtype=np.uint8)], minlength=12)


def _byte_table() -> np.ndarray:
    table = np.full(256, 9, dtype=np.uint8)  # 9: lower-case letters and what else is plain
    table[128:] = 11
    for c in (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D):
        table[c] = 10
    for k, group in enumerate(_GROUPS):
        table[list(group)] = k
    return table


def text_features(text: bytes, table: np.ndarray) -> list[float]:
    """The shape statistics of one whole text."""
    words = text.split()
    n = len(words)
    if not n:
        return [0.0] * (len(FEATURES) - 1) + [1.0]
    counts = _class_counts(text, table)
    solid = max(1, len(text) - int(counts[10]))
    sizes = np.fromiter(map(len, words), np.int32, n)
    numbers: dict[bytes, int] = {}
    ids = np.fromiter((numbers.setdefault(w, len(numbers)) for w in words), np.int64, n)
    pairs = ids[:-1] * n + ids[1:]
    lines = text.split(b"\n")
    marked = int(np.isin(np.frombuffer(b"".join(w[-1:] for w in words), np.uint8), np.frombuffer(b"#*$%&|<>!", np.uint8)).sum())
    upper = sum(map(bytes.isupper, words))
    share = counts / solid
    return [
        np.log1p(n), np.log1p(solid / n), *[np.sqrt(x) for x in share[:9]], np.sqrt(share[9]), np.sqrt(share[11]), len(numbers) / n ** 0.9, float((ids[1:] == ids[:-1]).sum()) / n, len(np.unique(pairs)) / max(1, n - 1), np.log1p(int(sizes.max())), float((sizes <= 2).sum()) / n, np.log1p(len(lines)), len(set(lines)) / len(lines), np.sqrt(marked / n), np.sqrt(upper / n), np.sqrt(int(np.bincount(ids).max()) / n), 0.0,
    ]


def feature_table(docs: DataFrame) -> DataFrame:
    """(doc_id, features array<double>) of each whole text; null text counts as empty."""
    schema = pa.schema([("doc_id", pa.int64()), ("features", pa.list_(pa.float64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _byte_table()
        for part in slices(batches, "text"):
            rows = [text_features(t, table) for t in text_bytes(part.column("text"))]
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(rows, pa.list_(pa.float64()))], schema=schema)

    return map_arrow(first_columns(docs, "doc_id", "text"), run, "doc_id long, features array<double>")


@dataclass
class PairwiseRanker:
    """Weights on standardised features, and the scale that puts the quantile threshold at 0.3."""

    mean: np.ndarray
    spread: np.ndarray
    weights: np.ndarray
    cut: float
    slope: float

    def raw(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.spread, -6, 6) @ self.weights

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.slope * (self.raw(x) - self.cut) + np.log(THRESHOLD / (1 - THRESHOLD))
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def fit_ranker(x: np.ndarray, y: np.ndarray, pairs_per_bad: int = 24, ridge: float = 1e-3, rounds: int = 25) -> PairwiseRanker:
    """Newton steps on the mean logistic loss of feature differences.

    Each bad row meets ``pairs_per_bad`` good ones, taken at even strides, so the pairs are a pure
    function of the rows. With one class only, every weight is 0 and every row counts as good (or
    as bad where all are bad).
    """
    d = x.shape[1]
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y != 1)
    if not len(good) or not len(bad):
        return PairwiseRanker(np.zeros(d), np.ones(d), np.zeros(d), -1.0 if len(good) or not len(bad) else 1.0, 1.0)
    mean, spread = x.mean(axis=0), x.std(axis=0)
    spread = np.where(spread > 1e-9, spread, 1.0)
    z = np.clip((x - mean) / spread, -6, 6)
    steps = np.arange(len(bad))[:, None] * 7919 + np.arange(pairs_per_bad)[None, :] * max(1, len(good) // pairs_per_bad)
    diff = (z[good[steps % len(good)]] - z[bad][:, None, :]).reshape(-1, d)
    w = np.zeros(d)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(np.clip(diff @ w, -60, 60)))  # chance that the pair is ranked wrongly
        gradient = ridge * w - diff.T @ p / len(diff)
        hessian = (diff * (p * (1 - p))[:, None]).T @ diff / len(diff) + ridge * np.eye(d)
        step = np.linalg.solve(hessian, gradient)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    raw = z @ w
    order = np.argsort(raw, kind="stable")
    ranked, bad_so_far = raw[order], np.cumsum(y[order] != 1)
    # quantile levels: reject the first k; the level that classifies the sample best, classes weighed evenly
    k = np.arange(1, len(raw))
    even = bad_so_far[:-1] / len(bad) + (len(good) - (k - bad_so_far[:-1])) / len(good)
    even[ranked[1:] == ranked[:-1]] = -1
    best = int(np.argmax(even))
    cut = float((ranked[best] + ranked[best + 1]) / 2)
    slope = 1.0 / max(1e-6, float(np.median(np.abs(raw - cut)))) * 2
    return PairwiseRanker(mean, spread, w, cut, slope)


def in_training(doc_id: F.Column) -> F.Column:
    """Rows whose labels may be learned from: CRC-32 of the id as text, modulo 5, is not 0."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 != 0


def learn(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000) -> PairwiseRanker:
    """Fit on at most ``max_rows`` labelled training rows, those whose ids hash lowest. An id counts
    once, however often it repeats: with its least label and its least text."""
    known = labels.where(labels["quality"].isNotNull() & labels["doc_id"].isNotNull() & in_training(labels["doc_id"])).select(labels["doc_id"].alias("label_id"), labels["quality"].alias("mark"))
    known = known.groupBy("label_id").agg(F.min("mark").alias("mark")).orderBy(F.xxhash64("label_id"), "label_id").limit(max_rows)
    text = first_columns(docs, "doc_id", "text")
    chosen = text.join(F.broadcast(known), text["doc_id"] == known["label_id"]).groupBy("doc_id").agg(F.min("text").alias("text"))
    features = feature_table(chosen).withColumnRenamed("doc_id", "of")
    rows = features.join(F.broadcast(known), F.col("of") == F.col("label_id")).select("of", "features", "mark").collect()
    rows.sort(key=lambda r: (r[0], r[2], tuple(r[1])))
    x = np.array([r[1] for r in rows], dtype=np.float64).reshape(len(rows), len(FEATURES))
    return fit_ranker(x, np.array([r[2] for r in rows], dtype=np.int64))


def score_documents(docs: DataFrame, model: PairwiseRanker) -> DataFrame:
    """(doc_id, held_out, score, predicted) of each row: ``predicted`` is 1 from a score of 0.3 on.

    Null and empty texts are scored by the feature that marks them; repeated rows get equal
    scores; a null doc_id is returned with held_out null; other columns are ignored.
    """
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _byte_table()
        for part in slices(batches, "text"):
            x = np.array([text_features(t, table) for t in text_bytes(part.column("text"))], dtype=np.float64)
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(model.score(x))], schema=schema)

    scored = map_arrow(first_columns(docs, "doc_id", "text"), run, "doc_id long, score double")
    return scored.select("doc_id", (~in_training(F.col("doc_id"))).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, model: PairwiseRanker) -> DataFrame:
    """Rows of ``docs`` that the ranker accepts, with their own columns."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = _byte_table()
        for part in slices(batches, "text"):
            x = np.array([text_features(t, table) for t in text_bytes(part.column("text"))], dtype=np.float64)
            yield part.filter(pa.array(model.score(x) >= THRESHOLD))

    return map_arrow(docs, run, docs.schema)


def train_on_tables(spark: SparkSession, docs: DataFrame, sf_dir: str, max_rows: int = 20_000) -> PairwiseRanker:
    return learn(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), max_rows)
