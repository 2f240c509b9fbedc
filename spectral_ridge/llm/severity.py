"""Toxicity severity by cumulative-link ordinal regression on sparse text features.

All thresholds share one weight vector: P(grade >= k) = sigmoid(w.x - theta_k). The features are
the presence of words and of word beginnings, those that set toxic and other labelled texts apart
most surely. The labels know toxic or not only, so grades among the toxic ones come from how many
features that point to toxicity a text holds (cut at terciles); the output is the expected grade,
the grade probabilities and the toxic flag.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, first_columns, map_arrow, materialise, slices

#: Turns every character but letters into a blank.
_NOT_LETTERS = re.compile(r"[\W\d_]+")
#: Lengths of the word beginnings that are features too: stems that longer words share.
STEMS = (4, 5, 6, 7)
GRADES = 4


def words_of(text: str) -> set[str]:
    return set(_NOT_LETTERS.sub(" ", text.lower()).split())


def features_of(word: str) -> list[str]:
    """The word itself and its beginnings."""
    return [word, *["^" + word[:n] for n in STEMS if len(word) > n]]


class Vocabulary:
    """Numbers of known features, and those that each word met so far has."""

    def __init__(self, features: list[str]):
        self.at = {f: k for k, f in enumerate(features)}
        self.held: dict[str, tuple[int, ...]] = {}

    def __getstate__(self) -> dict:
        return {"at": self.at, "held": {}}

    def of_word(self, word: str) -> tuple[int, ...]:
        found = self.held.get(word)
        if found is None:
            if len(self.held) > 200_000:
                self.held.clear()
            found = self.held[word] = tuple(self.at[f] for f in features_of(word) if f in self.at)
        return found

    def of_text(self, text: str) -> set[int]:
        return {k for w in words_of(text) for k in self.of_word(w)}


@dataclass
class OrdinalModel:
    """Shared weights over a vocabulary, and the ascending thresholds of the grades."""

    vocabulary: Vocabulary
    weights: np.ndarray
    thresholds: np.ndarray
    cut: float = 0.5  # chance of grade 1 or more from which a text counts as toxic

    def latent(self, texts: list[str]) -> np.ndarray:
        w = self.weights.tolist()
        return np.array([sum(w[k] for k in sorted(self.vocabulary.of_text(t))) for t in texts], dtype=np.float64)

    def at_least(self, texts: list[str]) -> np.ndarray:
        """P(grade >= k) for k = 1.. as columns."""
        z = self.latent(texts)[:, None] - self.thresholds[None, :]
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


class Presence:
    """0/1 features of each row, as the row numbers and feature numbers of the ones."""

    def __init__(self, held: list[list[int]], width: int):
        self.shape = len(held), width
        self.row = np.repeat(np.arange(len(held)), [len(h) for h in held])
        self.at = np.fromiter((k for h in held for k in h), np.int64, len(self.row))

    def dot(self, w: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, weights=w[self.at], minlength=self.shape[0])

    def back(self, r: np.ndarray) -> np.ndarray:
        return np.bincount(self.at, weights=r[self.row], minlength=self.shape[1])


def fit_ordinal(x: Presence, y: np.ndarray, grades: int, ridge: float = 1e-4, rounds: int = 300, rate: float = 0.1) -> tuple[np.ndarray, np.ndarray]:
    """Weights and thresholds by Adam steps on the mean negative log-likelihood (full batch).

    Thresholds are a first value and positive increments, so they stay in order.
    """
    n, d = x.shape
    w, base, gaps = np.zeros(d), np.log((np.sum(y < 1) + 1) / (np.sum(y >= 1) + 1)), np.zeros(grades - 2)
    first, second = np.zeros(d + grades - 1), np.zeros(d + grades - 1)
    rows = np.arange(n)
    for t in range(1, rounds + 1):
        theta = base + np.concatenate([[0.0], np.cumsum(np.exp(gaps))])
        z = x.dot(w)[:, None] - theta[None, :]
        up = 1 / (1 + np.exp(-np.clip(z, -60, 60)))
        padded = np.concatenate([np.ones((n, 1)), up, np.zeros((n, 1))], axis=1)
        p = np.maximum(padded[rows, y] - padded[rows, y + 1], 1e-12)
        slope = np.concatenate([np.zeros((n, 1)), up * (1 - up), np.zeros((n, 1))], axis=1)
        dz = np.zeros((n, grades + 1))
        dz[rows, y] -= slope[rows, y] / p
        dz[rows, y + 1] += slope[rows, y + 1] / p
        dz = dz[:, 1:-1]
        tails = (-dz.sum(axis=0) / n)[::-1].cumsum()[::-1]
        gradient = np.concatenate([x.back(dz.sum(axis=1)) / n + ridge * w, [tails[0]], tails[1:] * np.exp(gaps)])
        first = 0.9 * first + 0.1 * gradient
        second = 0.999 * second + 0.001 * gradient**2
        step = rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-9)
        w, base, gaps = w - step[:d], base - step[d], np.clip(gaps - step[d + 1 :], -6, 6)
    return w, base + np.concatenate([[0.0], np.cumsum(np.exp(gaps))])


def fit_texts(held: list[list[int]], toxic: np.ndarray, vocabulary: Vocabulary, pointing: np.ndarray) -> OrdinalModel:
    """Model of rows of features with 0/1 labels. The labels know no degrees, so a toxic text's
    grade is the tercile of how many features that point to toxicity it holds."""
    x = Presence(held, len(pointing))
    strength = x.dot(pointing.astype(np.float64))
    cuts = np.quantile(strength[toxic], [1 / 3, 2 / 3])
    y = np.where(toxic, 1 + np.searchsorted(cuts, strength, "left"), 0).clip(0, GRADES - 1)
    w, theta = fit_ordinal(x, y.astype(np.int64), GRADES)
    chance = 1 / (1 + np.exp(-np.clip(x.dot(w) - theta[0], -60, 60)))
    return OrdinalModel(vocabulary, w, theta, best_cut(chance, toxic))


def _feature_counts(docs: DataFrame) -> DataFrame:
    """(feature, t, c): in how many toxic and other texts of a slice each feature is."""
    schema = pa.schema([("feature", pa.string()), ("t", pa.int64()), ("c", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            counts: tuple[Counter, Counter] = Counter(), Counter()
            for text, mark in zip(part.column("text").to_pylist(), part.column("mark").to_pylist(), strict=True):
                counts[mark].update({f for w in words_of(text or "") for f in features_of(w)})
            names = list(counts[0] | counts[1])
            columns = [names, [counts[1][f] for f in names], [counts[0][f] for f in names]]
            yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(columns, schema)], schema=schema)

    return map_arrow(docs.select("text", "mark"), run, "feature string, t long, c long")


def learn(docs: DataFrame, labels: DataFrame, max_rows: int = 20_000, vocabulary_size: int = 4096, min_z: float = 1.5) -> OrdinalModel:
    """Fit on at most ``max_rows`` labelled rows (those whose ids hash lowest), with the
    ``vocabulary_size`` features of surest evidence. An id counts once, however often it repeats:
    with its largest label and its least text.

    With no toxic or no other label, the model has no features and calls nothing toxic.
    """
    known = labels.where(labels["toxic"].isin(0, 1) & labels["doc_id"].isNotNull())
    known = known.select(labels["doc_id"].alias("label_id"), labels["toxic"].cast("int").alias("mark"))
    known = known.groupBy("label_id").agg(F.max("mark").alias("mark")).orderBy(F.xxhash64("label_id"), "label_id").limit(max_rows)
    text = first_columns(docs, "doc_id", "text")
    joined = text.join(F.broadcast(known), text["doc_id"] == known["label_id"])
    once = joined.groupBy("label_id", "mark").agg(F.min("text").alias("text"))
    chosen = materialise(once.select("text", "mark"), "severity-sample")
    totals = {r[0]: r[1] for r in chosen.groupBy("mark").count().collect()}
    bad, good = totals.get(1, 0), totals.get(0, 0)
    if not bad or not good:
        discard(chosen)
        return OrdinalModel(Vocabulary([]), np.zeros(0), np.array([20.0] * (GRADES - 1)))
    counts = _feature_counts(chosen).groupBy("feature").agg(F.sum("t").alias("t"), F.sum("c").alias("c"))
    cells = F.col("t") + 0.5, bad - F.col("t") + 0.5, F.col("c") + 0.5, good - F.col("c") + 0.5
    odds = F.log(cells[0] / cells[1]) - F.log(cells[2] / cells[3])
    error = F.sqrt(sum(1 / x for x in cells))
    # by the lower end of the log-odds' interval: a feature that sets the texts apart, not a common one
    ranked = counts.withColumns({"z": odds / error, "sure": F.abs(odds) - 2 * error})
    top = ranked.where(F.abs("z") >= min_z).orderBy(F.desc("sure"), "feature").limit(vocabulary_size).collect()
    vocabulary = Vocabulary([r["feature"] for r in top])
    pointing = np.array([r["z"] >= min_z for r in top], dtype=bool)
    schema = pa.schema([("mark", pa.int32()), ("at", pa.list_(pa.int32()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            at = [sorted(vocabulary.of_text(t or "")) for t in part.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("mark").cast(pa.int32()), pa.array(at, pa.list_(pa.int32()))], schema=schema)

    found = map_arrow(chosen.select("text", "mark"), run, "mark int, at array<int>").toArrow()
    discard(chosen)
    held = sorted(zip(found.column("mark").to_pylist(), found.column("at").to_pylist(), strict=True))
    return fit_texts([at for _, at in held], np.array([m == 1 for m, _ in held]), vocabulary, pointing)


def best_cut(p: np.ndarray, toxic: np.ndarray) -> float:
    """The chance that parts the two classes best, weighed evenly; at most 0.5."""
    order = np.argsort(p, kind="stable")
    ranked, mark = p[order], toxic[order]
    clean_below, toxic_above = np.cumsum(~mark), mark.sum() - np.cumsum(mark)
    even = clean_below[:-1] / max(1, (~mark).sum()) + toxic_above[:-1] / max(1, mark.sum())
    even[ranked[1:] == ranked[:-1]] = -1
    best = int(np.argmax(even)) if len(even) else 0
    return min(0.5, float((ranked[best] + ranked[best + 1]) / 2)) if len(even) and even[best] > 0 else 0.5


def grade_documents(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """(doc_id, severity, p_mild, p_marked, p_severe, grade, toxic) of each whole text.

    ``severity`` is the expected grade, 0 to 3; ``p_*`` the chances of grades of at least 1, 2 and
    3; ``grade`` the largest that is likelier than not; ``toxic`` is 1 from the
    chance of grade 1 or more that parts the training labels best (0.5 at most).
    Null and empty texts have no words and get the grade of a text without known words; repeated
    rows get equal grades; other columns are ignored.
    """
    names = ("severity", "p_mild", "p_marked", "p_severe")
    schema = pa.schema([("doc_id", pa.int64()), *[(n, pa.float64()) for n in names], ("grade", pa.int32()), ("toxic", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            p = model.at_least([t or "" for t in part.column("text").to_pylist()])
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(p.sum(axis=1)), *[pa.array(p[:, k]) for k in range(GRADES - 1)], pa.array((p >= 0.5).sum(axis=1), pa.int32()), pa.array(p[:, 0] >= model.cut).cast(pa.int32())], schema=schema)

    return map_arrow(first_columns(docs, "doc_id", "text"), run, "doc_id long, severity double, p_mild double, p_marked double, p_severe double, grade int, toxic int")
