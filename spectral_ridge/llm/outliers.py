"""Quality rules with robust multivariate outliers.

Plain counts of each whole text fail a document by fixed rules first. The others are judged by a
vector of transformed rates against a minimum-covariance-determinant estimate of their language
and source: concentration steps keep the part of a group that lies nearest to the current centre,
and a document whose robust Mahalanobis distance is beyond the cutoff is rejected. A step is one
aggregation: moments by (group, distance bin) merge map-side, and the bins up to the wanted share
give the next centre and scatter, so no group is ever gathered in one task.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from statistics import NormalDist

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, first_columns, map_arrow, materialise, ship_package, slices, text_bytes

#: Smallest spread that counts, per transformed rate: keeps zero-inflated rates from a scatter of 0.
FLOORS = {"v_word": 0.03, "v_symbol": 0.03, "v_dup": 0.12, "v_repeat": 0.12, "v_upper": 0.03, "v_mark": 0.04}
VECTOR = tuple(FLOORS)
P = len(VECTOR)
_PAIRS = [(i, j) for i in range(P) for j in range(i, P)]
_BINS = 24  # distance bins per e-fold


@dataclass(frozen=True)
class OutlierRules:
    """``coverage``: share of a group that the estimate rests on; ``tail``: chance that a document
    from a normal group is rejected; ``first_steps``: steps from each start, ``steps``: the most from
    the best one, until the scatter's log-determinant moves less than ``still``; ``min_group``: smaller groups are judged by the estimate of
    their whole language, and where that is small too, by that of all sound rows. Every sound row
    gets a verdict, however few there are."""

    coverage: float = 0.75
    tail: float = 1e-7
    first_steps: int = 2
    steps: int = 8
    still: float = 0.01
    min_group: int = 100
    min_words: int = 20
    max_repeat_percent: int = 30
    broadcast_groups: int = 20_000


def chi2_quantile(p: float, degrees: int) -> float:
    """Wilson-Hilferty approximation of the chi-square quantile."""
    k = 2 / (9 * degrees)
    return degrees * (1 - k + NormalDist().inv_cdf(p) * math.sqrt(k)) ** 3


def repeated_words(ids: np.ndarray, window: int = 8) -> int:
    """Words that lie in a window of ``window`` words found twice or more."""
    n = len(ids) - window + 1
    if n < 2:
        return 0
    hashed = np.zeros(n, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(window):
            hashed = hashed * np.uint64(0x9E3779B97F4A7C15) + ids[k : k + n].astype(np.uint64) + np.uint64(1)
            hashed ^= hashed >> np.uint64(29)
    ordered = np.sort(hashed)
    if not (ordered[1:] == ordered[:-1]).any():
        return 0
    names, width = ids.astype(np.int64), 1  # exact: names of windows of 1, 2, 4, 8 words
    while width < window:
        pair = names[:-width] * (int(names.max()) + 1) + names[width:]
        names, width = np.unique(pair, return_inverse=True)[1].astype(np.int64), width * 2
    twice = np.bincount(names)[names] > 1
    cover = np.zeros(len(ids) + 1, dtype=np.int64)
    np.add.at(cover, np.flatnonzero(twice), 1)
    np.add.at(cover, np.flatnonzero(twice) + window, -1)
    return int((np.cumsum(cover)[:-1] > 0).sum())


def text_counts(text: bytes) -> tuple[int, int, int, int, int, int, int, int]:
    """(words, word code points, symbols, duplicate lines, repeated words, lines with a word,
    capitals, marks) of one whole text in UTF-8; words end at ASCII white space only."""
    words = text.split()
    if not words:
        return 0, 0, 0, 0, 0, 0, 0, 0
    solid = b"".join(words)
    count = np.bincount(np.frombuffer(solid, dtype=np.uint8), minlength=256)
    points = len(solid) - int(count[0x80:0xC0].sum())
    symbols = int(count[list(b"#*$%&|<>")].sum())
    lines = [x for x in text.split(b"\n") if x and not x.isspace()] if b"\n" in text else [text]
    numbers: dict[bytes, int] = {}
    ids = np.fromiter((numbers.setdefault(w, len(numbers)) for w in words), np.int64, len(words))
    return len(words), points, symbols, len(lines) - len(set(lines)), repeated_words(ids), len(lines), int(count[65:91].sum()), int(count[list(b"!?;:\"()[]{}")].sum())


def statistics_table(docs: DataFrame, rules: OutlierRules = OutlierRules()) -> DataFrame:
    """Counts, base rules, group names and transformed vector of each row."""
    ints = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    schema = pa.schema([("doc_id", pa.int64()), ("lang", pa.string()), ("source", pa.string()), *[(n, pa.int64()) for n in ints], *[(n, pa.float64()) for n in VECTOR]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, "text"):
            c = np.array([text_counts(t) for t in text_bytes(part.column("text"))], dtype=np.float64).T
            words, chars, symbols, dup, repeat, lines, upper, mark = c
            # rates lean to a common value while the text is short
            vector = [np.log((chars + 275) / (words + 50)), np.sqrt(symbols / (chars + 250)), np.sqrt(dup / (lines + 8)), np.sqrt(repeat / (words + 50)), np.sqrt(upper / (chars + 250)), np.sqrt(mark / (chars + 250))]
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), part.column("lang").cast(pa.string()), part.column("source").cast(pa.string()), *[pa.array(x.astype(np.int64)) for x in c[:5]], *map(pa.array, vector)], schema=schema)

    kinds = ", ".join(["doc_id long, lang string, source string", *[f"{n} long" for n in ints], *[f"{n} double" for n in VECTOR]])
    table = map_arrow(first_columns(docs, "doc_id", "lang", "source", "text"), run, kinds)
    failed = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.max_repeat_percent * F.col("n_words"))
    return table.withColumn("base_failed", failed)


def _named_groups(stats: DataFrame, rules: OutlierRules) -> tuple[DataFrame, DataFrame]:
    """Rows with ``grp``, language and source or the wider pool that judges them where these have
    too few rows; and the sound rows of every group in use: a pool holds all rows of its language,
    or of the table, those of larger groups too."""
    # as JSON, no language or source can be taken for two others, and null is no name
    pair, whole = F.to_json(F.array("lang", "source")), F.to_json(F.array("lang"))
    named = stats.withColumns({"pair": pair, "whole": whole})
    sizes = named.where("not base_failed").groupBy("pair", "whole").agg(F.count("*").alias("n"))
    wholes = sizes.groupBy("whole").agg(F.sum("n").alias("m"))
    pools = sizes.where(F.col("n") < rules.min_group).join(wholes, "whole").select(F.col("pair").alias("small"), F.when(F.col("m") >= rules.min_group, F.col("whole")).otherwise("all").alias("pool"))
    pools = materialise(pools, "outlier-pools")
    near = lambda x: F.broadcast(x) if x.count() <= rules.broadcast_groups else x
    judged = named.join(near(pools), F.col("pair") == F.col("small"), "left").withColumn("grp", F.coalesce("pool", "pair"))
    sound = judged.where("not base_failed")
    members = sound.where("pool is null").select("grp", *VECTOR)
    used = pools.select(F.col("pool").alias("used")).distinct()
    members = members.unionByName(sound.join(near(used), F.col("whole") == F.col("used"), "left_semi").select(F.col("whole").alias("grp"), *VECTOR))
    if not pools.where("pool = 'all'").isEmpty():
        members = members.unionByName(sound.select(F.lit("all").alias("grp"), *VECTOR))
    return judged.drop("pair", "whole", "small", "pool"), members


MODEL = ", ".join(["grp string", "start int", "n long", *[f"m{i} double" for i in range(P)], *[f"p{i}_{j} double" for i, j in _PAIRS], "logdet double"])
#: Starts of each group: medians and quartile spreads, the same with a first step on the nearest
#: half, and plain mean and covariance.
MEDIAN, CORE, WHOLE = range(3)


def _model_row(group: str, start: int, n: int, mean: np.ndarray, cov: np.ndarray) -> list:
    precision = np.linalg.inv(cov)
    return [group, start, n, *mean, *[precision[i, j] * (1 if i == j else 2) for i, j in _PAIRS], float(np.linalg.slogdet(cov)[1])]


def _models(rows: list[list]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=[x.split()[0] for x in MODEL.split(", ")])


def _start(frame: pd.DataFrame) -> pd.DataFrame:
    """Median and quartile spread of each rate, from its histogram."""
    mean, spread = np.zeros(P), np.zeros(P)
    for k, part in frame.sort_values("bin").groupby("k"):
        cum, at = part["n"].cumsum().to_numpy(), part["bin"].to_numpy()
        q = [at[np.searchsorted(cum, f * cum[-1])] * 0.005 for f in (0.25, 0.5, 0.75)]
        mean[k], spread[k] = q[1], (q[2] - q[0]) / 1.349
    floors = np.array(list(FLOORS.values()))
    cov = np.diag(np.maximum(spread, floors) ** 2)
    return _models([_model_row(frame["grp"].iloc[0], k, int(frame["n"].sum()) // P, mean, cov) for k in (MEDIAN, CORE)])


def scatter(held: float, total: float, sums: np.ndarray, squares: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Centre and scatter of the ``held`` rows of ``total`` that lie nearest, from their sums and
    sums of products; floors keep it regular."""
    mean = sums / held
    cov = squares / held - np.outer(mean, mean)
    # consistency: the nearest share of a normal cloud has a smaller scatter than the cloud
    edge = chi2_quantile(min(held / total, 1 - 1e-9), P)
    factor = (held / total) / max(1e-9, _chi2_share(edge, P + 2))
    return mean, cov * max(1.0, factor) + np.diag(np.array(list(FLOORS.values())) ** 2)


def _concentrate(frame: pd.DataFrame, coverage: dict[int, float]) -> pd.DataFrame:
    """Centre and scatter of the nearest bins that hold ``coverage`` of the group."""
    frame = frame.sort_values("bin")
    start = int(frame["start"].iloc[0])
    n = frame["n"].to_numpy(np.float64)
    last = int(np.searchsorted(np.cumsum(n), math.ceil(coverage[start] * n.sum()))) + 1
    inner = frame.iloc[:last]
    squares = np.zeros((P, P))
    for i, j in _PAIRS:
        squares[i, j] = squares[j, i] = inner[f"q{i}_{j}"].sum()
    sums = inner[[f"s{i}" for i in range(P)]].sum().to_numpy(np.float64)
    mean, cov = scatter(n[:last].sum(), n.sum(), sums, squares)
    return _models([_model_row(frame["grp"].iloc[0], start, int(n.sum()), mean, cov)])


def _chi2_share(x: float, degrees: int) -> float:
    k = 2 / (9 * degrees)
    return NormalDist().cdf(((max(x, 0.0) / degrees) ** (1 / 3) - 1 + k) / math.sqrt(k))


def _distance() -> Column:
    total: Column = F.lit(0.0)
    for i, j in _PAIRS:
        total = total + F.col(f"p{i}_{j}") * (F.col(VECTOR[i]) - F.col(f"m{i}")) * (F.col(VECTOR[j]) - F.col(f"m{j}"))
    return total


def _with_model(rows: DataFrame, model: DataFrame, rules: OutlierRules) -> DataFrame:
    """Rows beside their group's model: broadcast while the groups are few, else a salted join, so
    that a group with a third of the rows is spread over many tasks."""
    named = model.withColumnRenamed("grp", "of")
    if model.count() <= rules.broadcast_groups:
        return rows.join(F.broadcast(named), F.col("grp") == F.col("of"), "left")
    salts = 32
    spread = named.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return rows.withColumn("salt", F.pmod(F.xxhash64(*VECTOR), F.lit(salts))).join(spread, (F.col("grp") == F.col("of")) & (F.col("salt") == F.col("part")), "left").drop("salt", "part")


def _moments() -> list[Column]:
    products = [F.sum(F.col(VECTOR[i]) * F.col(VECTOR[j])).alias(f"q{i}_{j}") for i, j in _PAIRS]
    return [F.count("*").alias("n"), *[F.sum(v).alias(f"s{i}") for i, v in enumerate(VECTOR)], *products]


def _step(rows: DataFrame, model: DataFrame, coverage: dict[int, float], rules: OutlierRules) -> DataFrame:
    """The models after one concentration step of every group and start."""
    near = _with_model(rows, model, rules).withColumn("bin", F.floor(F.log(_distance() + 1e-3) * _BINS))
    binned = near.groupBy("grp", "start", "bin").agg(*_moments())

    def step(frame: pd.DataFrame) -> pd.DataFrame:
        return _concentrate(frame, coverage)

    return materialise(binned.groupBy("grp", "start").applyInPandas(step, MODEL), "outlier-step")


def fit_groups(rows: DataFrame, rules: OutlierRules = OutlierRules()) -> DataFrame:
    """One robust model per group of ``rows`` (``grp`` and the vector): a few concentration steps
    from each start, then the start of least determinant goes on until it stands still."""
    ship_package(rows.sparkSession)
    long = rows.select("grp", F.posexplode(F.array(*[F.round(F.col(v) / 0.005).cast("int") for v in VECTOR])).alias("k", "bin"))
    counted = long.groupBy("grp", "k", "bin").agg(F.count("*").alias("n"))
    medians = counted.groupBy("grp").applyInPandas(_start, MODEL)
    whole = rows.groupBy("grp", F.lit(WHOLE).alias("start"), F.lit(0).alias("bin")).agg(*_moments())
    whole = whole.groupBy("grp", "start").applyInPandas(lambda frame: _concentrate(frame, {WHOLE: 1.0}), MODEL)
    model = materialise(medians.unionByName(whole), "outlier-start")
    share = dict.fromkeys((MEDIAN, CORE, WHOLE), rules.coverage)
    for turn in range(rules.first_steps):
        before, model = model, _step(rows, model, share | ({CORE: 0.5} if turn == 0 else {}), rules)
        discard(before)
    least = model.groupBy("grp").agg(F.min_by(F.struct(*model.columns[1:]), F.struct("logdet", "start")).alias("best"))
    best = materialise(least.select("grp", "best.*"), "outlier-best")
    discard(model)
    for _ in range(rules.steps):
        after = _step(rows, best, share, rules)
        old = best.select(F.col("grp").alias("of"), F.col("logdet").alias("old"))
        moved = after.join(old, F.col("grp") == F.col("of")).agg(F.max(F.abs(F.col("logdet") - F.col("old")))).first()[0]
        discard(best)
        best = after
        if moved is None or moved < rules.still:
            break
    return best


def judge_documents(docs: DataFrame, rules: OutlierRules = OutlierRules()) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept,
    distance) of each row.

    ``base_failed``: fewer than 20 words, or over 30 % of them in repeated 8-word windows. ``kept``
    is false for these and for rows beyond the cutoff of their group's robust distance; ``distance``
    is null for base failures. Null text has no words and fails; null languages and sources are
    groups of their own; groups of fewer than 100 sound rows are judged by those of their language,
    or of the table; repeated rows are judged alike; an empty table gives an empty result;
    other columns are ignored.
    """
    stats = materialise(statistics_table(docs, rules), "outlier-stats")
    named, members = _named_groups(stats, rules)
    sound = materialise(members, "outlier-vectors")
    model = fit_groups(sound, rules)
    discard(sound)
    judged = _with_model(named, model, rules).withColumn("distance", F.when(~F.col("base_failed"), _distance()))
    cutoff = chi2_quantile(1 - rules.tail, P)
    kept = ~F.col("base_failed") & F.coalesce(F.col("distance") <= cutoff, F.lit(True))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"), F.round("distance", 6).alias("distance"))
