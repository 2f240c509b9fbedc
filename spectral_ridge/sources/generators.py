"""Synthetic regression rows of any size, as a Python data source."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..operators.features import cosine_matrix
from ..runtime import ship_package

SCHEMA = "row_id long, features array<double>, target double"


def planted(d: int, rank: int, seed: int) -> np.ndarray:
    """Unit coefficients on the first ``rank`` features, before rotation."""
    x = np.zeros(d)
    x[:rank] = np.random.default_rng([seed, 1]).standard_normal(rank)
    return x / np.linalg.norm(x)


def spread(d: int, rank: int) -> np.ndarray:
    """Standard deviations of the features: exp(-(i / rank)^2)."""
    return np.exp(-((np.arange(d) / rank) ** 2))


def rows_block(start: int, count: int, d: int, rank: int, seed: int, noise_sd: float) -> tuple[np.ndarray, np.ndarray]:
    """Rows start .. start + count: a pure function of seed and block, so a retry repeats them."""
    rng = np.random.default_rng([seed, 2, start])
    a = rng.standard_normal((count, d)) * spread(d, rank)
    b = a @ planted(d, rank, seed) + noise_sd * rng.standard_normal(count)
    return a @ cosine_matrix(d).T, b


class _Block(InputPartition):
    def __init__(self, start: int, count: int):
        self.start, self.count = start, count


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.d = int(options.get("n", 1024)), int(options.get("d", 64))
        self.rank = max(1, int(float(options.get("rank_frac", 0.1)) * self.d))
        self.seed, self.noise = int(options.get("seed", 0)), float(options.get("noise_sd", 2.0))
        self.block = int(options.get("block", 1024))

    def partitions(self) -> list[InputPartition]:
        return [_Block(s, min(self.block, self.n - s)) for s in range(0, self.n, self.block)]

    def read(self, partition: _Block) -> Iterator[pa.RecordBatch]:
        a, b = rows_block(partition.start, partition.count, self.d, self.rank, self.seed, self.noise)
        lists = pa.ListArray.from_arrays(np.arange(len(a) + 1, dtype=np.int32) * self.d, pa.array(a.reshape(-1)))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(partition.start, partition.start + len(a))), lists, pa.array(b)], names=["row_id", "features", "target"])


class GaussianRidgeSource(DataSource):
    """Options: n, d, rank_frac, seed, noise_sd, block (rows per partition)."""

    @classmethod
    def name(cls) -> str:
        return "gaussian_ridge"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def generate_ridge_rows(spark: SparkSession, n: int, d: int, rank_frac: float = 0.1, seed: int = 0, noise_sd: float = 2.0, block: int = 1024) -> DataFrame:
    """(row_id, features, target): normal features of falling spread, rotated by the cosine
    transform; a planted unit coefficient vector; normal noise."""
    ship_package(spark)
    spark.dataSource.register(GaussianRidgeSource)
    return spark.read.format("gaussian_ridge").options(n=n, d=d, rank_frac=rank_frac, seed=seed, noise_sd=noise_sd, block=block).load()
