"""Connected components of a link table, without gathering links anywhere.

Partitions first reduce their own links by union-find; alternating star steps (each node's larger,
then smaller neighbours move to the smallest) then leave a star per component.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, map_arrow, materialise


def roots(count: int, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """The smallest member of each node's component among 0..count-1."""
    label = np.arange(count)
    while True:
        low = np.minimum(label[left], label[right])
        new = label.copy()
        np.minimum.at(new, label[left], low)
        np.minimum.at(new, label[right], low)
        new = np.minimum(new, new[new])
        while not np.array_equal(new, new[new]):
            new = new[new]
        if np.array_equal(new, label):
            return label
        label = new


def local_stars(left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its component) for the nodes of these links, the smallest left out."""
    names, at = np.unique(np.concatenate([left, right]), return_inverse=True)
    root = names[roots(len(names), at[: len(left)], at[len(left) :])]
    moved = root != names
    return names[moved], root[moved]


#: Links of a task that are reduced together.
REDUCE_LINKS = 1 << 20


def _reduce(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def stars(held: list[np.ndarray]) -> pa.RecordBatch:
        left, right = np.concatenate(held, axis=1)
        return pa.RecordBatch.from_arrays([pa.array(x) for x in local_stars(left, right)], names=["u", "v"])

    held, count = [], 0
    for batch in batches:
        held.append(np.stack([batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (0, 1)]))
        count += batch.num_rows
        if count >= REDUCE_LINKS:
            yield stars(held)
            held, count = [], 0
    if count:
        yield stars(held)


def _all_stars(edges: DataFrame) -> bool:
    """Whether each node has one edge to a smaller node, which itself has none."""
    ends = edges.select(F.col("u").alias("node"), F.lit(1).alias("below"), F.lit(0).alias("above"))
    ends = ends.unionAll(edges.select("v", F.lit(0), F.lit(1)))
    seen = ends.groupBy("node").agg(F.sum("below").alias("below"), F.max("above").alias("above"))
    return seen.where("below > 1 or (below > 0 and above > 0)").isEmpty()


def connected(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for each node of ``links`` (u, v) that is not itself the smallest of its
    component. Null ends and self links are ignored; no links give an empty result. The result is a
    table in the shared folder, for the caller to discard."""
    clean = links.where("u is not null and v is not null and u <> v")
    clean = clean.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v"))
    edges = materialise(map_arrow(clean, _reduce, "u long, v long").distinct(), "links")  # u > v throughout
    for _ in range(max_rounds):
        if _all_stars(edges):
            break
        both = edges.union(edges.select(F.col("v"), F.col("u")).toDF("u", "v"))
        # written first, so that both sides of the join are plain shuffles, and one with a hot node can be split
        nearest = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("w"), F.least("m", "u").alias("m"))
        nearest = materialise(nearest, "links-least")
        large = both.join(nearest, F.col("u") == F.col("w")).where("v > u")
        large = materialise(large.select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), "links-large")
        least = large.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("w"), "m")
        up = F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v"))
        small = large.join(least, F.col("u") == F.col("w")).select(up.alias("u"), F.col("m").alias("v")).distinct()
        before, edges = edges, materialise(small, "links-small")
        discard(before, nearest, large)
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
