"""Range sharding by sampled splitters, with shards of near equal bytes.

Rows are ordered by (MD5 of the text, doc_id), so equal texts lie side by side. A size-weighted
key sample gives quantile boundaries, rows are range-partitioned by them, ranges that turn out
overfull are subdivided with further splitters drawn inside them, and exact byte counts of the
ranges then fix each row's global position. A row's shard follows from the bytes before it, so
the result does not depend on the sample: that only spreads the work.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import discard, materialise, ship_package

_SPACE = 1 << 53


class Splitters:
    """Ascending boundaries on the pair (hash, id)."""

    def __init__(self, hashes: np.ndarray, ids: np.ndarray):
        self.pairs = np.unique(np.stack([hashes, ids], axis=1).astype(np.int64), axis=0)

    def __len__(self) -> int:
        return len(self.pairs)

    def locate(self, hashes: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Boundaries at or below each pair."""
        asked = np.stack([hashes, ids], axis=1).astype(np.int64)
        names, at = np.unique(np.concatenate([self.pairs, asked]), axis=0, return_inverse=True)
        held = np.zeros(len(names) + 1, dtype=np.int64)
        held[at.reshape(-1)[: len(self)] + 1] = 1
        return np.cumsum(held)[at.reshape(-1)[len(self) :] + 1]

    def with_more(self, hashes: np.ndarray, ids: np.ndarray) -> Splitters:
        return Splitters(np.append(self.pairs[:, 0], hashes), np.append(self.pairs[:, 1], ids))


def _arrow_rows(spark: SparkSession, **columns: np.ndarray) -> DataFrame:
    return spark.createDataFrame(pa.table({name: pa.array(x) for name, x in columns.items()}))


def with_range(keyed: DataFrame, splitters: Splitters) -> DataFrame:
    """Rows with ``range``, the number of boundaries at or below their key, by halving in the JVM.

    The boundaries, bounded in number, are two constant arrays of the plan."""
    depth = len(splitters).bit_length()
    if not len(splitters):
        return keyed.withColumn("range", F.lit(0))
    hashes, ids = (F.split(F.lit(",".join(map(str, x.tolist()))), ",").cast("array<bigint>") for x in splitters.pairs.T)

    def halve(low: Column, step: Column) -> Column:
        bound, tie = F.get(hashes, low + step - 1), F.get(ids, low + step - 1)
        below = (bound < F.col("order_hash")) | ((bound == F.col("order_hash")) & (tie <= F.col("order_id")))
        return F.when(below, low + step).otherwise(low)  # null beyond the end

    steps = F.array(*[F.lit(1 << k) for k in reversed(range(depth))])
    return keyed.withColumn("range", F.aggregate(steps, F.lit(0), halve))


def _draw(keyed: DataFrame, per_byte: float, salt: int) -> np.ndarray:
    """Keys as rows (hash, id), each drawn with a chance in proportion to its size; a pure function
    of the row."""
    coin = F.pmod(F.xxhash64("order_hash", "order_id", F.lit(salt)), F.lit(_SPACE)) / F.lit(float(_SPACE))
    drawn = keyed.where(coin < F.col("size") * F.lit(per_byte)).select("order_hash", "order_id").toArrow()
    found = np.stack([drawn.column(k).to_numpy() for k in (0, 1)], axis=1).astype(np.int64)
    return found[np.lexsort((found[:, 1], found[:, 0]))]


def _pick(sample: np.ndarray, parts: int) -> np.ndarray:
    """Quantiles of a sorted sample."""
    if not len(sample) >= parts > 1:
        return sample
    return sample[np.arange(1, parts) * len(sample) // parts]


def key_rows(docs: DataFrame) -> DataFrame:
    """(doc_id, size, text_crc32, order_text, order_hash, order_id) of each row; no text."""
    text = F.coalesce(docs["text"], F.lit(""))
    return docs.select(
        docs["doc_id"].cast("long").alias("doc_id"), (F.octet_length(text).cast("long") + 1).alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.md5(text.cast("binary")).alias("order_text"),
    ).withColumns({"order_hash": F.conv(F.substring("order_text", 1, 15), 16, 10).cast("long"), "order_id": F.coalesce("doc_id", F.lit(-(1 << 62)))})


def shard_documents(
    docs: DataFrame,
    shards: int = 16,
    rows_per_range: int = 200_000,
    min_ranges: int = 256,
    max_ranges: int = 32_768,
    oversample: int = 16,
    rounds: int = 4,
) -> DataFrame:
    """Shards of near equal bytes: (doc_id, size, text_crc32, law, shard, slot, grown_shard).

    A shard's bytes differ from the mean by less than one document. Slots count from 0 without
    gaps in (MD5, doc_id) order. Null text counts as empty; a null doc_id sorts first and is
    returned as null; repeated rows each get a slot of their own; an empty table gives an empty
    result; other columns are ignored. The splitter sample holds about ``oversample`` keys for
    each range and ranges are at most four times ``max_ranges``: some 0.5 million pairs of
    numbers and 0.13 million counts reach the driver at most, as Arrow columns.
    """
    spark = docs.sparkSession
    ship_package(spark)
    keyed = materialise(key_rows(docs), "shard-keys")
    rows, total = keyed.agg(F.count("*"), F.coalesce(F.sum("size"), F.lit(0))).first()
    parts = int(min(max_ranges, max(min_ranges, -(-rows // rows_per_range))))
    splitters = Splitters(*_pick(_draw(keyed, parts * oversample / max(total, 1), 1), parts).T)
    for turn in range(rounds):
        ranged = with_range(keyed, splitters)
        counts = ranged.groupBy("range").agg(F.count("*").alias("n"), F.sum("size").alias("bytes")).toArrow()
        name, n, size = (counts.column(k).to_numpy().astype(np.int64) for k in range(3))
        times = np.maximum(n * parts / max(rows, 1), size * parts / max(total, 1))
        full = (n > 1) & (times > 2)
        if not full.any() or turn == rounds - 1:
            break
        wanted = _arrow_rows(spark, full_range=name[full].astype(np.int32))
        inside = ranged.join(F.broadcast(wanted), F.col("range") == F.col("full_range"), "left_semi")
        inside = inside.withColumn("size", F.col("size") + F.lit(total / max(rows, 1)))
        fresh = _draw(inside, oversample * parts / max(2 * total, 1), 2 + turn)
        where = splitters.locate(*fresh.T)
        cuts = [_pick(fresh[where == r], int(np.ceil(k))) for r, k in zip(name[full], times[full], strict=True)]
        grown = splitters.with_more(*np.concatenate(cuts).T)
        if len(grown) == len(splitters) or len(grown) > 4 * max_ranges:
            break
        splitters = grown

    order = np.argsort(name, kind="stable")
    before = [np.cumsum(x[order]) - x[order] for x in (n, size)]
    offsets = _arrow_rows(spark, at_range=name[order].astype(np.int32), rows_before=before[0], bytes_before=before[1])
    here = Window.partitionBy("range").orderBy("order_text", "order_id", "size")
    upto = here.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    within = ranged.withColumns({"k": F.row_number().over(here) - 1, "b": F.sum("size").over(upto) - F.col("size")})
    placed = within.join(F.broadcast(offsets), F.col("range") == F.col("at_range"))
    shard = F.expr(f"cast(least(((bytes_before + b) * {shards}L) div {max(total, 1)}L, {shards - 1}) as int)")
    rank = F.col("rows_before") + F.col("k")
    placed = materialise(placed.select("doc_id", "size", "text_crc32", rank.alias("rank"), shard.alias("shard")), "shard-placed")
    discard(keyed)
    first = placed.groupBy("shard").agg(F.min("rank").alias("first_rank"))
    slot = F.col("rank") - F.col("first_rank")
    return placed.join(F.broadcast(first), "shard").select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", slot.alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )
