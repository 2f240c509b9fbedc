"""Insertion-only streams: a global sketch per micro-batch ledger, per-key state, windows."""

from __future__ import annotations

import copy
import pickle
from collections.abc import Callable, Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators.design import RidgeSpec, design_rows, usable
from ..operators.fit import fit_sketch, merge_sketches, sketch_schema
from ..operators.relational import count_sketch
from ..operators.solve import solve
from ..runtime import ship_package
from ..sketch import SketchRow, make_sketcher


class SketchLedger:
    """The state of a stream's sketch as a table: one sketch per micro-batch id, each the merge of
    all up to it. A batch id that is there already is skipped, so a replay changes nothing.

    ``keep`` versions stay; state is a few sketch rows however long the stream runs.
    """

    def __init__(self, spark: SparkSession, path: str, keep: int = 2):
        self.spark, self.path, self.keep = spark, path.rstrip("/"), keep

    def _fs(self):
        jvm = self.spark.sparkContext._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        return root.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), root, jvm

    def versions(self) -> list[int]:
        """Batch ids whose write was completed, in order."""
        fs, root, jvm = self._fs()
        if not fs.exists(root):
            return []
        done = [s.getPath() for s in fs.listStatus(root) if fs.exists(jvm.org.apache.hadoop.fs.Path(s.getPath(), "_SUCCESS"))]
        return sorted(int(p.getName().removeprefix("batch=")) for p in done)

    def current(self) -> DataFrame | None:
        found = self.versions()
        return self.spark.read.parquet(f"{self.path}/batch={found[-1]}") if found else None

    def commit(self, batch_id: int, fresh: DataFrame, by: Sequence[str], method: str, fan_in: int = 16, **options) -> bool:
        """Merge a micro-batch's sketches with the stored ones; False for a replayed batch."""
        found = self.versions()
        if found and batch_id <= found[-1]:
            return False
        stored = self.current()
        named = fresh.withColumn("part_id", F.lit(1).cast("long"))
        if stored is not None:
            named = stored.withColumn("part_id", F.lit(0).cast("long")).unionByName(named)
        merge_sketches(named, tuple(by), fan_in, 2, method, **options).write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")
        fs, _, jvm = self._fs()
        for old in self.versions()[: -self.keep]:
            fs.delete(jvm.org.apache.hadoop.fs.Path(f"{self.path}/batch={old}"), True)
        return True


def _kernel_options(options: dict) -> dict:
    """Options of the sketch itself, without those of the fit around it."""
    return {k: v for k, v in options.items() if k not in ("seed", "merge_fan_in", "partitions", "deterministic_order")}


def stream_sketch(stream: DataFrame, spec: RidgeSpec, method: str, ell: int, ledger: SketchLedger, checkpoint: str, on_batch: Callable[[int, DataFrame], None] | None = None, available_now: bool = True, trigger_seconds: int = 10, **options):
    """Start the query that folds each micro-batch into the ledger's sketch.

    ``on_batch`` gets (batch id, current sketch) after each commit: an answer at any time.
    """
    def step(rows: DataFrame, batch_id: int) -> None:
        fresh = fit_sketch(rows, spec, method, ell, **options)
        if ledger.commit(batch_id, fresh, spec.group_by, method, **_kernel_options(options)) and on_batch is not None:
            on_batch(batch_id, ledger.current())

    writer = stream.writeStream.foreachBatch(step).option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer.trigger(processingTime=f"{trigger_seconds} seconds")).start()


def anytime_solution(ledger: SketchLedger, gamma: float | Sequence[float], by: Sequence[str] = ()) -> DataFrame | None:
    """Coefficients from the latest committed sketch."""
    current = ledger.current()
    return None if current is None else solve(current, gamma, by=by)


def windowed_sketches(rows: DataFrame, spec: RidgeSpec, method: str, ell: int, time: str, length: str, slide: str | None = None, **options) -> DataFrame:
    """One sketch per event-time window (batch twin of the streaming one).

    Panes are folded where their rows are; a sliding window is the merge of its panes, so a row
    is folded once however many windows hold it.
    """
    pane = slide or length
    cut = F.window(F.col(time).cast("timestamp"), pane)
    panes = rows.withColumn("pane_start", cut["start"])
    inner = RidgeSpec(spec.features, spec.target, spec.row_id, (*spec.group_by, "pane_start"), spec.on_invalid, spec.fit_intercept, spec.n_features)
    sketches = fit_sketch(panes, inner, method, ell, **options)
    if slide is None or slide == length:
        return sketches.withColumnRenamed("pane_start", "window_start")
    starts = F.expr(f"sequence(pane_start - INTERVAL {length} + INTERVAL {slide}, pane_start, INTERVAL {slide})")
    spread = sketches.withColumn("window_start", F.explode(starts)).withColumn("part_id", F.unix_seconds("pane_start")).drop("pane_start")
    ranked = spread.withColumn("part_id", F.pmod(F.col("part_id"), F.lit(16)).cast("long"))
    return merge_sketches(ranked, (*spec.group_by, "window_start"), 16, 16, method, **_kernel_options(options))


def session_sketches(rows: DataFrame, spec: RidgeSpec, method: str, ell: int, time: str, gap: str, user: str, **options) -> DataFrame:
    """One sketch per user session: sessions are numbered by gaps, then folded like groups."""
    order = Window.partitionBy(user).orderBy(time)
    seconds = F.unix_seconds(F.col(time).cast("timestamp"))
    limit = F.lit(_seconds(gap))
    fresh = (seconds - F.lag(seconds).over(order) > limit) | F.lag(seconds).over(order).isNull()
    numbered = rows.withColumn("session_no", F.sum(fresh.cast("int")).over(order))
    inner = RidgeSpec(spec.features, spec.target, spec.row_id, (user, "session_no"), spec.on_invalid, spec.fit_intercept, spec.n_features)
    return fit_sketch(numbered, inner, method, ell, **options)


def _seconds(gap: str) -> int:
    count, unit = gap.split()
    return int(count) * {"second": 1, "minute": 60, "hour": 3600, "day": 86400}[unit.rstrip("s").lower()]


def keyed_state_sketches(stream: DataFrame, spec: RidgeSpec, method: str, ell: int, key: str, n_features: int, **options) -> DataFrame:
    """A stream of updated sketches per key, each key's sketch held as keyed state.

    Rows arrive as one design row each; the state is the sketch row itself, so it does not grow
    with the stream. Output mode update. Deletions are not defined for these sketches.
    """
    ship_package(stream.sparkSession)
    targets, seed, policy = len(spec.targets), int(options.pop("seed", 0)), spec.on_invalid
    rows = design_rows(stream, RidgeSpec(spec.features, spec.target, spec.row_id, (key,), policy, spec.fit_intercept, n_features))
    schema = sketch_schema(rows, (key,))
    state = T.StructType([T.StructField("sketch", T.BinaryType())])

    def step(name: tuple, frames: Iterator[pd.DataFrame], held) -> Iterator[pd.DataFrame]:
        sketcher = pickle.loads(held.get[0]) if held.exists else make_sketcher(method, ell, n_features, targets, seed, **options)
        for frame in frames:
            x, y, used = usable(np.stack(frame["features"].to_numpy()), np.stack(frame["target"].to_numpy()), policy)
            sketcher.n_skipped += int((~used).sum())
            if len(x):
                sketcher.update(x, y, frame["row_hash"].to_numpy()[used])
        held.update((pickle.dumps(sketcher),))
        row: SketchRow = copy.deepcopy(sketcher).finish()  # finishing flushes: the state goes on unflushed
        yield pd.DataFrame([{key: name[0], **row.to_dict()}])

    return rows.groupBy(key).applyInPandasWithState(step, schema, state, "update", "NoTimeout")


def streaming_count_sketch(stream: DataFrame, key: str, features: Sequence[str], target: str, ell: int, seed: int = 17) -> DataFrame:
    """The count sketch as a native streaming aggregation: no Python state at all."""
    return count_sketch(stream, F.col(key), [F.col(f) for f in features], F.col(target), ell, seed)


def dedup_stream(stream: DataFrame, row_id: str, time: str, delay: str = "1 hour") -> DataFrame:
    """Rows sent twice would count twice in the moments: the first within the watermark stays."""
    return stream.withWatermark(time, delay).dropDuplicatesWithinWatermark([row_id])


def reject_retractions(stream: DataFrame, change: str) -> DataFrame:
    """Rows of a change feed, with an error for any that is not an insertion."""
    ok = F.coalesce(F.lower(F.col(change)).isin("i", "insert", "+i"), F.lit(False))
    return stream.where(F.when(ok, F.lit(True)).otherwise(F.raise_error(F.lit("only insertions can be folded into a sketch")).cast("boolean")))


