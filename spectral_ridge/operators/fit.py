"""Fitting: fold each partition into a sketch where its rows are, then merge in a tree.

A Python aggregate has no map-side part in Spark, so the fold is an Arrow map over partitions
and the merge a short chain of small grouped maps: only sketch rows are ever shuffled.
"""

from __future__ import annotations

import re
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..runtime import ship_package
from ..sketch import SketchRow, make_sketcher
from ..sketch.spectral import SparseSpectralSketcher
from .design import RidgeSpec, design_rows, feature_count, flat_matrix, usable

_KINDS = {"string": T.StringType(), "int": T.IntegerType(), "bigint": T.LongType(), "double": T.DoubleType(), "binary": T.BinaryType(), "array<double>": T.ArrayType(T.DoubleType())}
#: Columns of a sketch row and their types.
SKETCH_TYPE = T.StructType([
    T.StructField(name, _KINDS[kind])
    for kind, names in (
        ("string", "method"), ("int", "ell n_features n_targets version"), ("bigint", "n_rows n_skipped"), ("double", "frob_sq target_sq shrink_total dropped_total"), ("int", "n_svd rank"), ("array<double>", "sigma"), ("binary", "basis"), ("array<double>", "cross"), ("binary", "payload"), ("array<double>", "proj_target"), ("double", "residual_mass"), ("bigint", "seed part_id train_ns"),
    )
    for name in names.split()
])
_ARROW = {"string": pa.string(), "int": pa.int32(), "bigint": pa.int64(), "double": pa.float64(), "binary": pa.binary(), "array<double>": pa.list_(pa.float64())}
_COLUMNS = [(f.name, _ARROW[f.dataType.simpleString()]) for f in SKETCH_TYPE.fields]
#: Sketches of groups that one task keeps open before it sends partial ones on, and their bytes.
OPEN_GROUPS = 256
OPEN_BYTES = 128 << 20


def sketch_schema(df: DataFrame, groups: tuple[str, ...]) -> T.StructType:
    return T.StructType([*[df.schema[g] for g in groups], *SKETCH_TYPE.fields])


def _table(keys: list[tuple], rows: list[SketchRow], key_fields: list[pa.Field]) -> pa.Table:
    dicts = [r.to_dict() for r in rows]
    columns = [pa.array([k[i] for k in keys], f.type) for i, f in enumerate(key_fields)] + [pa.array([d[n] for d in dicts], t) for n, t in _COLUMNS]
    return pa.table(columns, names=[*[f.name for f in key_fields], *[n for n, _ in _COLUMNS]])


def fold_batches(batches: Iterator[pa.RecordBatch], method: str, ell: int, width: int, targets: int, groups: int, policy: str, seed: int, options: dict) -> Iterator[pa.RecordBatch]:
    """Fold Arrow batches (groups..., features, target, row_hash) into one sketch per group."""
    part, open_, fields = TaskContext.get().partitionId() if TaskContext.get() else 0, {}, None

    one = 8 * width * (width if method == "exact_ridge" else 2 * ell)
    limit = max(2, min(OPEN_GROUPS, OPEN_BYTES // max(one, 1)))

    def emit(keys: list[tuple]) -> Iterator[pa.RecordBatch]:
        rows = [open_.pop(k).finish(part) for k in keys]
        yield from _table(keys, rows, fields).to_batches()

    for batch in batches:
        if fields is None:
            fields = [batch.schema.field(i) for i in range(groups)]
        if not batch.num_rows:
            continue
        x, whole = flat_matrix(batch.column(groups), width)
        y, _ = flat_matrix(batch.column(groups + 1), targets)
        ids = batch.column(groups + 2).to_numpy(zero_copy_only=False)
        names = list(zip(*[batch.column(i).to_pylist() for i in range(groups)], strict=True)) if groups else None
        if names is None:
            parts = [((), slice(None))]
        else:
            numbers = {k: i for i, k in enumerate(dict.fromkeys(names))}
            at = np.array([numbers[n] for n in names])
            parts = [(k, np.flatnonzero(at == i)) for k, i in numbers.items()]
        for key, rows in parts:
            if key not in open_:
                if len(open_) >= limit:
                    yield from emit(list(open_)[: limit // 2])
                open_[key] = make_sketcher(method, ell, width, targets, seed, **options)
            sketcher = open_[key]
            a, b, used = usable(x[rows], y[rows], policy)
            sketcher.n_skipped += int((~used).sum())
            if len(a):
                sketcher.update(a, b, ids[rows][used])
    if open_:
        yield from emit(list(open_))


def _merge_tables(method: str, groups: int, options: dict):
    def merge(table: pa.Table) -> pa.Table:
        fields = [table.schema.field(i) for i in range(groups)]
        rows = sorted((SketchRow.from_dict(r) for r in table.select([n for n, _ in _COLUMNS]).to_pylist()), key=lambda r: r.part_id)
        first = rows[0]
        key = tuple(table.column(i)[0].as_py() for i in range(groups))
        if len(rows) == 1:
            return _table([key], rows, fields)
        out = make_sketcher(method, first.ell, first.n_features, first.n_targets, first.seed, **options)
        out.merge(rows)
        return _table([key], [out.finish(first.part_id)], fields)

    return merge


#: Numbers of partitions that a plan's text names.
_ASKED = re.compile(r"Repartition(?:ByExpression)? (?:\[.*\], )?(\d+)|splits=Some\((\d+)\)")


def expected_partitions(df: DataFrame) -> int:
    """About how many partitions ``df`` will have, from its plan and the settings: starts no job."""
    spark = df.sparkSession
    cores = spark.sparkContext.defaultParallelism
    plan = df._jdf.queryExecution().optimizedPlan()
    leaves = plan.collectLeaves()
    split = spark._jvm.org.apache.spark.sql.internal.SQLConf.get().filesMaxPartitionBytes()
    total = cores
    for k in range(leaves.size()):
        size = int(str(leaves.apply(k).stats().sizeInBytes()))
        total += cores if size >= 1 << 60 else -(-size // split)  # a table of unknown size
    asked = [int(n) for pair in _ASKED.findall(plan.toString()) for n in pair if n]
    return int(min(1 << 20, max([total, int(spark.conf.get("spark.sql.shuffle.partitions")), *asked])))


def merge_sketches(
    sketches: DataFrame, by: tuple[str, ...] | list[str] = (), fan_in: int = 16, parts: int | None = None, method: str | None = None, **options
) -> DataFrame:
    """One sketch per key from any number of partial ones; lazy where ``method`` is given.

    A tree of grouped merges: each level takes ``fan_in`` neighbours (by part_id) into one, so a
    task holds about that many sketches. Sketches of several sites are merged by giving their
    union; squared norms, moments and removed amounts add up. ``parts`` is how many there are, as
    far as is known: the tree's depth. Where there are more, those whose numbers agree modulo its
    width share a place, and still one sketch comes out.
    """
    by = tuple(by)
    if method is None:
        found = sketches.select("method").limit(1).collect()
        if not found:
            return sketches.select(*by, *SKETCH_TYPE.fieldNames())
        method = found[0][0]
    schema = sketch_schema(sketches, by)
    width = fan_in
    while width < (256 if parts is None else parts):
        width *= fan_in
    current = sketches.select(*by, *SKETCH_TYPE.fieldNames()).withColumn("part_id", F.pmod("part_id", F.lit(width)).cast("long"))
    while width > 1:
        width //= fan_in
        place = F.floor(F.col("part_id") / F.lit(fan_in)).cast("long")
        merged = current.groupBy(*by, place.alias("bucket")).applyInArrow(_merge_tables(method, len(by), options), schema)
        current = merged.withColumn("part_id", place)
    return current


def partial_sketches(df: DataFrame, spec: RidgeSpec, method: str, ell: int, *, seed: int = 0, **options) -> DataFrame:
    """A sketch row for each partition (and group): the first stage of a fit, in one pass."""
    ship_package(df.sparkSession)
    width, groups, targets, policy = feature_count(df, spec), len(spec.group_by), len(spec.targets), spec.on_invalid
    rows = design_rows(df, spec)
    schema = sketch_schema(rows, tuple(spec.group_by))
    if width is None:
        return df.sparkSession.createDataFrame([], schema)
    make_sketcher(method, ell, width, targets, seed, **options)  # wrong options fail here, not in a task

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from fold_batches(batches, method, ell, width, targets, groups, policy, seed, options)

    return rows.mapInArrow(run, schema)


def fit_sketch(df: DataFrame, spec: RidgeSpec, method: str, ell: int, *, batch_rows: int | None = None, seed: int = 0, partitions: int | None = None, merge_fan_in: int = 16, deterministic_order: bool = False, **options) -> DataFrame:
    """One sketch row (one per group of ``spec.group_by``), in one pass over ``df``; lazy.

    ``deterministic_order``: hash rows to ``partitions`` partitions and sort them by id, so that
    equal input gives equal bits however the files were split. Without it, the row order is the
    scan's, and the error guarantee holds just the same. An empty input gives no row.
    """
    if batch_rows is not None and method not in ("exact_ridge", "sign_projection_ridge", "count_sketch_ridge", "srht_ridge"):
        options["batch_rows"] = batch_rows
    if deterministic_order:
        if not spec.ids:
            raise ValueError("deterministic_order needs spec.row_id")
        df = df.repartition(partitions or 1, *spec.ids).sortWithinPartitions(*spec.ids)
    elif partitions:
        df = df.repartition(partitions)
    partial = partial_sketches(df, spec, method, ell, seed=seed, **options)
    parts = partitions or expected_partitions(df)
    return merge_sketches(partial, spec.group_by, merge_fan_in, parts, method, **options)


@dataclass(frozen=True)
class SketchPlan:
    """One of several sketches that a single pass makes."""

    method: str
    ell: int
    seed: int = 0
    options: tuple[tuple[str, object], ...] = ()

    def sketcher(self, width: int, targets: int):
        return make_sketcher(self.method, self.ell, width, targets, self.seed, **dict(self.options))


def fit_many(df: DataFrame, spec: RidgeSpec, plans: Sequence[SketchPlan], fan_in: int = 16) -> DataFrame:
    """(plan, sketch columns...): all sketches of ``plans`` from one pass over ``df``, each merged in
    a tree of its own; lazy. For comparisons: a task holds every plan's sketch at once."""
    ship_package(df.sparkSession)
    width, targets, policy = feature_count(df, spec), len(spec.targets), spec.on_invalid
    schema = T.StructType([T.StructField("plan", T.IntegerType()), *SKETCH_TYPE.fields])
    if width is None:
        return df.sparkSession.createDataFrame([], schema)
    plans, named = list(plans), [pa.field("plan", pa.int32())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId() if TaskContext.get() else 0
        made = [p.sketcher(width, targets) for p in plans]
        seen = False
        for batch in batches:
            if not batch.num_rows:
                continue
            seen = True
            x, _ = flat_matrix(batch.column(0), width)
            y, _ = flat_matrix(batch.column(1), targets)
            x, y, used = usable(x, y, policy)
            for sketcher in made:
                sketcher.n_skipped += int((~used).sum())
                if len(x):
                    sketcher.update(x, y, batch.column(2).to_numpy(zero_copy_only=False)[used])
        if seen:
            for k, sketcher in enumerate(made):
                yield from _table([(k,)], [sketcher.finish(part)], named).to_batches()

    def merge(table: pa.Table) -> pa.Table:
        plan = plans[table.column("plan")[0].as_py()]
        return _merge_tables(plan.method, 1, dict(plan.options))(table)

    slim = RidgeSpec(spec.features, spec.target, spec.row_id, (), policy, spec.fit_intercept, spec.n_features)
    rows, at_most, wide = design_rows(df, slim), expected_partitions(df), fan_in
    while wide < at_most:
        wide *= fan_in
    current = rows.mapInArrow(run, schema).withColumn("part_id", F.pmod("part_id", F.lit(wide)).cast("long"))
    while wide > 1:
        wide //= fan_in
        place = F.floor(F.col("part_id") / F.lit(fan_in)).cast("long")
        current = current.groupBy("plan", place.alias("bucket")).applyInArrow(merge, schema).withColumn("part_id", place)
    return current


def fit_sparse(df: DataFrame, width: int, ell: int, *, features: str = "sparse", target: str = "target", seed: int = 0, fan_in: int = 16, power_steps: int = 4) -> DataFrame:
    """The plain sketch of sparse rows: ``features`` is struct<indices array<int>, values array<double>>."""
    ship_package(df.sparkSession)
    rows = df.select(F.col(features)["indices"].alias("i"), F.col(features)["values"].cast("array<double>").alias("v"), F.col(target).cast("double").alias("t"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId() if TaskContext.get() else 0
        sketcher = SparseSpectralSketcher("fd_ridge", ell, width, 1, seed, power_steps=power_steps)
        for batch in batches:
            at, values = batch.column(0), batch.column(1)
            lengths = np.diff(np.asarray(at.offsets))
            sketcher.update_sparse(lengths, at.flatten().to_numpy(zero_copy_only=False), values.flatten().to_numpy(zero_copy_only=False), batch.column(2).to_numpy(zero_copy_only=False))
        if sketcher.n_rows:
            yield from _table([()], [sketcher.finish(part)], []).to_batches()

    partial = rows.mapInArrow(run, SKETCH_TYPE)
    return merge_sketches(partial, (), fan_in, expected_partitions(df), "fd_ridge")


def collect_sketch(sketches: DataFrame) -> SketchRow:
    """The single sketch of a table, on the driver: ell x n_features numbers at most."""
    rows = sketches.limit(2).collect()
    if len(rows) != 1:
        raise ValueError(f"one sketch expected, {len(rows)} found")
    return SketchRow.from_dict(rows[0].asDict())
