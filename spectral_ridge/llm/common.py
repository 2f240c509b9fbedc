"""Helpers shared by the operators: shared storage, materialised stages, text slicing."""

from __future__ import annotations

import ctypes
import os
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Folder for intermediate tables where the session names none (tests on one machine).
LOCAL_SHARED_DIR = "file:///tmp/checkpoints/corpus_ops"

#: Text bytes handled by one vectorised step inside a Python worker.
SLICE_BYTES = 1 << 20

#: Bytes in one Arrow batch on its way to a Python worker, at most.
BATCH_BYTES = 2 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` where it is set. Only a
    session on one machine may leave it unset."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named and not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    return (named or LOCAL_SHARED_DIR).rstrip("/")


def ship_package(spark: SparkSession) -> None:
    """Let Python workers import this package from the place the driver imports it from, and
    bound the batches they get by bytes: texts are of any length, so rows are no bound."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    paths = spark.sparkContext.environment.get("PYTHONPATH", "")
    if root not in paths.split(os.pathsep):
        spark.sparkContext.environment["PYTHONPATH"] = os.pathsep.join(p for p in (root, paths) if p)


def materialise(df: DataFrame, label: str, **options: str) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage ends here, and a lost
    executor costs a re-read and not a recomputation."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(*tables: DataFrame) -> None:
    """Delete the files behind tables made by :func:`materialise` that nothing needs any more, and let
    Spark delete the shuffle files of the plans that wrote them: it does so once the driver's JVM has
    collected its garbage, which a driver that only waits for large stages may never need to."""
    for df in tables:
        spark = df.sparkSession
        base = shared_dir(spark).split(":", 1)[-1].lstrip("/")
        jvm = spark.sparkContext._jvm
        for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
            if base in folder:
                path = jvm.org.apache.hadoop.fs.Path(folder)
                path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    if tables:
        tables[0].sparkSession.sparkContext._jvm.System.gc()


def bucket_count(docs: DataFrame, bucket_bytes: int = 16 << 20, least: int = 128) -> int:
    """Buckets, a power of two, for what the texts are made of: each holds that of about
    ``bucket_bytes`` of text."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = least
    while buckets * bucket_bytes < total and buckets < 1 << 22:
        buckets *= 2
    return buckets


def text_bytes(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each string; a null becomes empty bytes."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def slices(batches: Iterator[pa.RecordBatch], column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that each piece holds about ``limit`` bytes of ``column`` at most
    (one row at least), which bounds the memory of vectorised steps."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        start, held = 0, 0
        for i, n in enumerate(sizes.tolist()):
            if held and held + n > limit:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += n + 64
        if start < batch.num_rows:
            yield batch.slice(start)


def give_back() -> None:
    """Return free memory to the system: workers stay alive between tasks and stages."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def map_arrow(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """``mapInArrow`` with the package made importable on the workers first."""
    ship_package(df.sparkSession)

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return df.mapInArrow(task, schema)


def first_columns(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns: further columns, whatever their names, never reach an operator."""
    return df.select(*[df[n] for n in names])
