"""Tables, files, streams and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Columns of the given tables, as Spark DDL.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def load_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    """A given table; with ``columns``, only those are read."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_rows(spark: SparkSession, path: str | None = None, format: str = "parquet", schema: str | T.StructType | None = None, table: str | None = None, **options) -> DataFrame:
    """Rows of a file format (parquet, csv, json, orc, text, avro where its jar is there), of a JDBC
    source, or of a catalog table or view."""
    if table is not None:
        return spark.read.table(table)
    reader = spark.read.format(format).options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    return reader.load(path) if path else reader.load()


def read_libsvm(spark: SparkSession, path: str, width: int) -> DataFrame:
    """(target, sparse) rows of a libsvm file."""
    lines = spark.read.text(path).where("trim(value) <> ''").select(F.split(F.trim("value"), r"\s+").alias("p"))
    pairs = F.filter("p", lambda x, i: (i > 0) & x.contains(":"))
    at = F.transform(pairs, lambda x: F.split(x, ":")[0].cast("int") - 1)
    values = F.transform(pairs, lambda x: F.split(x, ":")[1].cast("double"))
    return lines.select(F.col("p")[0].cast("double").alias("target"), F.struct(at.alias("indices"), values.alias("values")).alias("sparse"), F.lit(width).alias("width"))


def read_stream(spark: SparkSession, path: str | None = None, format: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A stream of files, of the rate source, or of Kafka where its jar is there. Event times
    without a zone become timestamps, which watermarks need."""
    reader = spark.readStream.format(format).options(**options)
    if schema:
        reader = reader.schema(schema)
    df = reader.load(path) if path else reader.load()
    zoned = {f.name: F.col(f.name).cast("timestamp") for f in df.schema.fields if isinstance(f.dataType, T.TimestampNTZType)}
    return df.withColumns(zoned) if zoned else df


def write_sketch(sketches: DataFrame, path: str, version: str) -> str:
    """Sketches under ``path``/version=...; writing a version again replaces it."""
    target = f"{path.rstrip('/')}/version={version}"
    sketches.write.mode("overwrite").parquet(target)
    return target


def read_sketch(spark: SparkSession, path: str, version: str) -> DataFrame:
    return spark.read.parquet(f"{path.rstrip('/')}/version={version}")


def write_predictions(df: DataFrame, path: str, partition_by: tuple[str, ...] = ()) -> None:
    df.write.mode("overwrite").partitionBy(*partition_by).parquet(path)
