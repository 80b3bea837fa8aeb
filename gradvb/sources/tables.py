"""Reading and writing tables: given ones, user files, tile stores, buckets, traces and streams."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_observations(spark: SparkSession, path: str, fmt: str = "parquet", schema: StructType | str | None = None, **options) -> DataFrame:
    """User data in csv, json, orc, text or parquet; text formats want a schema, which spares a pass to infer it."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def register_views(spark: SparkSession, sf_dir: str, names: Iterable[str] = TABLES) -> None:
    for name in names:
        load_table(spark, sf_dir, name).createOrReplaceTempView(name)


def write_store(df: DataFrame, path: str, sort: str | None = "row_idx") -> None:
    """One folder per tile; rows sorted within tiles, so that Parquet statistics skip row groups."""
    laid = df.repartition("tile")
    (laid.sortWithinPartitions("tile", sort) if sort else laid).write.mode("overwrite").partitionBy("tile").parquet(path)


def read_tiles(spark: SparkSession, path: str, tiles: Iterable[int] | None = None) -> DataFrame:
    """The store, or some of its tiles: the literal list prunes folders before anything is read."""
    df = spark.read.parquet(path)
    return df if tiles is None else df.where(F.col("tile").isin([int(t) for t in tiles]))


def write_bucketed(df: DataFrame, key: str, buckets: int, name: str) -> None:
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def append_trace(spark: SparkSession, path: str, rows: list[dict], schema: str) -> None:
    spark.createDataFrame([tuple(r.values()) for r in rows], schema).coalesce(1).write.mode("append").parquet(path)


def save_result(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite") -> None:
    df.write.mode(mode).format(fmt).save(path)


def draws_frame(spark: SparkSession, theta, eps=None) -> DataFrame:
    """A small table of draws: (draw_id, theta, eps)."""
    eps = theta if eps is None else eps
    return spark.createDataFrame([(k, [float(v) for v in t], [float(v) for v in e]) for k, (t, e) in enumerate(zip(theta, eps, strict=True))], "draw_id int, theta array<double>, eps array<double>")


def table_sample_sql(spark: SparkSession, name: str, percent: float, seed: int) -> DataFrame:
    return spark.sql(f"SELECT * FROM {name} TABLESAMPLE ({percent} PERCENT) REPEATABLE ({int(seed)})")


def stream_table(spark: SparkSession, sf_dir: str, name: str, files_per_trigger: int = 1) -> DataFrame:
    """A given table as a stream of its files."""
    schema = load_table(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", f"{name}*.parquet").parquet(sf_dir)


def explain_text(df: DataFrame, mode: str = "formatted") -> str:
    """The physical plan as text, for tests of pushdown and of joins."""
    return df.sparkSession._jvm.PythonSQLUtils.explainString(df._jdf.queryExecution(), mode)
