"""Reading edges from files and streams; writing result tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src long, dst long"


def _split_place():
    """An id of a row of a row-based file: its file split and its place among the task's rows (stable
    over retries of the same read)."""
    return F.concat_ws("#", F.input_file_name(), F.input_file_block_start().cast("string"), F.monotonically_increasing_id().cast("string"))


def read_edges(spark: SparkSession, path: str, format: str = "parquet", src: str = "src", dst: str = "dst", key: list[str] | None = None, separator: str = r"\s+") -> DataFrame:
    """(eid, u, v) from parquet, csv (header), json or text pair lines; only the named columns are
    read.  Without ``key`` columns, eid is the row's place in its file."""
    if format == "text":
        raw = spark.read.text(path).where(~F.col("value").startswith("#"))
        parts = F.split(F.trim("value"), separator)
        df = raw.select(F.element_at(parts, 1).cast("long").alias(src), F.element_at(parts, 2).cast("long").alias(dst))
        if key is not None:
            raise ValueError("pair lines hold no key columns")
        df = df.withColumn("_eid", _split_place())
    elif format == "parquet":
        df = spark.read.parquet(path)
        if key is None:
            df = df.select("*", F.concat_ws("#", F.col("_metadata.file_path"), F.col("_metadata.row_index").cast("string")).alias("_eid"))
    else:
        schema = f"{src} long, {dst} long" + "".join(f", {c} string" for c in key or [])
        reader = spark.read.schema(schema)
        df = (reader.option("header", True).csv(path) if format == "csv" else reader.json(path))
        if key is None:
            df = df.withColumn("_eid", _split_place())
    eid = F.col("_eid") if key is None else F.concat_ws("|", *(F.col(c).cast("string") for c in key))
    return df.select(eid.alias("eid"), F.col(src).cast("long").alias("u"), F.col(dst).cast("long").alias("v")).where("u <> v")


def stream_edges(spark: SparkSession, path: str, schema: str, src: str, dst: str, key: list[str], format: str = "parquet", files_per_trigger: int = 1) -> DataFrame:
    """A streaming (eid, u, v, ts if there) from new files of a folder."""
    df = spark.readStream.format(format).schema(schema).option("maxFilesPerTrigger", files_per_trigger).load(path)
    more = [F.col("ts")] if "ts" in df.columns else []
    return df.select(F.concat_ws("|", *(F.col(c).cast("string") for c in key)).alias("eid"), F.col(src).cast("long").alias("u"), F.col(dst).cast("long").alias("v"), *more).where("u <> v")


def rate_edges(spark: SparkSession, rows_per_second: int, n: int) -> DataFrame:
    """A load stream of hashed edges over n vertices."""
    df = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    end = lambda tag: F.pmod(F.xxhash64("value", F.lit(tag)), F.lit(n))
    return df.select(F.col("value").cast("string").alias("eid"), end(1).alias("u"), end(2).alias("v"), F.col("timestamp").alias("ts")).where("u <> v")


def write_table(df: DataFrame, path: str, format: str = "parquet", partition_by: list[str] | None = None, mode: str = "overwrite") -> None:
    w = df.write.format(format).mode(mode)
    if format == "csv":
        w = w.option("header", True)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def bucketed(edges: DataFrame, table: str, buckets: int) -> DataFrame:
    """Stores edges bucketed by tail, so that repeated exact runs join without shuffling them."""
    edges.write.mode("overwrite").bucketBy(buckets, "u").sortBy("u").saveAsTable(table)
    return edges.sparkSession.table(table)
