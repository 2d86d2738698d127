"""Readers and writers: the given tables, transaction files and pattern files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
LINES = "tid long, item string, qty long, u long"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tables(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {n: table(spark, sf_dir, n) for n in NAMES}


def read_transactions(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """lines from parquet, csv or json files of (tid, item, qty, u), or from text files with a basket a line, `items:utility:utilities` with blanks between.

    Text baskets get ids from their file and position; the given total is checked against the sum of utilities.
    """
    if fmt in ("csv", "json"):
        reader = spark.read.schema(LINES)
        return reader.option("header", True).csv(path) if fmt == "csv" else reader.json(path)
    if fmt == "parquet":
        return spark.read.parquet(path)
    if fmt != "text":
        raise ValueError(f"unknown format {fmt!r}")
    parts = F.split("value", ":")
    rows = spark.read.text(path).where("trim(value) <> '' and not value rlike '^[#%@]'").withColumn("tid", F.monotonically_increasing_id())
    rows = rows.select("tid", F.split(F.trim(parts[0]), r"\s+").alias("items"), F.trim(parts[1]).cast("long").alias("tu"), F.split(F.trim(parts[2]), r"\s+").alias("us"))
    right = (F.size("items") == F.size("us")) & (F.col("tu") == F.aggregate("us", F.lit(0).cast("long"), lambda a, x: a + x.cast("long")))
    rows = rows.withColumn("items", F.when(right, F.col("items")).otherwise(F.raise_error(F.lit("a basket's utilities do not add up")).cast("array<string>")))
    lines = rows.select("tid", F.explode(F.arrays_zip("items", "us")).alias("x"))
    return lines.select("tid", F.col("x.items").alias("item"), F.lit(1).cast("long").alias("qty"), F.col("x.us").cast("long").alias("u"))


def read_thresholds(spark: SparkSession, path: str, fmt: str = "csv") -> DataFrame:
    reader = spark.read.schema("item string, mu long")
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)


def write_patterns(patterns: DataFrame, path: str, fmt: str = "parquet") -> None:
    """Patterns by length: parquet with all columns; csv or json with the key; text lines `items #UTIL: u`."""
    if fmt == "parquet":
        patterns.write.partitionBy("k").parquet(path)
    elif fmt == "text":
        patterns.select(F.concat(F.replace("key", F.lit(","), F.lit(" ")), F.lit(" #UTIL: "), F.col("utility").cast("string")).alias("value")).write.text(path)
    else:
        patterns.drop("items").write.partitionBy("k").option("header", True).format(fmt).save(path)


def write_encoded(enc: DataFrame, name: str, buckets: int = 64) -> None:
    """Encoded baskets as a table bucketed by tid, so that joins by basket need no exchange."""
    enc.write.bucketBy(buckets, "tid").sortBy("tid").mode("overwrite").saveAsTable(name)
