"""Helpers that the text operators have in common: the shared folder, bounded broadcasts, word expressions."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The characters between words: space and the five ASCII controls from tab to carriage return.
SPACES = " \t\n\x0b\f\r"
SPACE_CLASS = r"[\x20\x09-\x0D]"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_folder(spark: SparkSession) -> str:
    """A new folder name below the one that all machines share: spark.checkpoint.dir, or the checkpoint folder set on the context. Without either, local
    sessions get a temporary folder; on a cluster that would lose rows and is an error."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        context = spark.sparkContext
        current = context._jsc.sc().getCheckpointDir()
        if current.isDefined():
            root = current.get()
        elif context.master.startswith("local") and not context.master.startswith("local-cluster"):
            root = tempfile.mkdtemp(prefix="spark-shared-")
            context.setCheckpointDir(root)
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """The rows of df from a Parquet table in the shared folder: cuts the lineage, survives lost executors."""
    spark, path = df.sparkSession, shared_folder(df.sparkSession)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def broadcast_if_small(df: DataFrame, most_rows: int = 100_000) -> DataFrame:
    """df with a broadcast hint if a count proves it to have most_rows rows at most; else unchanged, so joins shuffle."""
    few = df.limit(most_rows + 1).count() <= most_rows
    return F.broadcast(df) if few else df


def unused_prefix(df: DataFrame) -> str:
    """Underscores that no column of df starts with, for columns beside those of the input."""
    prefix = "_"
    while any(c.startswith(prefix) for c in df.columns):
        prefix += "_"
    return prefix


def plain_names(names: list[str], prefix: str) -> list[str]:
    """names with those that hold a dot or backtick replaced by ones behind the prefix: functions over Arrow take no such columns."""
    return [f"{prefix}c{i}" if "." in n or "`" in n else n for i, n in enumerate(names)]


def whole_row(df: DataFrame, seed: int) -> Column:
    """A 64-bit hash of all columns of df; nulls are told apart by their place."""
    columns = [F.to_json(F.col(f"`{f.name}`")) if "map<" in f.dataType.simpleString() else F.col(f"`{f.name}`") for f in df.schema]
    return F.xxhash64(F.lit(seed), F.concat(*(F.when(c.isNull(), "1").otherwise("0") for c in columns)), *columns)


def let(value: Column, body) -> Column:
    """body(value) with value computed once, as lambdas do not share subexpressions with the rest of a plan."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text: Column) -> Column:
    """Array of the words of a text; a null text has none."""
    bare = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACES))
    return F.when(bare == "", F.array().cast("array<string>")).otherwise(F.split(bare, f"{SPACE_CLASS}+"))


def n_words(text: Column) -> Column:
    return F.size(words(text)).cast("long")
