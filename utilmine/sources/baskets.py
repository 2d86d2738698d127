"""Basket lines from any table: one row for each basket and item, lines(tid, item, qty, u, pr?, ts?, cust?)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def from_lines(df: DataFrame, tid: Column | str, item: Column | str, qty: Column | str | None = None, pr: Column | str | None = None, utility: Column | str | None = None, ts: Column | str | None = None, cust: Column | str | None = None, on_negative: str = "error") -> DataFrame:
    """Repeated (tid, item) rows are one line with summed quantity and the least pr. u is the sum of qty * pr over its rows, or of a ready-made utility.

    Lines without a basket, an item or a positive quantity are dropped (see dropped()). Utilities are BIGINT in a declared unit; a
    negative one is an error, or with on_negative="drop" a dropped line, as every bound adds utilities that are not negative.
    """
    quantity = _col(qty).cast("long") if qty is not None else F.lit(1).cast("long")
    rows = df.select(_col(tid).alias("tid"), _col(item).alias("item"), quantity.alias("qty"), *([_col(pr).cast("long").alias("pr")] if pr is not None else []), *([_col(utility).cast("long").alias("u")] if utility is not None else []), *([_col(ts).alias("ts")] if ts is not None else []), *([_col(cust).alias("cust")] if cust is not None else []))
    rows = rows.where("tid is not null and item is not null and qty > 0")
    sums = [F.sum("qty").alias("qty")]
    sums += [F.min("pr").alias("pr")] if pr is not None else []
    sums += [F.sum("u" if utility is not None else F.col("qty") * F.col("pr")).alias("u")] if utility is not None or pr is not None else []
    sums += [F.min(c).alias(c) for c in ("ts", "cust") if c in rows.columns]
    merged = rows.groupBy("tid", "item").agg(*sums)
    if "u" in merged.columns:
        if on_negative == "drop":
            merged = merged.where("u >= 0")
        else:
            merged = merged.withColumn("u", F.when(F.col("u") >= 0, F.col("u")).otherwise(F.raise_error(F.lit("a utility is negative")).cast("long")))
    return merged


def dropped(df: DataFrame, tid: Column | str, item: Column | str, qty: Column | str) -> DataFrame:
    """One row: how many lines from_lines leaves out."""
    bad = _col(tid).isNull() | _col(item).isNull() | ~F.coalesce(_col(qty) > 0, F.lit(False))
    return df.agg(F.count(F.when(bad, 1)).alias("dropped"))


def scaled(money: Column | str, scale: int = 100) -> Column:
    """A DOUBLE amount of money as BIGINT in 1/scale units, rounded once."""
    return F.round(_col(money) * scale).cast("long")


def profit_of(lines: DataFrame) -> DataFrame:
    """item, pr of lines that carry pr."""
    return lines.groupBy("item").agg(F.min("pr").alias("pr"))


def mapped(lines: DataFrame, mapping: DataFrame) -> DataFrame:
    """Lines with items replaced by mapping(item, parent): part to brand, for instance; utilities of equal parents add up."""
    joined = lines.select("tid", "item", "qty", "u").join(mapping, "item")
    return joined.groupBy("tid", F.col("parent").alias("item")).agg(F.sum("qty").alias("qty"), F.sum("u").alias("u"))
