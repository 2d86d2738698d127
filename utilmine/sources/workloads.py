"""The experiment workloads on the given tables, and the two literal examples. Each gives lines(tid, item, qty, u, pr)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from utilmine.sources import baskets
from utilmine.sources.tables import table

#: Fixed values of the running example: profits, thresholds and quantities.
TOY_PROFIT = {"a": 6, "b": 12, "c": 1, "d": 9, "e": 3}
TOY_MU = {"a": 56, "b": 65, "c": 53, "d": 50, "e": 70}
TOY_BASKETS = {1: "a1 c2 d3", 2: "a2 d1 e2", 3: "b3 c5", 4: "a1 c3 d1 e2", 5: "b1 d3 e2", 6: "b2 d2", 7: "b3 c2 d1 e1", 8: "a2 c3", 9: "c2 d2 e1", 10: "a2 c2 d1"}
#: Fixed values of the shopping example: total profits in tenths of a dollar.
SHOP_BASKETS = {
    1: {"milk": 20, "bread": 60, "beer": 60, "cheese": 30, "cereal": 30},
    2: {"foodProcessor": 240},
    3: {"milk": 60, "bread": 60, "beer": 60},
    4: {"milk": 20, "cereal": 15, "cheese": 30},
    5: {"foodProcessor": 120, "cookingPan": 160},
    6: {"bread": 30, "milk": 20},
    10: {"bread": 30, "butter": 40, "oatmeal": 100},
}


def toy(spark: SparkSession, sf_dir: str | None = None) -> DataFrame:
    rows = [(t, x[0], int(x[1:]), TOY_PROFIT[x[0]]) for t, line in TOY_BASKETS.items() for x in line.split()]
    return baskets.from_lines(spark.createDataFrame(rows, "tid long, item string, qty long, pr long"), "tid", "item", "qty", "pr")


def toy_thresholds(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(TOY_MU.items()), "item string, mu long")


def shop(spark: SparkSession, sf_dir: str | None = None) -> DataFrame:
    rows = [(t, i, u) for t, line in SHOP_BASKETS.items() for i, u in line.items()]
    return baskets.from_lines(spark.createDataFrame(rows, "tid long, item string, u long"), "tid", "item", utility="u")


def _sold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity")


def _customer_year(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_custkey") * 10000 + F.year("o_orderdate")).alias("tid"))
    return _sold(spark, sf_dir).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def _sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("long").alias("p_size"))


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _sold(spark, sf_dir).join(_sizes(spark, sf_dir), F.col("l_partkey") == F.col("p_partkey"))
    return baskets.from_lines(rows, "l_orderkey", "l_partkey", "l_quantity", "p_size")


def customer_year_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _customer_year(spark, sf_dir).join(_sizes(spark, sf_dir), F.col("l_partkey") == F.col("p_partkey"))
    return baskets.from_lines(rows, "tid", "l_partkey", "l_quantity", "p_size")


def customer_year_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baskets.from_lines(_customer_year(spark, sf_dir), "tid", "l_suppkey", "l_quantity", 1 + F.col("l_suppkey") % 10)


def _brand_profit(brand: Column) -> Column:
    return 1 + (7 * brand) % 10


def order_brand(spark: SparkSession, sf_dir: str) -> DataFrame:
    brand = F.regexp_extract("p_brand", "([0-9]+)", 1).cast("long")
    parts = table(spark, sf_dir, "part").select("p_partkey", brand.alias("brand"))
    rows = _sold(spark, sf_dir).join(parts, F.col("l_partkey") == F.col("p_partkey"))
    return baskets.from_lines(rows, "l_orderkey", "brand", "l_quantity", _brand_profit(F.col("brand")))


def order_record(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight attribute=value items for each order; ids by the order of their strings."""
    customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "o_orderdate", "o_totalprice")
    balance = F.when(F.col("c_acctbal") < 0, "neg").when(F.col("c_acctbal") < 5000, "mid").otherwise("hi")
    values = {"st": F.col("o_orderstatus"), "pri": F.col("o_orderpriority"), "seg": F.col("c_mktsegment"), "nat": F.col("c_nationkey"), "yr": F.year("o_orderdate"), "mon": F.month("o_orderdate"), "tp": F.least(F.lit(9), F.floor(F.col("o_totalprice") / 50000)), "bal": balance}
    named = F.array(*(F.concat(F.lit(f"{k}="), v.cast("string")) for k, v in values.items()))
    long = orders.join(customer, F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").alias("tid"), F.explode(named).alias("name"))
    ids = long.select("name").distinct().withColumn("id", F.row_number().over(Window.orderBy("name")).cast("long"))
    rows = long.join(F.broadcast(ids), "name")  # attribute values: a few dozen at any scale
    return baskets.from_lines(rows, "tid", "id", 1 + (F.col("tid") * 7 + F.col("id") * 13) % 5, 1 + (7 * F.col("id")) % 10)


def user_day_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    return event_lines(table(spark, sf_dir, "events"))


def event_lines(events: DataFrame) -> DataFrame:
    key = F.get_json_object("props", "$.k").cast("long")
    lines = baskets.from_lines(events, F.col("user_id") * 100 + F.dayofmonth("ts"), key, utility=baskets.scaled("value"))
    return lines.withColumn("pr", 1 + F.col("item") % 10)


def doc_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tokens of whole texts, dealt by document before they are split: a text is smaller than its tokens' rows."""
    found = F.regexp_extract_all(F.lower("text"), F.lit("[a-zéèàêçïü]+"), F.lit(0))
    rows = table(spark, sf_dir, "documents").select("doc_id", "text").repartition("doc_id").select("doc_id", F.explode(found).alias("token"))
    return baskets.from_lines(rows, "doc_id", "token", F.lit(1), F.length("token"))


ALL = {
    "order_part": order_part,
    "customer_year_part": customer_year_part,
    "order_record": order_record,
    "customer_year_supplier": customer_year_supplier,
    "order_brand": order_brand,
    "user_day_key": user_day_key,
    "doc_tokens": doc_tokens,
}
