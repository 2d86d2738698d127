from __future__ import annotations

from pyspark.sql import functions as F

from utilmine import sqlapi
from utilmine.operators import post
from utilmine.operators.mine import mine
from utilmine.sources import baskets, tables, workloads
from utilmine.streaming import windows


def test_text_round_trip(spark, tmp_path):
    (tmp_path / "in.txt").write_text("1 3 4:19:5 12 2\n1 2:12:6 6\n")
    lines = tables.read_transactions(spark, str(tmp_path / "in.txt"), "text")
    assert lines.count() == 5 and lines.agg(F.sum("u")).first()[0] == 31
    found = mine(lines, lines.select("item").distinct().withColumn("mu", F.lit(17).cast("long")))
    for fmt in ("parquet", "csv", "json", "text"):
        tables.write_patterns(found, str(tmp_path / fmt), fmt)
    assert spark.read.parquet(str(tmp_path / "parquet")).count() == found.count()
    assert sorted(r[0] for r in spark.read.text(str(tmp_path / "text")).collect()) == sorted(f"{r['key'].replace(',', ' ')} #UTIL: {r['utility']}" for r in found.collect())


def test_repeated_lines_of_other_prices(spark):
    rows = spark.createDataFrame([(1, "x", 2, 10), (1, "x", 3, 4), (1, "y", 1, 7), (2, "x", 1, 10), (2, None, 1, 1), (None, "x", 1, 1), (2, "y", 0, 5)], "t long, i string, q long, p long")
    lines = baskets.from_lines(rows, "t", "i", "q", "p")
    assert sorted((r["tid"], r["item"], r["qty"], r["pr"], r["u"]) for r in lines.collect()) == [(1, "x", 5, 4, 32), (1, "y", 1, 7, 7), (2, "x", 1, 10, 10)]
    parents = spark.createDataFrame([("x", "z"), ("y", "z")], "item string, parent string")
    assert sorted(map(tuple, baskets.mapped(lines, parents).collect())) == [(1, "z", 6, 39), (2, "z", 1, 10)]


def test_sql_table_function(spark):
    lines, mu = workloads.toy(spark), workloads.toy_thresholds(spark)
    sqlapi.register(spark, lines, mu, mine(lines, mu))
    assert spark.sql("select * from mine_subtree(TABLE(tails) PARTITION BY root)").count() == 11 == spark.sql("select * from huis").count()


def test_streams_equal_batches(spark, sf):
    batch = windows.window_baskets(workloads.table(spark, sf, "events").select(F.col("user_id").alias("user"), F.col("ts").cast("timestamp").alias("ts"), F.get_json_object("props", "$.k").cast("long").alias("item"), F.round(F.col("value") * 100).cast("long").alias("u")), "1 day")
    stream = windows.run_to_table(windows.window_baskets(windows.event_stream(spark, sf), "1 day"), "complete")
    pick = ["start", "user", "tu", F.size("its").alias("n")]
    assert stream.select(*pick).exceptAll(batch.select(*pick)).count() == 0 and stream.count() == batch.count()


def test_closed_windows_only(spark, sf):
    made = windows.run_to_table(windows.window_baskets(windows.event_stream(spark, sf), "1 day", watermark="0 seconds").select("start", "end", "user", "tu"), "append")
    latest = workloads.table(spark, sf, "events").agg(F.max(F.col("ts").cast("timestamp"))).first()[0]
    assert made.where(F.col("end") > F.lit(latest)).count() == 0


def test_reports(spark):
    huis = mine(workloads.toy(spark), workloads.toy_thresholds(spark)).cache()
    assert [r["key"] for r in post.topn(huis, 2).collect()] == ["b,d", "d"]
    assert {r["key"] for r in post.maximal(huis).collect()} == {"b,c,d,e", "a,c,d"}
    assert {r["key"] for r in post.containing(huis, "a").collect()} == {"a,d", "a,c,d"}
    assert post.rare_items(huis, workloads.toy_thresholds(spark), 0.5).count() == 10
    assert post.share(huis, workloads.toy(spark).agg(F.sum("u").alias("total"))).agg(F.max("running")).first()[0] == huis.agg(F.sum("utility")).first()[0]


def test_latest_thresholds(spark, tmp_path):
    schema = "item string, mu long, ts timestamp"
    rows = [("a", 5, "2024-01-02"), ("a", 3, "2024-01-01"), ("b", 9, "2024-01-01"), ("a", 7, "2024-01-03")]
    for i, part in enumerate((rows[:1], rows[1:])):
        spark.createDataFrame([(x, m, t) for x, m, t in part], "item string, mu long, ts string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(str(tmp_path / f"part{i}"))
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", True).parquet(str(tmp_path))
    query = windows.latest_thresholds(stream).writeStream.outputMode("update").format("memory").queryName("newest").trigger(availableNow=True).start()
    query.awaitTermination()
    assert {(r["item"], r["mu"]) for r in spark.table("newest").collect()} >= {("a", 7), ("b", 9)}
