"""Mixing sources to target weights: weighted sampling without replacement by exponential keys, natively.

Each source gets a word budget; a budget of q full passes and a rest takes every document q times, then documents in
the order of their keys -ln(u)/w until the rest is met. u comes from a hash of the row, so reruns agree, and w is the
quality weight of the document.

Texts are measured once, into a table of numbers. Nothing but numbers is shuffled. Sources are cut at a key, found in three aggregates: words by source; words by
source and key bucket (a source of n documents has sqrt(n) buckets of about sqrt(n) documents, so that one with a third of
all rows leaves no large group to any task); and a running sum inside the one bucket where the rest runs out, over distinct rows, so that
any number of equal ones is one row of it. The cuts, a row for each source, are joined to the documents, so texts never leave their scan.

Rows equal in all columns have one key. Where a cut falls among them, as many as the rest demands are taken once more and the others not:
they are made anew from one of them and their number, in pieces of PIECE rows dealt over tasks, as equal rows cannot be told apart.

Defined results: a null text has size 0; a null source is a source, the last; empty tables give empty results; documents of
size 0 are taken as the rest demands; columns of any name pass through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from utilmine.llm.shared import broadcast_if_small, n_words, unused_prefix, whole_row, written

#: Characters that lower the quality weight of a text.
NOISE = "#*$%&|<>!{}[]=+"
MOST_EPOCHS = 3
PIECE = 10_000


def quality_weight(text: Column) -> Column:
    """Between 0.5 and 1: one for text without noise characters, falling with their share."""
    full = F.coalesce(text, F.lit(""))
    noisy = F.length(full) - F.length(F.translate(full, NOISE, ""))
    return F.greatest(F.lit(0.5), 1 - 5 * noisy / F.greatest(F.length(full), F.lit(1)))


def exponential_key(weight: Column, *of: Column, seed: int = 0) -> Column:
    """-ln(u)/w with u in (0, 1) from 52 bits of a hash of the columns and the seed."""
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), *of), 12) + 0.5) / float(1 << 52)
    return -F.log(u) / weight


def target_table(sizes: DataFrame, cap: float = MOST_EPOCHS) -> DataFrame:
    """source, source_size, n_docs -> the same with target: weights 1, 2, 3, 1, ... by rank share all words; no more than cap times a source's size.

    Sharing the excess again by weight until none is above its cap ends at one level l with
    target = min(cap * size, l * weight). Sorted by cap * size / weight, the capped sources are a prefix.
    The window over all rows sees one row for each source, never documents.
    """
    by_name, by_ratio = Window.orderBy(F.col("source").asc_nulls_last()), Window.orderBy("ratio", F.col("source").asc_nulls_last())
    ranked = sizes.withColumn("weight", (F.row_number().over(by_name) - 1) % 3 + 1)
    ranked = ranked.withColumns({"most": cap * F.col("source_size"), "ratio": cap * F.col("source_size") / F.col("weight")})
    before, everything = by_ratio.rowsBetween(Window.unboundedPreceding, -1), by_ratio.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    left = F.sum("source_size").over(everything) - F.coalesce(F.sum("most").over(before), F.lit(0.0))
    weights = F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    level = ranked.withColumn("level", left / weights).withColumn("open", F.col("level") <= F.col("ratio"))
    level = level.withColumn("final", F.min(F.when(F.col("open"), F.struct("ratio", "level"))).over(everything)["level"])
    target = F.least(F.col("most"), F.coalesce(F.col("final"), F.lit(0.0)) * F.col("weight"))
    return level.select("source", "source_size", "n_docs", "weight", target.alias("target"))


def keyed(docs: DataFrame, seed: int, prefix: str) -> DataFrame:
    """docs with size, key, tie and source, named behind the prefix."""
    text = F.col("text")
    own = {"size": n_words(text), "key": exponential_key(quality_weight(text), F.col("doc_id"), text, seed=seed), "tie": whole_row(docs, seed + 1), "source": F.col("source")}
    return docs.withColumns({prefix + k: v for k, v in own.items()})


def cuts(rows: DataFrame) -> DataFrame:
    """rows(source, size, key, tie) -> for each source: source_size, target, the full passes, the key and tie of the last document
    that the rest takes, how many rows have these (equal) and how many of them it takes (extra)."""
    sizes = rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    targets = target_table(sizes)
    passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("int")
    targets = targets.withColumns({"passes": passes, "rest": F.col("target") - passes * F.col("source_size"), "buckets": F.ceil(F.sqrt(F.col("n_docs").cast("double")))})
    targets = broadcast_if_small(written(targets))
    own = targets.select(F.col("source").alias("t_source"), "rest", "buckets")
    placed = rows.select("source", "size", "key", "tie").join(own, F.col("source").eqNullSafe(F.col("t_source"))).drop("t_source")
    placed = placed.withColumn("bucket", F.least(F.col("buckets") - 1, F.floor((1 - F.exp(-F.col("key"))) * F.col("buckets"))))
    per_bucket = placed.groupBy("source", "bucket").agg(F.sum("size").alias("words"), F.first("rest").alias("rest"))
    running = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    per_bucket = per_bucket.withColumn("before", F.sum("words").over(running) - F.col("words"))
    edge = per_bucket.where((F.col("before") < F.col("rest")) & (F.col("before") + F.col("words") >= F.col("rest"))).groupBy("source").agg(F.min(F.struct("bucket", "before")).alias("edge"))
    edge = broadcast_if_small(written(edge.select(F.col("source").alias("e_source"), F.col("edge.bucket").alias("e_bucket"), F.col("edge.before").alias("before"))))
    inside = placed.join(edge, F.col("source").eqNullSafe(F.col("e_source")) & (F.col("bucket") == F.col("e_bucket")))
    inside = inside.groupBy("source", "key", "tie", "size", "before", "rest", "e_bucket", "buckets").agg(F.count(F.lit(1)).alias("equal"))
    words = F.col("size") * F.col("equal")
    order = Window.partitionBy("source").orderBy("key", "tie").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    left = F.col("rest") - (F.col("before") + F.sum(words).over(order) - words)
    extra = F.when(F.col("size") > 0, F.floor(left / F.col("size") + 0.5)).when(left >= 0, F.col("equal")).otherwise(0)
    inside = inside.withColumn("extra", F.least(F.col("equal"), F.greatest(F.lit(0), extra)).cast("long"))
    last = inside.groupBy("source").agg(F.max(F.when(F.col("extra") > 0, F.struct("key", "tie", "equal", "extra"))).alias("cut"), F.first("e_bucket").alias("e_bucket"), F.first("buckets").alias("n"))
    floor_key = -F.log(1 - F.col("e_bucket") / F.col("n"))
    last = last.select(F.col("source").alias("c_source"), F.coalesce(F.col("cut.key"), floor_key).alias("key"), F.coalesce(F.col("cut.tie"), F.lit(-(1 << 63))).alias("tie"), F.coalesce("cut.equal", F.lit(0)).alias("equal"), F.coalesce("cut.extra", F.lit(0)).alias("extra"))
    return targets.join(last, F.col("source").eqNullSafe(F.col("c_source")), "left").select("source", "source_size", "target", "passes", "rest", "key", "tie", "equal", "extra")


def _taken(rows: DataFrame, cut: DataFrame, prefix: str) -> DataFrame:
    """rows of keyed() with the columns of their source's cut (prefix cut_) and copies: how often the mix takes the row, where no cut falls among equal rows;
    at such a cut, one row for each of them, made from one and their number."""
    named = broadcast_if_small(cut.select(*(F.col(c).alias(f"{prefix}cut_{c}") for c in cut.columns)))
    col = lambda name: F.col(prefix + name)
    joined = rows.join(named, col("source").eqNullSafe(col("cut_source")))
    at = (col("key") == col("cut_key")) & (col("tie") == col("cut_tie"))
    more = (col("cut_rest") > 0) & ((col("key") < col("cut_key")) | (col("key") == col("cut_key")) & (col("tie") <= col("cut_tie")))
    simple = joined.withColumn(f"{prefix}copies", col("cut_passes") + F.coalesce(more, F.lit(False)).cast("int"))
    if not cut.where("extra < equal").limit(1).count():
        return simple
    parted = F.coalesce(at & (col("cut_extra") < col("cut_equal")), F.lit(False))
    names = joined.columns
    # a row for each source at most; written, as the optimizer loses fields of a struct between a generator and an exchange
    one = written(joined.where(parted).groupBy(f"{prefix}source").agg(F.first(F.struct(*(F.col(f"`{c}`") for c in names))).alias("row")).select("row.*"))
    pieces = one.withColumn(f"{prefix}piece", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((col("cut_equal") - 1) / PIECE)))).repartition(f"{prefix}source", f"{prefix}piece")
    number = F.explode(F.sequence(col("piece") * PIECE, F.least((col("piece") + 1) * PIECE, col("cut_equal")) - 1))
    again = pieces.select(*(F.col(f"`{c}`") for c in names), number.alias(f"{prefix}number"))
    again = again.withColumn(f"{prefix}copies", col("cut_passes") + (col("number") < col("cut_extra")).cast("int")).drop(f"{prefix}number")
    return simple.where(~parted).unionByName(again)


def _measured(docs: DataFrame, seed: int, prefix: str) -> DataFrame:
    own = keyed(docs, seed, prefix)
    return written(own.select("doc_id", *(F.col(prefix + c).alias(c) for c in ("source", "size", "key", "tie"))))


def mix(docs: DataFrame, seed: int = 17) -> DataFrame:
    """A row for each document: doc_id, size, source_size, target of its source, and copies, the times that the mix takes it (0 to 3)."""
    rows = _measured(docs, seed, unused_prefix(docs))
    taken = _taken(rows.select("doc_id", *(F.col(c).alias(f"_{c}") for c in ("source", "size", "key", "tie"))), written(cuts(rows)), "_")
    return taken.select("doc_id", F.col("_size").alias("size"), F.col("_cut_source_size").alias("source_size"), F.col("_cut_target").alias("target"), F.col("_copies").alias("copies"))


def mixed_documents(docs: DataFrame, seed: int = 17) -> DataFrame:
    """The mix itself: each document as often as it is taken, with the columns of docs."""
    prefix = unused_prefix(docs)
    cut = written(cuts(_measured(docs, seed, prefix)))
    taken = _taken(keyed(docs, seed, prefix), cut, prefix).where(F.col(f"{prefix}copies") > 0)
    return taken.withColumn(f"{prefix}copy", F.explode(F.array_repeat(F.lit(0), F.col(f"{prefix}copies")))).select(*(F.col(f"`{c}`") for c in docs.columns))
