"""What a search would do: the engine, how rows carry tails, waves and broadcasts, from sums over the encoded baskets."""

from __future__ import annotations

from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from utilmine.plans.encode import Dictionary

#: Mean basket length from which rows fetch their tails by basket, and entries of a root that a worker walks.
LONG_BASKETS, ROOT_BUDGET, WAVE_BUDGET = 32, 4_000_000, 1 << 40
BROADCAST_ROWS = 200_000


@dataclass
class Plan:
    items: int
    baskets: int
    mean_length: float
    max_length: int
    entries: int
    heavy_roots: int
    engine: str
    carry: str
    groups: int
    waves: int
    broadcast_dictionary: bool


def root_weights(enc: DataFrame, fraction: float | None = None) -> DataFrame:
    """root, weight: entries of the baskets projected on each root; from a sample of baskets if a fraction is given, for planning only."""
    seen = enc.sample(fraction, seed=1) if fraction else enc
    rows = seen.select(F.posexplode("its").alias("p", "x"), F.size("its").alias("w"))
    weight = F.sum(F.col("w") - F.col("p"))
    return rows.groupBy(F.col("x.r").alias("root")).agg((F.ceil(weight / F.lit(fraction)) if fraction else weight).alias("weight"))


def plan(enc: DataFrame, dictionary: Dictionary, fraction: float | None = None, root_budget: int = ROOT_BUDGET, wave_budget: int = WAVE_BUDGET) -> Plan:
    """One row of sums comes to the driver, whatever the input."""
    shape = enc.agg(F.count(F.lit(1)), F.avg(F.size("its")), F.max(F.size("its"))).first()
    heavy = F.col("weight") > root_budget
    sums = root_weights(enc, fraction).agg(F.coalesce(F.sum("weight"), F.lit(0)), F.count(F.when(heavy, 1)), F.coalesce(F.sum(F.when(heavy, F.col("weight"))), F.lit(0)), F.count(F.lit(1))).first()
    engine = "subtree" if not sums[1] else "frontier" if sums[1] == sums[3] else "hybrid"
    return Plan(dictionary.n, shape[0], float(shape[1] or 0), shape[2] or 0, sums[0], sums[1], engine, "rejoin" if (shape[1] or 0) > LONG_BASKETS else "suffix", max(1, -(-sums[0] // root_budget)), -(-sums[2] // wave_budget), dictionary.n <= BROADCAST_ROWS)


def explain(enc: DataFrame, dictionary: Dictionary, **options) -> DataFrame:
    """The plan as rows (what, value)."""
    rows = [(k, str(v)) for k, v in asdict(plan(enc, dictionary, **options)).items()]
    return enc.sparkSession.createDataFrame(rows, "what string, value string")
