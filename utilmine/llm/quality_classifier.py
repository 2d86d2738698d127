"""Quality classifier: document evidence combined with site priors by hierarchical empirical Bayes.

1. A logistic model over format measures and the share of hashed words that mark rejected documents gives every document a
   probability of being bad (low quality or toxic). It is fitted on a bounded sample of labelled documents.
2. Sums of these probabilities by path and host give posterior rates. A host's rate shrinks toward the global
   rate by a strength estimated from the spread of host rates (method of moments), a path's rate toward its host's.
   Sparse sites so have their parent's rate, large ones their own.
3. A document's log odds move by the difference between its site's log odds and the global ones, weighed by site_weight.

Scores are computed in the scan. Only (host, path, score) sums are exchanged, in partial aggregates, so a host
with a third of all rows costs one row for each task.

Defined results: a null text is an empty one (bad by its evidence); a null host or path is a site of its own; repeated rows get equal scores; without labelled
rows of both kinds every document is kept with probability 0.5; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from utilmine.llm import tokens
from utilmine.llm.shared import broadcast_if_small, unused_prefix, written
from utilmine.llm.tokens import ALNUM_WORD, Block

WORD_BITS = 22
#: The bound on labelled rows that a fit reads, the words that may mark bad documents, and Newton steps.
SAMPLE, LEXICON, STEPS = 6_000, 400, 30
STRONGEST, WEAKEST = 1e6, 1.0

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>{}[]=+^~@\\"]] = True
_UPPER, _LOWER, _SPACE = np.zeros(256, bool), np.zeros(256, bool), np.zeros(256, bool)
_UPPER[65:91], _LOWER[97:123], _SPACE[[32, *range(9, 14)]] = True, True, True
_SHOUT = np.zeros(256, bool)
_SHOUT[ord("!")] = True
_BAR = np.zeros(256, bool)
_BAR[ord("|")] = True
FEATURES = ("symbols", "upper", "shouts", "bars", "short", "word length", "long words", "repeats", "marked words")


def _share(block: Block, table: np.ndarray) -> np.ndarray:
    sums = np.append(0, np.cumsum(table[block.data], dtype=np.int64))
    return sums[block.bounds[1:]] - sums[block.bounds[:-1]]


def evidence(block: Block, marked: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """A matrix of measures for the texts of a block (marked: sorted hashes of words), and for each word its text and hash."""
    block.words(ALNUM_WORD)
    hashes = block.hashes(fold=True)
    owner = np.repeat(np.arange(len(block)), block.counts)
    size = np.maximum(np.diff(block.bounds) - _share(block, _SPACE), 1)
    n = np.maximum(block.counts, 1)
    lengths = np.bincount(owner, block.ends - block.starts, len(block)) / n
    echo = np.flatnonzero((hashes[1:] == hashes[:-1]) & (owner[1:] == owner[:-1]))
    echoes = np.bincount(owner[echo], minlength=len(block)) / n
    hits = np.zeros(len(block))
    if len(marked):
        at = np.minimum(np.searchsorted(marked, hashes), len(marked) - 1)
        found = np.flatnonzero(marked[at] == hashes)
        hits = np.bincount(np.unique(owner[found] * len(marked) + at[found]) // len(marked), minlength=len(block))
    cols = [10 * _share(block, _SYMBOL) / size, 4 * _share(block, _UPPER) / size, 10 * _share(block, _SHOUT) / size, 10 * _share(block, _BAR) / size, np.exp(-block.counts / 8), lengths / 5, lengths > 12, 4 * echoes, np.log1p(np.minimum(hits, 20))]
    return np.stack([np.asarray(c, float) for c in cols], 1), owner, hashes


def _distinct(owner: np.ndarray, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct pairs of a text and a bucket of its words."""
    shift = np.uint64(WORD_BITS)
    pairs = np.unique((owner.astype(np.uint64) << shift) | (hashes >> np.uint64(64 - WORD_BITS)))
    return (pairs >> shift).astype(np.int64), (pairs & np.uint64((1 << WORD_BITS) - 1)).astype(np.int64)


class Model:
    """Weights of the measures and the sorted hashes of marked words; small and fixed in size."""

    def __init__(self, marked: np.ndarray, weights: np.ndarray):
        self.marked, self.weights = marked, weights

    def bad(self, block: Block) -> np.ndarray:
        x, _, _ = evidence(block, self.marked)
        found = 1 / (1 + np.exp(-np.clip(x @ self.weights[1:] + self.weights[0], -30, 30)))
        return np.where((block.counts == 0) & self.weights.any(), 1.0, found)  # nothing to read


def marked_words(texts: pa.ChunkedArray, y: np.ndarray, least_support: int) -> np.ndarray:
    """Hashes of words whose share among bad documents is far above that among good ones.

    A word counts from 1% of the bad documents on, so that a few near copies do not make their words telling. A first pass counts documents by bucket of the word hash, a second one the exact words of the best buckets.
    """

    def strong(in_bad: np.ndarray, in_good: np.ndarray) -> np.ndarray:
        odds = np.log((in_bad + 0.5) / (y.sum() + 1)) - np.log((in_good + 0.5) / (len(y) - y.sum() + 1))
        excess = odds * np.sqrt(in_bad)
        return np.where((in_bad >= max(least_support, 0.01 * y.sum())) & (odds > 3) & (excess > 8), excess, 0)

    none = np.zeros(0, np.uint64)
    counts = np.zeros((2, 1 << WORD_BITS), np.int32)
    for block in tokens.blocks(texts):
        _, owner, hashes = evidence(block, none)
        text, word = _distinct(owner, hashes)
        np.add.at(counts, (y[block.first + text].astype(int), word), 1)
    gain = strong(counts[1], counts[0])
    best = np.zeros(1 << WORD_BITS, bool)
    best[np.argsort(-gain)[:LEXICON]] = True
    best &= gain > 0
    pairs = []
    for block in tokens.blocks(texts):
        _, owner, hashes = evidence(block, none)
        at = np.flatnonzero(best[(hashes >> np.uint64(64 - WORD_BITS)).astype(np.int64)])
        pairs.append(np.unique(np.stack([hashes[at], (block.first + owner[at]).astype(np.uint64)]), axis=1))
    hashes, text = np.concatenate(pairs, 1)
    words, at = np.unique(hashes, return_inverse=True)
    bad = y[text.astype(np.int64)]
    return words[strong(np.bincount(at, bad, len(words)), np.bincount(at, 1 - bad, len(words))) > 0]


def fit(texts: pa.ChunkedArray, bad: np.ndarray, least_support: int = 4) -> Model:
    """Marked words first, then Newton steps with a ridge."""
    y = np.asarray(bad, float)
    if not len(y) or y.min() == y.max():
        return Model(np.zeros(0, np.uint64), np.zeros(len(FEATURES) + 1))
    marked = marked_words(texts, y, least_support)
    x = np.concatenate([evidence(b, marked)[0] for b in tokens.blocks(texts)])
    x = np.hstack([np.ones((len(x), 1)), x])
    weights, ridge = np.zeros(x.shape[1]), np.diag([1e-6] + [0.05] * (x.shape[1] - 1))
    for _ in range(STEPS):
        p = 1 / (1 + np.exp(-np.clip(x @ weights, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge, x.T @ (y - p) - ridge @ weights)
        weights += np.clip(step, -2, 2)
    return Model(marked, weights)


def labelled_sample(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> pa.Table:
    """At most `most` labelled texts, the least by a hash of doc_id; the join sees only documents whose id the sample names."""
    marks = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.max(((F.col("quality") == 0) | (F.coalesce("toxic", F.lit(0)) == 1)).cast("int")).alias("bad"))
    chosen = F.broadcast(marks.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most))
    rows = docs.select("doc_id", "text").join(chosen, "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.first("bad").alias("bad"))
    # copies would make every word of a much copied document look telling
    first = rows.groupBy(F.coalesce("text", F.lit("")).alias("text")).agg(F.min("doc_id").alias("doc_id"), F.max("bad").alias("bad"))
    return first.select("doc_id", "text", "bad").toArrow().sort_by("doc_id")


def _scorer(model: Model, column: str):
    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.schema.get_field_index("__text")
            found = [model.bad(b) for b in tokens.blocks(batch.column(at))]
            bad = pa.array(np.concatenate(found) if found else np.zeros(0))
            kept = [i for i in range(batch.num_columns) if i != at]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in kept), bad], names=[*(batch.schema.names[i] for i in kept), column])

    return score


def scored(docs: DataFrame, model: Model, host: Column, path: Column, keep: list[str]) -> DataFrame:
    """The columns in keep with __host, __path and __bad."""
    rows = docs.select(*keep, F.coalesce(host.cast("string"), F.lit("\x00")).alias("__host"), F.coalesce(path.cast("string"), F.lit("\x00")).alias("__path"), F.coalesce(F.col("text"), F.lit("")).alias("__text"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema if f.name != "__text") + ", __bad double"
    return rows.mapInArrow(_scorer(model, "__bad"), schema)


def _shrunk(bad: Column, n: Column, prior: Column, strength: Column) -> Column:
    return (bad + strength * prior) / (n + strength)


def _strength(sites: DataFrame, rate: str) -> DataFrame:
    """One row, k: prior observations worth of a parent's rate, from the spread of children's rates beyond chance (method of moments).

    With rates r of n documents about means m: the excess variance over m(1-m)/n gives k = m(1-m)/excess - 1.
    """
    m = F.col(rate)
    chance = F.sum(m * (1 - m))
    spread = F.sum(F.col("n") * F.pow(F.col("bad") / F.col("n") - m, 2))
    beyond = (spread - chance) / F.sum("n")
    inside = F.sum(F.col("n") * m * (1 - m)) / F.sum("n")
    k = F.when(beyond > 0, F.least(F.lit(STRONGEST), F.greatest(F.lit(WEAKEST), inside / beyond - 1))).otherwise(F.lit(STRONGEST))
    return sites.agg(F.coalesce(k, F.lit(STRONGEST)).alias("k"))


def site_rates(scores: DataFrame) -> DataFrame:
    """__host, __path, host_rate, path_rate and the global rate for every site."""
    paths = written(scores.groupBy("__host", "__path").agg(F.sum("__bad").alias("bad"), F.count(F.lit(1)).alias("n")))
    hosts = paths.groupBy("__host").agg(F.sum("bad").alias("bad"), F.sum("n").alias("n"))
    whole = F.broadcast(paths.agg((F.sum("bad") / F.sum("n")).alias("rate")))  # one row, as are the strengths
    hosts = hosts.join(whole)
    hosts = hosts.join(F.broadcast(_strength(hosts, "rate"))).select("__host", "rate", _shrunk(F.col("bad"), F.col("n"), F.col("rate"), F.col("k")).alias("host_rate"))
    below = paths.join(hosts, "__host")
    return below.join(F.broadcast(_strength(below, "host_rate"))).select("__host", "__path", "rate", "host_rate", _shrunk(F.col("bad"), F.col("n"), F.col("host_rate"), F.col("k")).alias("path_rate"))


def _logit(p: Column) -> Column:
    q = F.least(F.greatest(p, F.lit(1e-4)), F.lit(1 - 1e-4))
    return F.log(q / (1 - q))


def classify(docs: DataFrame, labels: DataFrame, host: Column | None = None, path: Column | None = None, keep: list[str] | None = None, site_weight: float = 0.5, threshold: float = 0.5, sample: int = SAMPLE) -> DataFrame:
    """The columns in keep (default: doc_id) with evidence, site_rate, quality (posterior of being good) and kept, for each row of docs."""
    host, path = host if host is not None else F.col("source"), path if path is not None else F.col("lang")
    rows = labelled_sample(docs, labels, sample)
    model = fit(rows["text"], rows["bad"].to_numpy())
    del rows
    rates = broadcast_if_small(written(site_rates(scored(docs, model, host, path, []))))
    keep = keep if keep is not None else ["doc_id"]
    joined = scored(docs, model, host, path, keep).join(rates, ["__host", "__path"])
    odds = _logit(F.col("__bad")) + site_weight * (_logit(F.col("path_rate")) - _logit(F.col("rate")))
    quality = 1 / (1 + F.exp(odds))
    return joined.select(*keep, (1 - F.col("__bad")).alias("evidence"), (1 - F.col("path_rate")).alias("site_rate"), quality.alias("quality"), (quality >= threshold).alias("kept"))


def without_rejected(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """docs without the documents that classify rejects."""
    p = unused_prefix(docs)
    names = {c: f"{p}in{i}" for i, c in enumerate(docs.columns)}
    renamed = docs.select(*(F.col(f"`{c}`").alias(n) for c, n in names.items()), *(F.col(f"`{c}`") for c in docs.columns))
    kept = classify(renamed, labels, keep=list(names.values()), **options).where("kept")
    return kept.select(*(F.col(n).alias(c) for c, n in names.items()))
