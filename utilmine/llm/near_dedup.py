"""Near-duplicate detection: improved consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard similarity.

1. The documents that hold each five-word shingle are counted over all documents into a table of 2**18 buckets, fixed at any
   size of the input. A shingle's share of documents is its bucket's count, less the usual count of a bucket, over the number of documents;
   shares do not change with the size of the input, so neither do weights. A shingle weighs (1 + ln tf) * (1/2 + idf/2), where
   idf falls from 1, for shares up to 1%, to 0 for a shingle of all documents; plain tf would make texts near
   that share nothing but one phrase repeated a hundred times.
2. Each text gets 56 consistent weighted samples and 56 unweighted ones (least hashes of its shingles), as either similarity makes a
   link: where counts differ, texts near by the plain one can be far by the weighted one. Four samples of a kind make a band key.
   Texts of equal words are one node, named by 128 bits of hashes.
3. In each bucket (equal band keys) every node is compared with the bucket's least node; verified pairs become links, links components.
   So groups of copies cost a few comparisons for each member, not one for each pair. No link within a bucket is given up: what still
   differs then is compared pair by pair in buckets of up to 32 (unless the samples exclude 0.8 for both similarities); larger buckets that overlap
   are put together, their members dealt into blocks of bounded size, and each pair of blocks is compared as matrices
   in one task, which returns a spanning set of links and no pairs.
4. A pair counts as near if the weighted or the plain Jaccard similarity of its shingles is 0.8 or more. At 0.8 a pair shares a band
   with a chance above 0.999.

Defined results: a null text is an empty one; texts without words are copies of one another; a text of one to four words has one shingle, its
words; a null doc_id takes part like any other and its class is named by the least id that is not null, if any; an empty table
gives an empty result; columns of any name pass through.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from utilmine.llm import tokens
from utilmine.llm.components import components
from utilmine.llm.shared import broadcast_if_small, unused_prefix, whole_row, written
from utilmine.llm.tokens import WORD_POWERS, Block, mix, prefix, span_hashes

WIDTH, SIMILARITY = 5, 0.8
ROWS, BANDS = 4, 14
FREQUENCY_BITS, HASH_BITS = 18, 46
#: Shingles in no more than this share of the documents weigh most.
RARE = 0.01
BLOCK = 1 << 18
BUCKETS = 1 << 20
#: A pair at similarity 0.8 agrees in fewer of its 56 samples of that kind than this with a chance below 1e-5. Samples are kept as 8 bits, which only adds agreement.
LEAST_AGREEING = 32
#: Members of a bucket that are compared pair by pair; nodes and bytes of a block of a larger one; columns of a matrix.
SMALL, BLOCK_NODES, BLOCK_BYTES, COLUMNS = 32, 500, 2 << 20, 1024
LINKS = "a binary, b binary, similarity double"

_draw = np.random.default_rng(20240229)
_R = _draw.gamma(2.0, 1.0, 1 << 16).astype(np.float32)
_LOG_C = np.log(_draw.gamma(2.0, 1.0, 1 << 16)).astype(np.float32)
_FACTORS = mix(np.arange(1, ROWS * BANDS + 1, dtype=np.uint64)) | np.uint64(1)
_SEEDS = mix(np.arange(1001, ROWS * BANDS + 1001, dtype=np.uint64))
_PLAIN_FACTORS = mix(np.arange(2001, ROWS * BANDS + 2001, dtype=np.uint64)) | np.uint64(1)
_PLAIN_SEEDS = mix(np.arange(3001, ROWS * BANDS + 3001, dtype=np.uint64))


def weighted_shingles(block: Block) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Text, shingle and count of the distinct shingles of each text, in order of the text. Calls block.words()."""
    block.words()
    hashes = block.hashes()
    found, owner = block.shingles(hashes, WIDTH)
    few = np.flatnonzero((block.counts > 0) & (block.counts < WIDTH))
    if len(few):
        whole = span_hashes(prefix(hashes, WORD_POWERS), block.at[few], block.at[few + 1], WORD_POWERS)
        found, owner = np.append(found, whole), np.append(owner, few)
    shift = np.uint64(HASH_BITS)
    both, counts = np.unique((owner.astype(np.uint64) << shift) | (found >> np.uint64(64 - HASH_BITS)), return_counts=True)
    return (both >> shift).astype(np.int64), both & np.uint64((1 << HASH_BITS) - 1), counts


def bucket_of(shingles: np.ndarray) -> np.ndarray:
    return (shingles & np.uint64((1 << FREQUENCY_BITS) - 1)).astype(np.int64)


def _count_frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Bucket counts of this task's texts; bucket -1 counts texts."""
    counts, n = np.zeros(1 << FREQUENCY_BITS, np.int64), 0
    for batch in batches:
        n += batch.num_rows
        for block in tokens.blocks(batch.column(0), BLOCK):
            counts += np.bincount(bucket_of(weighted_shingles(block)[1]), minlength=len(counts))
    at = np.flatnonzero(counts)
    yield pa.record_batch({"bucket": pa.array(np.append(-1, at).astype(np.int32)), "n": pa.array(np.append(n, counts[at]))})


def bucket_weights(counts: np.ndarray, n: int) -> np.ndarray:
    """The weight of each bucket, between 1/2 and 1, from the documents counted in it, of n in all."""
    share = np.clip((counts - np.median(counts)) / max(n, 1), RARE, 1)
    return (0.5 + 0.5 * np.log(share) / np.log(RARE)).astype(np.float32)


def frequency_table(docs: DataFrame) -> np.ndarray:
    """2**18 floats, whatever the input."""
    table = docs.select("text").mapInArrow(_count_frequencies, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    bucket, n = table["bucket"].to_numpy(), table["n"].to_numpy()
    counts = np.zeros(1 << FREQUENCY_BITS)
    counts[bucket[bucket >= 0]] = n[bucket >= 0]
    return bucket_weights(counts, int(n[bucket == -1].sum()))


def samples(owner: np.ndarray, shingles: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """A row of 32-bit sample names for each text that has shingles; rows of owner must be in order.

    For each sample a shingle draws r, c (gamma) and b (uniform) from its hash; with t = floor(ln w / r + b) it
    scores ln c - r (t - b + 1), and the least score is the sample, named by shingle and t.
    """
    heads = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
    log_w = np.log(weights).astype(np.float32)
    spread = mix(shingles)
    own = (spread >> np.uint64(20)).astype(np.uint32)
    out = np.empty((len(heads), ROWS * BANDS), np.uint32)
    low = np.uint64(0xFFFFFFFF)
    for i in range(ROWS * BANDS):
        h = (spread ^ _SEEDS[i]) * _FACTORS[i]
        r = _R[(h >> np.uint64(48)).astype(np.int32)]
        b = (h & low).astype(np.float32) * np.float32(2**-32)
        t = np.floor(log_w / r + b)
        score = _LOG_C[((h >> np.uint64(32)) & np.uint64(0xFFFF)).astype(np.int32)] - r * (t - b + np.float32(1))
        bits = score.view(np.int32)
        order = (bits ^ ((bits >> 31) | np.int32(-(1 << 31)))).view(np.uint32)
        name = own + t.astype(np.int32).view(np.uint32) * np.uint32(0x9E3779B1)
        out[:, i] = np.minimum.reduceat((order.astype(np.uint64) << np.uint64(32)) | name, heads) & low
    return out


def plain_samples(owner: np.ndarray, shingles: np.ndarray) -> np.ndarray:
    """As samples, without weights: the shingle of the least hash, named by 32 other bits of it."""
    heads = np.flatnonzero(np.append(True, owner[1:] != owner[:-1]))
    spread = mix(shingles + np.uint64(1))
    out = np.empty((len(heads), ROWS * BANDS), np.uint32)
    for i in range(ROWS * BANDS):
        out[:, i] = np.minimum.reduceat((spread ^ _PLAIN_SEEDS[i]) * _PLAIN_FACTORS[i], heads) & np.uint64(0xFFFFFFFF)
    return out


def band_keys(found: np.ndarray) -> np.ndarray:
    """A key for each four samples of each row."""
    bands = np.zeros((len(found), found.shape[1] // ROWS), np.uint64)
    for r in range(ROWS):
        bands = mix(bands * np.uint64(0x2545F4914F6CDD1D) + found[:, r::ROWS].astype(np.uint64) + np.uint64(r))
    return bands + np.arange(bands.shape[1], dtype=np.uint64)


def node_names(block: Block, hashes: np.ndarray) -> pa.Array:
    """16 bytes for each text, from two independent hashes of its words."""
    ways = (prefix(hashes, WORD_POWERS), prefix(mix(hashes + np.uint64(77)), WORD_POWERS))
    names = np.stack([span_hashes(x, block.at[:-1], block.at[1:], WORD_POWERS) + mix(block.counts.astype(np.uint64)) for x in ways], 1)
    return pa.array([row.tobytes() for row in names], pa.binary())


def _sketcher(table):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weight_of = table.value
        for batch in batches:
            names = batch.schema.names
            key, other, doc = (batch.column(names.index(c)) for c in ("key", "other", "doc_id"))
            for block in tokens.blocks(batch.column(names.index("text")), BLOCK):
                owner, shingle, count = weighted_shingles(block)
                keys, drawn = [None] * len(block), [None] * len(block)
                if len(owner):
                    found = np.hstack([samples(owner, shingle, (1 + np.log(count)) * weight_of[bucket_of(shingle)]), plain_samples(owner, shingle)])
                    bands, low = band_keys(found), found.astype(np.uint8).view(np.int8)
                    for k, i in enumerate(np.unique(owner)):
                        keys[i], drawn[i] = bands[k].view(np.int64), low[k]
                own = lambda c: c.slice(block.first, len(block))  # noqa: B023, E731
                yield pa.record_batch({"key": own(key), "other": own(other), "doc_id": own(doc), "node": node_names(block, block.hashes()), "bands": pa.array(keys, pa.list_(pa.int64())), "samples": pa.array(drawn, pa.list_(pa.int8()))})

    return rows


def similarity(a: bytes, b: bytes, weight_of: np.ndarray) -> float:
    """The larger of weighted and plain Jaccard similarity of two texts' shingles."""
    block = next(tokens.blocks(pa.array([a, b], pa.binary()).cast(pa.string()), 1 << 62))
    owner, shingle, count = weighted_shingles(block)
    first, second = owner == 0, owner == 1
    if not first.any() or not second.any():
        return float(not first.any() and not second.any())
    both, i, j = np.intersect1d(shingle[first], shingle[second], assume_unique=True, return_indices=True)
    w = (1 + np.log(count)) * weight_of[bucket_of(shingle)]
    u, v = w[first], w[second]
    shared = np.minimum(u[i], v[j]).sum()
    return max(float(shared / (u.sum() + v.sum() - shared)), len(both) / (len(u) + len(v) - len(both)))


def _verifier(table):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            names = batch.schema.names
            one, two = (batch.column(names.index(c)) for c in ("text_a", "text_b"))
            found = pa.array([similarity((x.as_py() or "").encode(), (y.as_py() or "").encode(), table.value) for x, y in zip(one, two, strict=True)], pa.float64())
            yield pa.record_batch({"a": batch.column(names.index("a")), "b": batch.column(names.index("b")), "similarity": found})

    return rows


def _entries(texts: pa.Array, weight_of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text, column and weight such that products of columns, added up, are the weight that two texts share; and each text's whole weight and number of shingles.

    The least of two counts is a sum over levels: a shingle of count c has the columns (shingle, 1) to (shingle, c).
    """
    found = [(block.first + o, s, c) for block in tokens.blocks(texts, BLOCK) for o, s, c in [weighted_shingles(block)]]
    owner, shingle, count = (np.concatenate(x) for x in zip(*found, strict=True))
    n = len(texts)
    idf = weight_of[bucket_of(shingle)].astype(float)
    at = np.repeat(np.arange(len(owner)), count)
    level = np.arange(len(at)) - np.repeat(np.cumsum(count) - count, count) + 1
    step = 1 + np.log(level) - np.where(level > 1, 1 + np.log(np.maximum(level - 1, 1)), 0)
    _, column = np.unique(shingle[at] * np.uint64(0x9E3779B97F4A7C15) + mix(level.astype(np.uint64)), return_inverse=True)
    column[level == 1] = 2 * column[level == 1]
    column[level > 1] = 2 * column[level > 1] + 1  # odd columns are higher levels
    weight = idf[at] * step
    return owner[at], column, weight, np.bincount(owner, (1 + np.log(count)) * idf, n).astype(np.float32), np.bincount(owner, minlength=n).astype(np.float32)


def _spanning(near: np.ndarray) -> np.ndarray:
    """The least index of the component of each row of a symmetric matrix of links."""
    label = np.arange(len(near))
    near = near | np.eye(len(near), dtype=bool)
    while True:
        least = np.array([label[row].min() for row in near])
        least = least[least]
        if (least == label).all():
            return label
        label = least


def block_links(texts: pa.Array, weight_of: np.ndarray, threshold: float) -> np.ndarray:
    """For each text the first of those that it is linked to, directly or over others of these texts."""
    owner, column, weight, whole, sizes = _entries(texts, weight_of)
    n = len(texts)
    shared = np.bincount(column)[column] > 1
    owner, weight = owner[shared], weight[shared]
    plain = column[shared] % 2 == 0
    _, column = np.unique(column[shared], return_inverse=True)
    both, count = np.zeros((n, n), np.float32), np.zeros((n, n), np.float32)
    order = np.argsort(column, kind="stable")
    cuts = np.searchsorted(column[order], np.arange(0, column.max(initial=-1) + COLUMNS, COLUMNS))
    for first, (a, b) in zip(range(0, int(column.max(initial=-1)) + 1, COLUMNS), zip(cuts[:-1], cuts[1:], strict=True), strict=False):
        part = order[a:b]
        m = np.zeros((n, COLUMNS), np.float32)
        m[owner[part], column[part] - first] = np.sqrt(weight[part])
        both += m @ m.T
        own = part[plain[part]]
        m = np.zeros((n, COLUMNS), np.float32)
        m[owner[own], column[own] - first] = 1
        count += m @ m.T
    weighted = both / np.maximum(whole[:, None] + whole[None, :] - both, 1e-9)
    jaccard = count / np.maximum(sizes[:, None] + sizes[None, :] - count, 1)
    return _spanning((weighted >= threshold - 1e-6) | (jaccard >= threshold - 1e-6))


def _block_comparer(table, threshold: float):
    def links(group: pa.Table) -> pa.Table:
        group = group.combine_chunks()
        node = group["node"].combine_chunks() if isinstance(group["node"], pa.ChunkedArray) else group["node"]
        first = block_links(group["text"].combine_chunks() if isinstance(group["text"], pa.ChunkedArray) else group["text"], table.value, threshold)
        other = first != np.arange(len(first))
        return pa.table({"a": node.take(pa.array(first[other])), "b": node.filter(pa.array(other)), "similarity": pa.array(np.full(int(other.sum()), threshold))})

    return links


class NearCopies:
    """One run over docs (doc_id, text); links holds the verified pairs of nodes so far.

    Tables that are joined are written first: a join of two plain exchanges can be split where a key is hot, and a small side is broadcast.
    """

    def __init__(self, docs: DataFrame, threshold: float = SIMILARITY):
        spark = docs.sparkSession
        self.threshold = threshold
        self.table = spark.sparkContext.broadcast(frequency_table(docs))
        rows = docs.select("doc_id", "text", whole_row(docs, 1).alias("key"), whole_row(docs, 2).alias("other"))
        kind = docs.schema["doc_id"].dataType.simpleString()
        self.sketches = written(rows.mapInArrow(_sketcher(self.table), f"key long, other long, doc_id {kind}, node binary, bands array<long>, samples array<tinyint>"))
        first = F.min(F.struct("key", "other")).alias("row")
        self.nodes = written(self.sketches.where("bands is not null").groupBy("node").agg(first, F.first("bands").alias("bands"), F.first("samples").alias("samples")))
        members = written(self.nodes.select("node", F.explode("bands").alias("band")))
        shared = written(members.groupBy("band").agg(F.min("node").alias("least"), F.max("node").alias("most")).where("least < most").select("band", "least"))
        self.members = written(members.join(shared, "band"))
        involved = written(self.members.select("node").distinct().join(self.nodes.select("node", "row"), "node").select("node", "row.*"))
        sieve = F.broadcast(involved.select(F.pmod("key", F.lit(BUCKETS)).alias("bucket")).distinct())
        near = rows.select("text", "key", "other", F.pmod("key", F.lit(BUCKETS)).alias("bucket")).join(sieve, "bucket", "left_semi")
        self.texts = written(near.join(involved, ["key", "other"]).select("node", "text").dropDuplicates(["node"]))
        self.links = self.verified(self.members.where("least < node").select(F.col("least").alias("a"), F.col("node").alias("b")).distinct())
        self.settle()

    def verified(self, pairs: DataFrame) -> DataFrame:
        one, two = (self.texts.select(F.col("node").alias(c), F.col("text").alias(f"text_{c}")) for c in "ab")
        found = pairs.join(one, "a").join(two, "b").select("a", "b", "text_a", "text_b").mapInArrow(_verifier(self.table), LINKS)
        return written(found.where(F.col("similarity") >= self.threshold))

    def settle(self) -> None:
        """What buckets with several components still hold."""
        labels = components(self.links)
        placed = written(self.members.select("band", "node").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node")))
        low, high = F.min("label").alias("low"), F.max("label").alias("high")
        sizes = written(placed.groupBy("band").agg(low, high, F.count(F.lit(1)).alias("n"), F.min("node").alias("lead")).where("low < high").select("band", "n", "lead"))
        few = written(placed.join(sizes.where(F.col("n") <= SMALL).select("band"), "band"))
        few = written(few.join(self.nodes.select("node", "samples"), "node"))
        other = few.select("band", F.col("node").alias("b"), F.col("label").alias("label_b"), F.col("samples").alias("samples_b"))
        many = written(placed.join(sizes.where(F.col("n") > SMALL), "band").select(F.col("node").alias("a"), F.col("lead").alias("b")))
        self.add(self.verified(self._unlike(few.join(other, (few["band"] == other["band"]) & (F.col("node") < F.col("b"))))))
        self.add(self._in_blocks(many))

    @staticmethod
    def _unlike(pairs: DataFrame) -> DataFrame:
        """Pairs a < b of different components, without those whose samples exclude the threshold for both similarities."""

        def agreeing(first: int):
            one, two = (F.slice(c, first, ROWS * BANDS).alias(n) for c, n in (("samples", "x"), ("samples_b", "y")))
            return F.size(F.filter(F.arrays_zip(one, two), lambda z: z["x"] == z["y"])) >= LEAST_AGREEING

        return pairs.where((F.col("label") != F.col("label_b")) & (agreeing(1) | agreeing(1 + ROWS * BANDS))).select(F.least("node", "b").alias("a"), F.greatest("node", "b").alias("b")).distinct()

    def add(self, found: DataFrame) -> None:
        self.links = written(self.links.unionByName(found))

    def _in_blocks(self, together: DataFrame) -> DataFrame:
        """Links among nodes that large buckets put together (a: node, b: leader), found by comparing blocks of them."""
        clusters = components(together).withColumnRenamed("label", "cluster")
        texts = written(self.texts.join(clusters, "node").withColumn("bytes", F.octet_length("text")))
        blocks = F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_NODES), F.ceil(F.sum("bytes") / BLOCK_BYTES))
        blocks = written(texts.groupBy("cluster").agg(blocks.cast("int").alias("blocks")))
        placed = texts.join(blocks, "cluster").withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        placed = placed.select("cluster", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "node", "text")
        return written(placed.groupBy("cluster", "i", "j").applyInArrow(_block_comparer(self.table, self.threshold), LINKS))

    def classes(self) -> DataFrame:
        """key, other, doc_id, node, label for every row of docs; label names the class."""
        labels = components(self.links)
        return self.sketches.select("key", "other", "doc_id", "node").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))


def near_duplicates(docs: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """For each row of docs: doc_id, class_id (the least doc_id of its class) and class_size."""
    rows = written(NearCopies(docs.select("doc_id", "text"), threshold).classes())
    named = written(rows.groupBy("label").agg(F.min("doc_id").alias("class_id"), F.count(F.lit(1)).alias("class_size")))
    return rows.join(named, "label").select("doc_id", "class_id", "class_size")


def without_near_copies(docs: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """docs with one document of each class, that of the least doc_id (a null counts as larger than all), then by a hash of the row.

    Rows are told apart by 128 bits of hashes of all their columns. Only the keys of rows that go, and of kept rows that are repeated, are joined to
    the texts, behind a sieve of key buckets.
    """
    rows = written(NearCopies(docs, threshold).classes().select("key", "other", "doc_id", "label"))
    order = F.struct(F.col("doc_id").isNull(), "doc_id", "key", "other")
    first = written(rows.groupBy("label").agg(F.min(order).alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("label", F.col("first.key").alias("first_key"), F.col("first.other").alias("first_other")))
    stays = (F.col("key") == F.col("first_key")) & (F.col("other") == F.col("first_other"))
    marks = written(rows.join(first, "label").groupBy("key", "other").agg(F.max(stays).alias("stays"), F.count(F.lit(1)).alias("n")).where("not stays or n > 1"))
    p = unused_prefix(docs)
    keyed = docs.withColumns({f"{p}key": whole_row(docs, 1), f"{p}other": whole_row(docs, 2)})
    names = {"key": f"{p}mark", "other": f"{p}mark_other"}
    marks = marks.withColumnsRenamed(names)
    on = (F.col(f"{p}key") == F.col(f"{p}mark")) & (F.col(f"{p}other") == F.col(f"{p}mark_other"))
    sieve = F.broadcast(marks.select(F.pmod(f"{p}mark", F.lit(BUCKETS)).alias(f"{p}bucket")).distinct())
    inside = F.pmod(f"{p}key", F.lit(BUCKETS)) == F.col(f"{p}bucket")
    own = [F.col(f"`{c}`") for c in docs.columns]
    never = keyed.join(sieve, inside, "left_anti").select(*own)
    maybe = keyed.join(sieve, inside, "left_semi")
    small = broadcast_if_small(marks.select(*names.values()))
    again = maybe.join(broadcast_if_small(marks.where("stays").select(*names.values())), on, "left_semi").dropDuplicates([f"{p}key", f"{p}other"])
    return never.unionByName(maybe.join(small, on, "left_anti").select(*own)).unionByName(again.select(*own))
