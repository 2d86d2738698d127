"""Substring dedup by recompression: long passages that an earlier document holds are removed from later ones.

Rounds rename the words of every document: one round names short runs of a repeated symbol, each further round names pairs (a, b)
where a hash of the symbol puts a on the left side and b on the right. Names are hashes of what they stand for, hence global
without any exchange, and a round's decisions depend on adjacent symbols only. So two equal passages get equal symbols except
for a margin at their ends, whose length is bounded by the lengths of the symbols that a round can make.

A window of 50 words keeps a core inside that margin. Its anchor is the longest high-level symbol (then the least by hash)
inside the core, the same for equal windows wherever they stand. All windows that choose an anchor share the words
around it (its context), and lie in its neighbourhood. That turns the search into grouped aggregates over anchors,
a row for about eighteen words:

1. By (context, neighbourhood): the least document. An anchor whose whole neighbourhood stands in an earlier document
   settles all its windows. Copies in any number meet only in this aggregate.
2. Contexts with several neighbourhoods: the first document of each neighbourhood (and it alone) lists its windows under
   (context, window hash); the least document of each settles the rest.

Hashes of 64 bits in pairs verify equality: context and neighbourhood, or context and window, 128 bits from independent hashes.
Documents meet their settled anchors in a join by row key. A broadcast set of at most BUCKETS key buckets first lets
pass, map-side, the documents that cannot have any, so that their texts are not exchanged.

Defined results: a null text has no words and the sha256 of nothing; a null doc_id counts as larger than all others; documents of
equal id never remove from one another; a repeated row gets the same result again; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from utilmine.llm import tokens
from utilmine.llm.shared import written
from utilmine.llm.tokens import WORD_POWERS, Block, mix, prefix, span_hashes

LAST_ID = (1 << 63) - 1
BUCKETS = 1 << 20
SIDE = np.uint64(1)


class Parse:
    """The recompression of a block: symbols with start, end (in words) and name after all rounds."""

    def __init__(self, block: Block, hashes: np.ndarray, longest_run: int, pair_rounds: int):
        n = len(hashes)
        self.owner = np.repeat(np.arange(len(block)), block.counts)
        start, name = np.arange(n), hashes
        start, name = self._runs(start, name, longest_run)
        for level in range(pair_rounds):
            start, name = self._pairs(start, name, level)
        self.start, self.name = start, name
        self.end = np.append(start[1:], n)

    def _joined(self, start: np.ndarray, name: np.ndarray) -> np.ndarray:
        """Whether each symbol and the next belong to one text."""
        own = self.owner[start]
        return own[:-1] == own[1:] if len(start) else np.zeros(0, bool)

    def _runs(self, start: np.ndarray, name: np.ndarray, longest: int) -> tuple[np.ndarray, np.ndarray]:
        """Names maximal runs of 2 to longest equal symbols; longer runs stay as they are, alike at every place in them."""
        if len(start) < 2:
            return start, name
        same = self._joined(start, name) & (name[:-1] == name[1:])
        heads = np.flatnonzero(np.append(True, ~same))
        lengths = np.diff(np.append(heads, len(start)))
        short = (lengths > 1) & (lengths <= longest)
        keep = np.ones(len(start), bool)
        inner = np.repeat(short, lengths)
        inner[heads] = False
        keep[inner] = False
        out = name.copy()
        out[heads[short]] = mix(name[heads[short]] + lengths[short].astype(np.uint64) * np.uint64(0xA0761D6478BD642F))
        return start[keep], out[keep]

    def _pairs(self, start: np.ndarray, name: np.ndarray, level: int) -> tuple[np.ndarray, np.ndarray]:
        if len(start) < 2:
            return start, name
        left = mix(name + np.uint64(0x8BB84B93962EACC9 * (level + 1) % (1 << 64))) & SIDE == 0
        pair = self._joined(start, name) & left[:-1] & ~left[1:]
        at = np.flatnonzero(pair)
        out = name.copy()
        out[at] = mix(mix(name[at] + np.uint64(level + 1)) * np.uint64(3) + name[at + 1])
        keep = np.ones(len(start), bool)
        keep[at + 1] = False
        return start[keep], out[keep]


class Passages:
    """The parameters: windows of width words, rounds, and the margin that follows from them."""

    def __init__(self, width: int = 50, longest_run: int = 2, pair_rounds: int = 2):
        self.width, self.longest_run, self.pair_rounds = width, longest_run, pair_rounds
        sizes = [longest_run * 2**k for k in range(pair_rounds + 1)]  # longest symbols after each round
        self.margin = longest_run + sum(sizes[:-1])
        if width < 2 * (self.margin + sizes[-1]):
            raise ValueError("a window must keep a whole symbol inside its margins")

    def anchors(self, block: Block, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each window in order: its first word and the first and last (exclusive) word of its anchor."""
        p = Parse(block, hashes, self.longest_run, self.pair_rounds)
        n = np.maximum(block.counts - self.width + 1, 0)
        first = np.arange(n.sum()) + np.repeat(block.at[:-1] - (np.cumsum(n) - n), n)
        if not len(first):
            return first, first, first
        low = np.searchsorted(p.start, first + self.margin)
        high = np.searchsorted(p.end, first + self.width - self.margin, "right")  # exclusive
        spread = (np.uint64(63) - (p.end - p.start).astype(np.uint64)) << np.uint64(56)
        rank = spread | (mix(p.name) >> np.uint64(8))
        best = self._least(rank, low, high)
        return first, p.start[best], p.end[best]

    @staticmethod
    def _least(rank: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """The index of the leftmost least rank in each range, from tables of the least over powers of two."""
        level = np.frexp((high - low).astype(np.float64))[1] - 1
        table, out = np.arange(len(rank)), np.empty(len(low), np.int64)
        for k in range(int(level.max()) + 1):
            if k:
                half = 1 << (k - 1)
                a, b = table[:-half], table[half:]
                table = np.where(rank[b] < rank[a], b, a)
            at = np.flatnonzero(level == k)
            a, b = table[low[at]], table[high[at] - (1 << k)]
            out[at] = np.where(rank[b] < rank[a], b, a)
        return out

    def groups(self, block: Block, hashes: np.ndarray) -> tuple[np.ndarray, ...]:
        """For each anchor that windows choose: text, first and last window (both inclusive, as first words), context and neighbourhood hash; and prefix sums for window hashes.

        An anchor's windows are consecutive. Context and neighbourhood come from two independent hashes.
        """
        first, start, end = self.anchors(block, hashes)
        sums, other = prefix(hashes, WORD_POWERS), prefix(mix(hashes + np.uint64(0x51ED270B)), WORD_POWERS)
        if not len(first):
            z = np.zeros(0, np.int64)
            return z, z, z, z.astype(np.uint64), z.astype(np.uint64), other
        own = np.searchsorted(block.at, first, "right") - 1
        change = np.flatnonzero(np.append(True, (start[1:] != start[:-1]) | (own[1:] != own[:-1])))
        last = first[np.append(change[1:], len(first)) - 1]
        begin = first[change]
        s, e, text = start[change], end[change], own[change]
        # what every window that can choose the anchor holds: from margin words before it to margin words after it
        context = mix(span_hashes(sums, s - self.margin, e + self.margin, WORD_POWERS) + (e - s).astype(np.uint64))
        around = span_hashes(other, begin, last + self.width, WORD_POWERS)
        return text, begin, last, context, mix(around + (s - begin).astype(np.uint64) * np.uint64(977) + (last - begin).astype(np.uint64)), other


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def _column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def _anchor_rows(passages: Passages):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key, doc = _column(batch, "key").to_numpy(), _column(batch, "doc").to_numpy()
            for block in tokens.blocks(_column(batch, "text")):
                block.words()
                text, begin, last, context, around, _ = passages.groups(block, block.hashes())
                if len(text):
                    offset = block.at[text]
                    yield pa.record_batch({"context": _signed(context), "around": _signed(around), "doc": pa.array(doc[block.first + text]), "key": pa.array(key[block.first + text]), "at": pa.array((begin - offset).astype(np.int32)), "n": pa.array((last - begin + 1).astype(np.int32))})

    return rows


def _window_rows(passages: Passages):
    """Window hashes of the anchors that a document lists in open_at."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key, doc = _column(batch, "key").to_numpy(), _column(batch, "doc").to_numpy()
            asked = _column(batch, "open_at")
            for block in tokens.blocks(_column(batch, "text")):
                block.words()
                text, begin, last, context, _, other = passages.groups(block, block.hashes())
                at = begin - block.at[text]
                picked = np.zeros(len(text), bool)
                cut = np.searchsorted(text, np.arange(len(block) + 1))
                for i in range(len(block)):
                    wanted = asked[block.first + i].as_py()
                    picked[cut[i] : cut[i + 1]] = np.isin(at[cut[i] : cut[i + 1]], wanted)
                text, begin, last, context = text[picked], begin[picked], last[picked], context[picked]
                n = last - begin + 1
                window = np.repeat(begin, n) + np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                own = np.repeat(text, n)
                if len(own):
                    yield pa.record_batch({"context": _signed(np.repeat(context, n)), "window": _signed(span_hashes(other, window, window + passages.width, WORD_POWERS)), "doc": pa.array(doc[block.first + own]), "key": pa.array(key[block.first + own]), "at": pa.array((window - block.at[own]).astype(np.int32))})

    return rows


def _cleaned(width: int, with_text: bool):
    """Removes the words under windows at..at+n-1 and reports what is left."""

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, spans = _column(batch, "text"), _column(batch, "spans")
            total, gone, digest, kept_text = [], [], [], []
            for i in range(batch.num_rows):
                words = (texts[i].as_py() or "").encode().split()
                found = spans[i].as_py()
                kept = words
                if found:
                    edges = np.zeros(len(words) + 1, np.int32)
                    np.add.at(edges, [x["at"] for x in found], 1)
                    np.add.at(edges, [x["at"] + x["n"] - 1 + width for x in found], -1)
                    kept = [w for w, c in zip(words, np.cumsum(edges[:-1]), strict=True) if not c]
                left = b" ".join(kept)
                total.append(len(words))
                gone.append(len(words) - len(kept))
                digest.append(hashlib.sha256(left).hexdigest())
                kept_text.append(left.decode() if with_text else None)
            out = {"doc_id": _column(batch, "doc_id"), "n_words": pa.array(total, pa.int64()), "n_removed": pa.array(gone, pa.int64()), "kept_sha256": pa.array(digest, pa.string())}
            yield pa.record_batch(out | ({"kept_text": pa.array(kept_text, pa.string())} if with_text else {}))

    return rows


def _buckets(keys: DataFrame) -> DataFrame:
    """The buckets that keys fall into, at most BUCKETS rows at any size of the input, broadcast: a lossless sieve for joins by key."""
    return F.broadcast(keys.select(F.pmod("key", F.lit(BUCKETS)).alias("bucket")).distinct())


def settled_spans(rows: DataFrame, passages: Passages) -> DataFrame:
    """key, at, n: the n windows from word at of the rows with this key start in an earlier document too."""
    ids = rows.select("text", "key", "doc")
    anchors = written(ids.mapInArrow(_anchor_rows(passages), "context long, around long, doc long, key long, at int, n int"))
    # tables that are joined are written first: a join of two plain exchanges can be split where a key is hot
    shared = written(anchors.groupBy("context").agg(F.min("doc").alias("low"), F.max("doc").alias("high")).where("low < high").select("context"))
    known = written(anchors.join(shared, "context"))
    groups = written(known.groupBy("context", "around").agg(F.min("doc").alias("least")))
    forms = written(groups.groupBy("context").agg(F.count(F.lit(1)).alias("forms")))
    several = written(groups.join(forms, "context"))
    told = written(known.join(several, ["context", "around"]).select("key", "doc", "at", "n", "least", "forms"))
    settled = told.where("least < doc").select("key", "at", "n")
    open_at = told.where("least = doc and forms > 1").groupBy("key").agg(F.collect_set("at").alias("open_at"))
    wanted = ids.withColumn("bucket", F.pmod("key", F.lit(BUCKETS))).join(_buckets(open_at), "bucket", "left_semi").join(open_at, "key")
    windows = written(wanted.select("text", "key", "doc", "open_at").mapInArrow(_window_rows(passages), "context long, window long, doc long, key long, at int"))
    first = written(windows.groupBy("context", "window").agg(F.min("doc").alias("low"), F.max("doc").alias("high")).where("low < high").select("context", "window", "low"))
    return settled.union(windows.join(first, ["context", "window"]).where("low < doc").select("key", "at", F.lit(1).alias("n")))


def dedup_passages(docs: DataFrame, width: int = 50, with_text: bool = False, **rounds) -> DataFrame:
    """For each row of docs (doc_id, text): doc_id, n_words, n_removed, kept_sha256 and, if asked for, kept_text (words joined by one space)."""
    passages = Passages(width, **rounds)
    rows = docs.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("key"), F.coalesce("doc_id", F.lit(LAST_ID)).alias("doc"))
    spans = written(settled_spans(rows, passages).groupBy("key").agg(F.collect_list(F.struct("at", "n")).alias("spans")))
    placed = rows.select("doc_id", "text", "key", F.pmod("key", F.lit(BUCKETS)).alias("bucket"))
    maybe = placed.join(_buckets(spans), "bucket", "left_semi").join(spans, "key", "left").select("doc_id", "text", "spans")
    never = placed.join(_buckets(spans), "bucket", "left_anti").select("doc_id", "text", F.lit(None).cast(spans.schema["spans"].dataType).alias("spans"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    return maybe.unionByName(never).mapInArrow(_cleaned(width, with_text), f"doc_id {kind}, n_words long, n_removed long, kept_sha256 string" + ", kept_text string" * with_text)
