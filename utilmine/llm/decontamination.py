"""Benchmark decontamination: SimHash over item-sized windows, a multi-index of Hamming blocks, exact verification.

A benchmark item of n words is looked for in windows of n words of every document; a shorter document is one window. A window and an item that share no
five-word shingle have similarity 0, so only windows over a shingle of some item (found by hash in the scan) are fingerprinted; this
drops nothing that the verification could accept. The 64-bit fingerprints of items are kept in one table for each block of
bits, holding for each block value the items within radius // blocks of it: two fingerprints within the radius must agree that
closely in one block at least, so the lookup returns every item within the radius. Candidates within it are verified by the
weighted Jaccard similarity of their shingles (weights: counts).

Words are runs of letters and digits, without case. An item of fewer than five words has one shingle, all its words.

The benchmark does not grow with the corpus; its size is checked and a larger one is refused. Documents are read in one scan
without an exchange.

Defined results: a null text or item has no words and matches nothing; a null doc_id is reported as null; repeated rows are reported each; an
item of null id is reported as null, items that share an id are looked for each (a document can then have several rows of that id); empty
tables give an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from utilmine.llm import tokens
from utilmine.llm.shared import plain_names, unused_prefix
from utilmine.llm.tokens import ALNUM_WORD, Block, mix

WIDTH, SIMILARITY = 5, 0.8
RADIUS, BLOCKS = 22, 7
MOST_ITEM_BYTES = 64 << 20
SIEVE_BITS = 20
STRETCH = 20_000


def _word_block(texts: list[str | None]) -> Block:
    block = next(tokens.blocks(pa.array(texts, pa.string()), 1 << 62))
    block.words(ALNUM_WORD)
    return block


def signs(shingles: np.ndarray) -> np.ndarray:
    """A row of 64 values -1 or 1 for each shingle."""
    return (np.unpackbits(mix(shingles ^ np.uint64(0x5851F42D4C957F2D)).view(np.uint8).reshape(-1, 8), axis=1).astype(np.int32) << 1) - 1


def packed(sums: np.ndarray) -> np.ndarray:
    return np.packbits(sums > 0, axis=1).view(np.uint64).ravel()


def covered(starts: np.ndarray, span: int, low: int, high: int) -> np.ndarray:
    """The positions from low to before high that lie in [s, s + span) for some s of starts, in memory of the order of high - low."""
    edges = np.zeros(max(high - low, 0) + 1, np.int64)
    np.add.at(edges, np.clip(starts - low, 0, len(edges) - 1), 1)
    np.add.at(edges, np.clip(starts + span - low, 0, len(edges) - 1), -1)
    return low + np.flatnonzero(np.cumsum(edges)[:-1] > 0)


class Item:
    def __init__(self, item_id: int, n_words: int, shingles: np.ndarray):
        self.id, self.n, self.width = item_id, n_words, min(n_words, WIDTH)
        self.order = shingles
        self.shingles, self.counts = np.unique(shingles, return_counts=True)
        self.print = packed(signs(shingles).sum(0, keepdims=True))[0]


class Index:
    """Items by number of words, a sieve of their shingles, and the block tables."""

    def __init__(self, rows: list[tuple[int, str | None]], radius: int = RADIUS, blocks: int = BLOCKS):
        self.radius = radius
        self.items: list[Item] = []
        for item_id, text in rows:
            if text and (block := _word_block([text])).counts[0]:
                n = int(block.counts[0])
                self.items.append(Item(item_id, n, block.shingles(block.hashes(fold=True), min(n, WIDTH))[0]))
        self.prints = np.array([i.print for i in self.items], np.uint64)
        self.sizes = np.array([i.n for i in self.items], np.int64)
        edges = np.linspace(0, 64, blocks + 1).astype(int)
        self.cuts = [(np.uint64(a), int(b - a)) for a, b in zip(edges[:-1], edges[1:], strict=True)]
        near = radius // blocks
        self.tables = []
        for at, bits in self.cuts:
            values = self._block(self.prints, at, bits)
            all_values = np.arange(1 << bits, dtype=np.uint64)
            self.tables.append([np.flatnonzero(np.bitwise_count(values ^ v) <= near) for v in all_values])
        self.by_width = {}
        for width in sorted({i.width for i in self.items}):
            of = [(s, i.n) for i in self.items if i.width == width for s in i.shingles]
            shingles, sizes = np.array([s for s, _ in of], np.uint64), np.array([n for _, n in of])
            order = np.lexsort((sizes, shingles))
            sieve = np.zeros(1 << SIEVE_BITS, bool)
            sieve[(shingles >> np.uint64(64 - SIEVE_BITS)).astype(np.int64)] = True
            self.by_width[width] = (shingles[order], sizes[order], sieve)

    @staticmethod
    def _block(prints: np.ndarray, at: np.uint64, bits: int) -> np.ndarray:
        return (prints >> at) & np.uint64((1 << bits) - 1)

    def hits(self, shingles: np.ndarray, width: int) -> np.ndarray:
        """Positions of shingles that some item has."""
        known, _, sieve = self.by_width[width]
        maybe = np.flatnonzero(sieve[(shingles >> np.uint64(64 - SIEVE_BITS)).astype(np.int64)])
        at = np.searchsorted(known, shingles[maybe])
        return maybe[known[np.minimum(at, len(known) - 1)] == shingles[maybe]]

    def candidates(self, prints: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """All pairs of a fingerprint and an item of this size within the radius."""
        windows, items = [], []
        for (at, bits), table in zip(self.cuts, self.tables, strict=True):
            values = self._block(prints, at, bits).astype(np.int64)
            for v in np.unique(values):
                if len(found := table[v]) and len(found := found[self.sizes[found] == size]):
                    rows = np.flatnonzero(values == v)
                    windows.append(np.repeat(rows, len(found)))
                    items.append(np.tile(found, len(rows)))
        if not windows:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        pairs = np.unique(np.concatenate(windows) * len(self.items) + np.concatenate(items))
        w, i = pairs // len(self.items), pairs % len(self.items)
        inside = np.bitwise_count(prints[w] ^ self.prints[i]) <= self.radius
        return w[inside], i[inside]

    def search(self, shingles: np.ndarray, width: int, found: np.ndarray, threshold: float) -> list[tuple[int, int, float]]:
        """The best window for each item that one text has: item number, first word, similarity."""
        best: dict[int, tuple[float, int]] = {}
        known, known_sizes, _ = self.by_width[width]
        left, right = np.searchsorted(known, shingles[found]), np.searchsorted(known, shingles[found], "right")
        for size in np.unique(np.concatenate([known_sizes[a:b] for a, b in zip(left, right, strict=True)])):
            span = min(size - width + 1, len(shingles))
            own = found[[size in known_sizes[a:b] for a, b in zip(left, right, strict=True)]]
            starts = covered(own - (span - 1), span, 0, len(shingles) - span + 1)
            for part in np.split(starts, range(STRETCH, len(starts), STRETCH)):
                if not len(part):
                    continue
                low, high = int(part[0]), int(part[-1]) + span
                inner = covered(part, span, low, high)
                sums = np.zeros((len(inner) + 1, 64), np.int32)
                np.cumsum(signs(shingles[inner]), 0, out=sums[1:])
                at = np.searchsorted(inner, part)
                w, items = self.candidates(packed(sums[at + span] - sums[at]), size)
                for start, i in zip(part[w], items, strict=True):
                    value = self.similarity(shingles[start : start + span], self.items[i])
                    if value >= threshold and (int(i) not in best or (-value, start) < (-best[int(i)][0], best[int(i)][1])):
                        best[int(i)] = (value, int(start))
        return [(i, start, value) for i, (value, start) in sorted(best.items())]

    @staticmethod
    def similarity(window: np.ndarray, item: Item) -> float:
        shingles, counts = np.unique(window, return_counts=True)
        _, a, b = np.intersect1d(shingles, item.shingles, assume_unique=True, return_indices=True)
        both = int(np.minimum(counts[a], item.counts[b]).sum())
        return both / (len(window) + len(item.order) - both)


def _searcher(index: Index, threshold: float):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, out = batch.column(0), []
            for block in tokens.blocks(batch.column(1)):
                block.words(ALNUM_WORD)
                hashes = block.hashes(fold=True)
                for width in index.by_width:
                    shingles, owner = block.shingles(hashes, width)
                    hits = index.hits(shingles, width)
                    for text in np.unique(owner[hits]):
                        a, b = np.searchsorted(owner, [text, text + 1])
                        own = hits[np.searchsorted(hits, a) : np.searchsorted(hits, b)] - a
                        out += [(block.first + int(text), index.items[i].id, start, min(index.items[i].n, int(b - a) + width - 1), value) for i, start, value in index.search(shingles[a:b], width, own, threshold)]
            at, item, start, n, value = zip(*out, strict=True) if out else ((),) * 5
            yield pa.record_batch({"doc_id": doc.take(pa.array(at, pa.int64())), "item_id": pa.array(item, pa.int64()), "start_word": pa.array(start, pa.int64()), "n_words": pa.array(n, pa.int64()), "similarity": pa.array(value, pa.float64())})

    return rows


def benchmark_index(benchmark: DataFrame, most_bytes: int = MOST_ITEM_BYTES) -> Index:
    """The index over item_id, text; a benchmark of more than most_bytes is refused rather than cut."""
    from pyspark.sql import functions as F

    size = benchmark.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if size > most_bytes:
        raise ValueError(f"the benchmark has {size} bytes, more than {most_bytes}; search it in parts")
    rows = ((r["item_id"], r["text"]) for r in benchmark.select("item_id", "text").collect())
    return Index(sorted(rows, key=lambda r: (r[0] is None, r[0] or 0, r[1] or "")))


def contaminated(docs: DataFrame, benchmark: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """A row for each document and item it holds: doc_id, item_id, start_word, n_words, similarity of its best window."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(_searcher(benchmark_index(benchmark), threshold), f"doc_id {kind}, item_id long, start_word long, n_words long, similarity double")


def without_contaminated(docs: DataFrame, benchmark: DataFrame, threshold: float = SIMILARITY) -> DataFrame:
    """docs without those that hold an item; one scan, rows pass or go as they are."""
    index = benchmark_index(benchmark)
    at = docs.columns.index("text")

    def passing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = _searcher(index, threshold)
        for batch in batches:
            numbered = pa.record_batch({"doc_id": pa.array(np.arange(batch.num_rows)), "text": batch.column(at)})
            keep = np.ones(batch.num_rows, bool)
            for found in search(iter([numbered])):
                keep[found.column(0).to_numpy()] = False
            yield batch.filter(pa.array(keep))

    named = docs.toDF(*plain_names(docs.columns, unused_prefix(docs)))
    return named.mapInArrow(passing, named.schema).toDF(*docs.columns)
