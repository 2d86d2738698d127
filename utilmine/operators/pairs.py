"""Itemsets of one and two items, as tiles of two buckets of items each, in workers.

No item gets a global rank and no pair becomes a row before it is found. Workers pack lines by bucket of their items, once; each bucket numbers its
items and gives its lines to the tiles it is in (a bucket with every bucket, itself included), compressed. A tile joins two buckets by basket and sums
the pairs of each item over the baskets it is in: into a row of sums as wide as the other bucket if there are many, else by sorting them.
The two exchanges carry a few bytes for each line and tile, and a tile holds two buckets of lines and the sums of one item.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

#: Lines of a bucket that are aimed at, the fewest buckets, lines that are packed at once, and pairs that are summed at once.
BUCKET, FEWEST, PACKED, BATCH = 3_000_000, 6, 1 << 19, 1 << 18
#: A row of sums is made for an item if it is at most so many times as wide as the item's pairs are many.
WIDE = 32
#: Found pairs that a worker gives out at once.
GIVEN = 1 << 16
BLOB = "__key int, tid binary, item binary, u binary, name binary, mu binary"
FOUND = "key string, k int, utility long, miu long, support long"


def _small(x: np.ndarray) -> bytes:
    """Numbers in as few bytes as the largest needs, compressed."""
    kind = next(t for t in (np.uint8, np.uint16, np.uint32, np.int64) if not len(x) or t is np.int64 or (x.min() >= 0 and x.max() <= np.iinfo(t).max))
    raw = x.astype(kind).tobytes()
    return bytes([np.dtype(kind).itemsize]) + len(raw).to_bytes(8, "little") + pa.Codec("zstd", compression_level=1).compress(raw, asbytes=True)


def _large(b: bytes) -> np.ndarray:
    """The numbers of _small, kept as narrow as they are: to be widened before they are added."""
    kind = {1: np.uint8, 2: np.uint16, 4: np.uint32, 8: np.int64}[b[0]]
    size = int.from_bytes(b[1:9], "little")
    return np.frombuffer(pa.Codec("zstd").decompress(b[9:], decompressed_size=size, asbytes=True) if size else b"", kind)


def _names(x: pa.Array) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, pa.schema({"x": pa.large_string()}), options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
        w.write_batch(pa.record_batch({"x": x.cast(pa.large_string())}))
    return sink.getvalue().to_pybytes()


def _read_names(b: bytes) -> pa.Array:
    found = pa.ipc.open_stream(b).read_all()["x"].combine_chunks()
    return found.combine_chunks() if isinstance(found, pa.ChunkedArray) else found


def _sums(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The keys in order, the sum of each and how often it comes."""
    order = np.argsort(keys)
    keys = keys[order]
    heads = np.flatnonzero(np.append(True, keys[1:] != keys[:-1])) if len(keys) else np.zeros(0, np.int64)
    return keys[heads], np.add.reduceat(values[order], heads) if len(keys) else values, np.diff(np.append(heads, len(keys)))


def _joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches of at least PACKED rows, but the last."""
    held: list[pa.RecordBatch] = []
    for batch in batches:
        held.append(batch)
        if sum(map(len, held)) >= PACKED:
            yield pa.concat_batches(held)
            held = []
    if sum(map(len, held)):
        yield pa.concat_batches(held)


def _by_bucket(n: int, kind: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Lines (tid, item, u) or thresholds (item, mu), as one blob for each bucket and batch."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _joined(batches):
            coded = batch["item"].dictionary_encode()
            of = np.fromiter((crc32(x.encode()) % n for x in coded.dictionary.to_pylist()), np.int64, len(coded.dictionary))
            code = coded.indices.to_numpy().astype(np.int64)
            columns = {c: batch[c].to_numpy().astype(np.int64) for c in batch.schema.names if c != "item"}
            for b in range(n):
                at = np.flatnonzero(of[code] == b)
                if not len(at):
                    continue
                used, own = np.unique(code[at], return_inverse=True)
                blobs = {"tid": None, "item": _small(own), "u": None, "name": _names(coded.dictionary.take(pa.array(used))), "mu": None}
                if kind == "lines":
                    blobs |= {"tid": _small(columns["tid"][at]), "u": _small(columns["u"][at])}
                else:
                    blobs["mu"] = _small(columns["mu"][at])
                yield pa.record_batch([pa.array([b], pa.int32()), *(pa.array([x], pa.binary()) for x in blobs.values())], names=["__key", *blobs])

    return pack


def _to_tiles(n: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The blobs of a bucket as one, its lines in order of baskets, for each of its tiles: numbered n * (lesser bucket) + greater one; the item blob begins
    with the bucket."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tids, items, us, name, least, bucket = [], [], [], [], [], None
        for batch in batches:
            for row in batch.to_pylist():
                bucket = row["__key"]
                own = _large(row["item"])
                name.append(_read_names(row["name"]))
                items.append(own)
                tids.append(_large(row["tid"]) if row["mu"] is None else None)
                us.append(_large(row["u"]) if row["mu"] is None else None)
                least.append(_large(row["mu"]) if row["mu"] is not None else None)
        coded = pa.chunked_array(name).combine_chunks()
        coded = (coded.combine_chunks() if isinstance(coded, pa.ChunkedArray) else coded).dictionary_encode()
        number, start = coded.indices.to_numpy(), np.cumsum([0, *map(len, name)])
        items = [number[start[i] : start[i + 1]][own] for i, own in enumerate(items)]
        mu = np.full(len(coded.dictionary), -1, np.int64)
        for own, values in zip(items, least, strict=True):
            if values is not None:
                mu[own] = values
        lines = [i for i, t in enumerate(tids) if t is not None]
        if not lines:
            return
        tid, item, u = (np.concatenate([x[i] for i in lines]) for x in (tids, items, us))
        del name, items, tids, us, least, number
        if (mu[item] < 0).any():
            raise ValueError("an item has no threshold")
        order = np.lexsort((item, tid))  # by item within a basket, too, so that a pair has one order in all
        tid, item, u = tid[order].astype(np.int64), item[order], u[order]
        blobs = [_small(np.diff(tid, prepend=0)), bucket.to_bytes(4, "little") + _small(item), _small(u), _names(coded.dictionary), _small(mu)]
        for other in range(n):
            a, b = min(bucket, other), max(bucket, other)
            yield pa.record_batch([pa.array([a * n + b], pa.int32()), *(pa.array([x], pa.binary()) for x in blobs)], names=["__key", "tid", "item", "u", "name", "mu"])

    return merge


class _Side:
    """One bucket in a tile: its lines by basket, its items' names and thresholds. tile: the number of the tile."""

    def __init__(self, row: dict):
        self.tile, self.bucket = row["__key"], int.from_bytes(row["item"][:4], "little")
        self.tid, self.item, self.u = np.cumsum(_large(row["tid"]), dtype=np.int64), _large(row["item"][4:]), _large(row["u"])
        self.names, self.mu = _read_names(row["name"]), _large(row["mu"]).astype(np.int64)


class _Found:
    """Sums of pairs (item a of one side, b of the other) that reach their threshold, given out GIVEN or more at once."""

    def __init__(self, one: _Side, other: _Side):
        self.one, self.other, self.held, self.n = one, other, [], 0

    def add(self, a: np.ndarray | int, b: np.ndarray, total: np.ndarray, support: np.ndarray) -> Iterator[pa.RecordBatch]:
        miu = np.minimum(self.one.mu[a], self.other.mu[b])
        hit = np.flatnonzero(total >= miu)
        if len(hit):
            self.held.append((np.broadcast_to(a, b.shape)[hit], b[hit], total[hit].astype(np.int64), miu[hit], support[hit]))
            self.n += len(hit)
        if self.n >= GIVEN:
            yield from self.rest()

    def rest(self) -> Iterator[pa.RecordBatch]:
        if not self.held:
            return
        a, b, total, miu, support = (np.concatenate(x) for x in zip(*self.held, strict=True))
        self.held, self.n = [], 0
        for first in range(0, len(a), 2 * GIVEN):
            at = slice(first, first + 2 * GIVEN)
            x, y = self.one.names.take(pa.array(a[at])), self.other.names.take(pa.array(b[at]))
            ordered = pc.less(x, y)
            key = pc.binary_join_element_wise(pc.if_else(ordered, x, y), pc.if_else(ordered, y, x), pa.scalar(",", pa.large_string()))
            yield pa.record_batch({"key": key.cast(pa.string()), "k": pa.array(np.full(len(x), 2, np.int32)), "utility": pa.array(total[at]), "miu": pa.array(miu[at]), "support": pa.array(support[at])})


def _singles(side: _Side) -> pa.RecordBatch:
    total, support = np.zeros(len(side.mu), np.int64), np.bincount(side.item, minlength=len(side.mu))
    np.add.at(total, side.item, side.u.astype(np.int64))
    at = np.flatnonzero((total >= side.mu) & (support > 0))
    return pa.record_batch({"key": side.names.take(pa.array(at)).cast(pa.string()), "k": pa.array(np.ones(len(at), np.int32)), "utility": pa.array(total[at]), "miu": pa.array(side.mu[at]), "support": pa.array(support[at].astype(np.int64))})


def _tile(n: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """What the pairs of two buckets give, in a tile of one bucket also its items alone."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sides = sorted((_Side(row) for batch in batches for row in batch.to_pylist()), key=lambda x: x.bucket)
        a, b = sides[0], sides[-1]
        same = a.tile // n == a.tile % n
        if len(sides) == 1 and not same:  # no item is in the other bucket
            return
        if same:
            yield _singles(a)
        found = _Found(a, b)
        begin = np.arange(1, len(a.tid) + 1) if same else np.searchsorted(b.tid, a.tid, "left")
        begin, end = begin.astype(np.int32), np.searchsorted(b.tid, a.tid, "right").astype(np.int32)
        a.tid = b.tid = None
        order = np.argsort(a.item, kind="stable")
        order = order[end[order] > begin[order]]
        if len(order):
            most = (int(b.u.max()) + int(a.u.max())) * len(b.u)
            yield from _summed(found, a.item[order], a.u[order], begin[order], end[order], most)
        yield from found.rest()

    return sums


def _summed(found: _Found, item, u, begin, end, most: int) -> Iterator[pa.RecordBatch]:
    """item, u: lines of the one side in order of items; begin, end: where the other side's lines of their basket are; most: no sum is larger."""
    b, width = found.other, len(found.other.mu)
    heads = np.flatnonzero(np.append(True, item[1:] != item[:-1]))
    stops, done = np.append(heads[1:], len(item)), np.append(0, np.cumsum(end - begin, dtype=np.int64))
    pairs = done[stops] - done[heads]
    rows = (WIDE * pairs > width) & (most < 1 << 52)  # doubles add exactly below that
    first = 0
    while first < len(heads):
        if rows[first]:
            yield from found.add(int(item[heads[first]]), *_row_of_sums(b, u, begin, end, done, heads[first], stops[first], width))
            first += 1
            continue
        last = max(first + 1, int(np.searchsorted(done[stops], done[heads[first]] + BATCH, "right")))
        dense = np.flatnonzero(rows[first:last])
        last = first + int(dense[0]) if len(dense) else last
        at, to = heads[first], stops[last - 1]
        n = (end[at:to] - begin[at:to]).astype(np.int64)
        of = np.repeat(np.arange(at, to), n)
        y = np.arange(len(of)) - np.repeat(np.cumsum(n) - n - begin[at:to], n)
        names, total, support = _sums(item[of].astype(np.int64) * width + b.item[y], u[of].astype(np.int64) + b.u[y])
        yield from found.add(names // width, names % width, total, support)
        first = last


def _row_of_sums(b: _Side, u, begin, end, done, at: int, stop: int, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The items that the lines from at to stop meet, with the sums and numbers of their pairs."""
    total = support = None
    while at < stop:
        to = max(at + 1, min(stop, int(np.searchsorted(done, done[at] + BATCH, "right")) - 1))
        spans = [slice(x, y) for x, y in zip(begin[at:to].tolist(), end[at:to].tolist(), strict=True)]
        y = np.concatenate([b.item[x] for x in spans])
        w = np.concatenate([b.u[x] for x in spans]).astype(np.float64) + np.repeat(u[at:to], end[at:to] - begin[at:to])
        sums, count = np.bincount(y, w, width), np.bincount(y, minlength=width)
        total, support = (sums, count) if total is None else (total + sums, support + count)
        at = to
    y = np.flatnonzero(support)
    return y, total[y].astype(np.int64), support[y]


def mine_pairs(lines: DataFrame, thresholds: DataFrame, buckets: int | None = None) -> DataFrame:
    """key, k, utility, miu, support of all high-utility itemsets of one and two items. lines(tid, item, u): one for each basket and item, and read twice
    without a number of buckets; thresholds(item, mu). tid is a BIGINT, items are strings, in keys by their bytes."""
    lines, thresholds = lines.select("tid", "item", "u"), thresholds.select("item", "mu")
    n = buckets or max(FEWEST, -(-lines.count() // BUCKET))
    packed = lines.mapInArrow(_by_bucket(n, "lines"), BLOB).unionByName(thresholds.mapInArrow(_by_bucket(n, "thresholds"), BLOB))
    tiles = packed.groupBy("__key").applyInArrow(_to_tiles(n), BLOB)
    # few tiles that are much work each: more partitions than tiles, so that seldom two meet in a task
    return tiles.repartition(4 * n * (n + 1), "__key").groupBy("__key").applyInArrow(_tile(n), FOUND)
