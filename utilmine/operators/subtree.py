"""The search inside workers: baskets projected on their first item, walked depth-first over chunks of itemsets.

Baskets are projected by workers, too: each packs what a group of roots needs of a chunk of baskets into one row of flat arrays, without the tail items
that may not follow the root by the pair table, so a basket item costs bytes and not a struct in an array of the exchange and its sort.
A worker then holds the projected baskets of its roots as flat arrays. A chunk of itemsets with their occurrences is expanded at once: all tail
items become child occurrences, sorted and summed by child; children that may go on are cut into chunks of bounded size,
smaller ones the more entries wait above them, so memory hardly follows the depth of the tree and not its width. An itemset is its last item and
the place of its prefix in the chunk above, and is spelled out only when it is found, so its cost does not follow its length.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, GroupedData
from pyspark.sql import functions as F

from utilmine.operators.search import RESULT, Options
from utilmine.plans.cut import broadcast_if, broadcast_if_small, cached
from utilmine.plans.encode import Dictionary

#: Entries that a chunk of itemsets expands to, or that are packed at once.
CHUNK = 1 << 18
#: Entries for which all chunks that wait may stand, and those that a chunk may expand to at any depth.
STACK, LEAST = 1 << 21, 1 << 10
#: Found itemsets, and items in them, after which a worker gives them out.
BATCH, CELLS = 1 << 14, 1 << 19


def _after(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All indices of the ranges start..end - 1, and the range of each."""
    n = end - start
    of = np.repeat(np.arange(len(n)), n)
    return np.arange(len(of)) - np.repeat(np.cumsum(n) - n - start, n), of


class Walk:
    """One worker's data: entries r, u, ru of all projected baskets end to end; stop: where the basket of each entry ends; n: how many
    baskets an entry stands for. visited: itemsets met. counting: what is found is counted in hits and not spelled out."""

    def __init__(self, r: np.ndarray, u: np.ndarray, ru: np.ndarray, stop: np.ndarray, n: np.ndarray, options: Options, pairs: tuple[np.ndarray, np.ndarray] | None, width: int):
        self.r, self.u, self.ru, self.stop, self.n, self.options, self.pairs, self.width = r, u, ru, stop, n, options, pairs, width
        self.visited = self.hits = 0
        self.counting = False
        self.found: list[tuple[np.ndarray, ...]] = []

    def run(self, at: np.ndarray, mu: np.ndarray) -> Iterator[pa.RecordBatch]:
        """What is found, as it is found. at: the entries of the roots; mu: the threshold of each."""
        order = np.argsort(self.r[at], kind="stable")
        at = at[order]
        heads = np.flatnonzero(np.append(True, self.r[at][1:] != self.r[at][:-1]))
        owner = np.cumsum(np.isin(np.arange(len(at)), heads)) - 1
        # 64 bits: names of pairs are products of ranks
        roots = self.r[at][heads].astype(np.int64)
        self.path = []
        # the chunks left of each expanded chunk, and how many entries these stood for when made
        left = [(len(at), self._chunks(1, roots, np.zeros(len(roots), np.int64), mu[order][heads], owner, at, self.u[at], None, self._room(len(at))))]
        self.visited += len(roots)
        while left:
            if not left[-1][1]:
                left.pop()
                continue
            chunk = left[-1][1].pop()
            k, last, parent = chunk[:3]
            self.path[k - 1 :] = [(last.copy(), parent.copy())]
            live = yield from self._report(*chunk)
            if live is not None:
                held = sum(n for n, _ in left)
                del chunk
                left.append(self._expand(*live, held))
        yield from self.batches()

    @staticmethod
    def _room(held: int) -> int:
        """Entries that a chunk may expand to beside those that wait: less and less, so that all chunks that wait stay below STACK (but for LEAST at each depth)."""
        return max(min(LEAST, CHUNK), min(CHUNK, (STACK - held) // 8))

    def _chunks(self, k, last, parent, mu, owner, at, iu, beside, most):
        """Itemsets of k items dealt to chunks that expand to at most `most` entries at once (one itemset may be more)."""
        stops = np.cumsum(np.bincount(owner, minlength=len(last)))
        work = np.cumsum(self.stop[at] - at)[stops - 1]
        chunks, first = [], 0
        while first < len(last):
            to = max(first + 1, int(np.searchsorted(work, (work[first - 1] if first else 0) + most, "right")))
            a, b = stops[first - 1] if first else 0, stops[to - 1]
            chunks.append((k, last[first:to], parent[first:to], mu[first:to], owner[a:b] - first, at[a:b], iu[a:b], beside))
            first = to
        return chunks

    def _report(self, k, last, parent, mu, owner, at, iu, beside):
        """Gives out the found itemsets of a chunk; the chunk with its occurrences that may go on, or none."""
        o, n = self.options, len(last)
        heads = np.searchsorted(owner, np.arange(n))  # occurrences stand by their itemset, and each has some
        total, support, rest = (np.add.reduceat(x, heads) for x in (iu, self.n[at], self.ru[at]))
        gain, most = (support, support) if o.measure == "support" else (total, total + rest)
        hits = np.flatnonzero(gain >= mu)
        self.hits += len(hits)
        # long itemsets in smaller parts
        part = max(1, min(BATCH, CELLS // k))
        for i in range(0, 0 if self.counting else len(hits), part):
            hit = hits[i : i + part]
            self.found.append((self._named(k, hit), mu[hit], total[hit], support[hit]))
            if sum(len(x[1]) for x in self.found) >= BATCH or sum(x[0].size for x in self.found) >= CELLS:
                yield from self.batches()
        if o.max_len is not None and k >= o.max_len:
            return None
        live = (most >= mu)[owner]
        live &= self.stop[at] > at + 1
        return (k, last, parent, mu, owner[live], at[live], iu[live], beside) if live.any() else None

    def _named(self, k: int, of: np.ndarray) -> np.ndarray:
        """The itemsets of the chunk at depth k that stand at the given places: each item from the chunk of its depth."""
        nodes = np.empty((len(of), k), np.int32)
        for i in range(k - 1, -1, -1):
            last, parent = self.path[i]
            nodes[:, i], of = last[of], parent[of]
        return nodes

    def _expand(self, k, last, above, mu, owner, at, iu, beside, held):
        """How many entries the children of a chunk stand for, and their chunks. owner, at, iu: occurrences that go on.

        beside: sorted (parent, last) numbers of the staying itemsets among which the chunk's are; an item may follow an itemset only if it stays beside it.
        """
        o = self.options
        tail, of = _after(at + 1, self.stop[at])
        parent, y = owner[of], self.r[tail]
        keep = np.ones(len(y), bool)
        if beside is not None:
            wanted = above[parent] * self.width + y
            spot = np.minimum(np.searchsorted(beside, wanted), len(beside) - 1)
            keep &= beside[spot] == wanted
        if self.pairs is not None:
            names, twu = self.pairs
            wanted = last[parent] * self.width + y
            spot = np.minimum(np.searchsorted(names, wanted), len(names) - 1)
            keep &= (names[spot] == wanted) & (twu[spot] >= mu[parent])
        tail, of, parent, y = tail[keep], of[keep], parent[keep], y[keep]
        if not len(tail):
            return 0, []
        key = parent * self.width + y
        order = np.argsort(key, kind="stable")
        key, tail, of = key[order], tail[order], of[order]
        heads = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        child = np.repeat(np.arange(len(heads)), np.diff(np.append(heads, len(key))))
        down_iu = iu[of] + self.u[tail]
        names, parents = key[heads], key[heads] // self.width
        stays = np.ones(len(heads), bool)
        if o.look and o.measure == "utility":
            bound = np.add.reduceat(iu[of] + self.ru[at][of], heads)
            stays = bound >= mu[parents]
        names, parents = names[stays], parents[stays]
        kept = stays[child]
        child = (np.cumsum(stays) - 1)[child[kept]]
        tail, down_iu = tail[kept], down_iu[kept]
        self.visited += len(names)
        if not len(names):
            return 0, []
        most = self._room(held + len(tail))
        return len(tail), self._chunks(k + 1, names % self.width, parents, mu[parents], child, tail, down_iu, names if o.variant != "base" else None, most)

    def batches(self) -> Iterator[pa.RecordBatch]:
        found, self.found = self.found, []
        for nodes, mu, total, support in found:
            offsets = pa.array(np.arange(len(nodes) + 1, dtype=np.int32) * nodes.shape[1])
            yield pa.record_batch({"node": pa.ListArray.from_arrays(offsets, pa.array(nodes.ravel())), "mu1": pa.array(mu), "iu": pa.array(total), "support": pa.array(support)})


def _walk(batches: Iterator[pa.RecordBatch], options: Options, pairs, width: int) -> tuple[Walk, Iterator[pa.RecordBatch]]:
    group = pa.Table.from_batches(list(batches))
    column = lambda name, kind: np.frombuffer(b"".join(x for x in group[name].to_pylist() if x), kind)
    known = group.filter(pa.compute.is_valid(group["root"]))
    ranks, mu = known["root"].to_numpy(), known["mu1"].to_numpy()
    order = np.argsort(ranks)
    sizes = column("size", np.int32).astype(np.int64)
    ends = np.cumsum(sizes)
    r = column("r", np.int32)
    w = Walk(r, column("u", np.int64), column("ru", np.int64), np.repeat(ends, sizes), np.repeat(column("n", np.int64), sizes), options, pairs.value[:2] if pairs is not None else None, width)
    at = ends - sizes
    return w, w.run(at, mu[order][np.searchsorted(ranks[order], r[at])])


def walker(options: Options, pairs, width: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Gives what it finds in batches, so that a worker holds no more of it than BATCH rows or a chunk."""

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _walk(batches, options, pairs, width)[1]

    return walk


def counter(options: Options, pairs, width: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, found = _walk(batches, options, pairs, width)
        w.counting = True
        for _ in found:
            pass
        yield pa.record_batch({"visited": pa.array([w.visited]), "found": pa.array([w.hits])})

    return count


PACKED = "__group int, root int, mu1 long, size binary, n binary, r binary, u binary, ru binary"


def packer(groups: int, pairs, width: int, chosen) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Baskets (n, its) as rows of PACKED, one for each group of roots (rank modulo groups) and chunk: sizes and n of its projected baskets, and their entries
    end to end, each basket from its root on. chosen: for each rank whether it is a root, all if none."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            its = batch["its"]
            offsets = its.offsets.to_numpy().astype(np.int64)
            entries, offsets = its.flatten(), offsets - offsets[0]
            r, u, ru = (entries.field(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("r", "u", "ru"))
            stop, n = np.repeat(offsets[1:], np.diff(offsets)), np.repeat(batch["n"].to_numpy(), np.diff(offsets))
            roots = np.arange(len(r)) if chosen is None else np.flatnonzero(chosen.value[r])
            ends, first = np.cumsum(stop[roots] - roots), 0
            while first < len(roots):
                last = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + CHUNK, "right")))
                yield from _packed_chunk(roots[first:last], r, u, ru, n, stop, groups, pairs, width)
                first = last

    return pack


def _packed_chunk(at, r, u, ru, n, stop, groups: int, pairs, width: int) -> Iterator[pa.RecordBatch]:
    at = at[np.lexsort((r[at], r[at] % groups))]
    tail, of = _after(at + 1, stop[at])
    if pairs is not None:
        names, _, strong = pairs.value
        wanted = r[at][of] * width + r[tail]
        spot = np.minimum(np.searchsorted(names, wanted), len(names) - 1)
        keep = (names[spot] == wanted) & strong[spot] if len(names) else np.zeros(len(of), bool)
        tail, of = tail[keep], of[keep]
    size = 1 + np.bincount(of, minlength=len(at))
    # roots that nothing follows are only summed: those of a rank stand beside each other
    alone = size == 1
    heads = np.append(True, ~(alone[1:] & alone[:-1] & (r[at][1:] == r[at][:-1])))
    first = np.flatnonzero(heads)
    sizes, begin = size[first], np.cumsum(size[first]) - size[first]
    entry = np.empty(sizes.sum(), np.int64)
    is_root = np.zeros(len(entry), bool)
    is_root[begin] = True
    entry[is_root], entry[~is_root] = at[first], tail
    of_u, of_ru, many = u[entry], ru[entry], np.add.reduceat(n[at], first)
    of_u[begin], of_ru[begin] = np.add.reduceat(u[at], first), np.add.reduceat(ru[at], first)
    ranks = r[entry].astype(np.int32)
    own = r[at][first] % groups
    cut = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
    ends, entry_ends = np.append(cut[1:], len(own)), np.append(begin[cut[1:]], len(entry))
    spans, entry_spans = list(zip(cut, ends, strict=True)), list(zip(begin[cut], entry_ends, strict=True))
    of_bytes = lambda x, where: pa.array([x[a:b].tobytes() for a, b in where], pa.binary())
    blank = lambda kind: pa.nulls(len(cut), kind)
    columns = [pa.array(own[cut].astype(np.int32)), blank(pa.int32()), blank(pa.int64()), of_bytes(sizes.astype(np.int32), spans), of_bytes(many, spans)]
    columns += [of_bytes(x, entry_spans) for x in (ranks, of_u, of_ru)]
    yield pa.record_batch(columns, names=["__group", "root", "mu1", "size", "n", "r", "u", "ru"])


def packed(enc: DataFrame, dictionary: Dictionary, groups: int, pairs, roots: DataFrame | None = None) -> DataFrame:
    """Rows of PACKED: the projected baskets of all roots (or of the given ones), and a row for each root with its threshold."""
    spark, chosen = enc.sparkSession, None
    known = dictionary.items
    if roots is not None:
        known = known.join(roots.select("rank"), "rank", "left_semi")
        is_root = np.zeros(dictionary.n + 1, bool)
        is_root[known.select("rank").toArrow()["rank"].to_numpy()] = True
        chosen = spark.sparkContext.broadcast(is_root)
    rows = enc.select("n", "its").mapInArrow(packer(groups, pairs, dictionary.n + 1, chosen), PACKED)
    blobs = [F.lit(None).cast("binary").alias(c) for c in ("size", "n", "r", "u", "ru")]
    return rows.unionByName(known.select((F.col("rank") % groups).alias("__group"), F.col("rank").alias("root"), F.col("mu").alias("mu1"), *blobs))


def projected(enc: DataFrame, dictionary: Dictionary, roots: DataFrame | None = None) -> DataFrame:
    """root, mu1, n, tail: for each basket and root in it, the basket from the root on."""
    mu = broadcast_if(dictionary.items.select(F.col("rank").alias("root"), F.col("mu").alias("mu1")), dictionary.n)
    rows = enc.select(F.posexplode("its").alias("p", "x"), "its", "n")
    rows = rows.select(F.col("x.r").alias("root"), "n", F.slice("its", F.col("p") + 1, F.size("its")).alias("tail")).join(mu, "root")
    return rows.join(broadcast_if_small(roots.select(F.col("rank").alias("root"))), "root", "left_semi") if roots is not None else rows


def shipped(pairs: DataFrame | None, dictionary: Dictionary, most_pairs: int = 4_000_000):
    """The pair table for workers (names of pairs in order, their weights, and whether that reaches the threshold of the first), or none if it is large."""
    if pairs is None:
        return None
    width = dictionary.n + 1
    if dictionary.n * (dictionary.n - 1) // 2 > most_pairs:  # else there cannot be as many, and they need not be counted
        pairs = cached(pairs)
        if pairs.limit(most_pairs + 1).count() > most_pairs:
            pairs.unpersist()
            return None
    mu = broadcast_if(dictionary.items.select(F.col("rank").alias("a"), "mu"), dictionary.n)
    found = pairs.join(mu, "a").select((F.col("a").cast("long") * width + F.col("b")).alias("name"), "twu", (F.col("twu") >= F.col("mu")).alias("strong")).toArrow()
    pairs.unpersist()
    name, twu, strong = (found[c].to_numpy() for c in ("name", "twu", "strong"))
    order = np.argsort(name)
    return dictionary.items.sparkSession.sparkContext.broadcast((name[order], twu[order], strong[order]))


def _by_group(rows: DataFrame, groups: int) -> GroupedData:
    """Dealt to a task for each group or so: the rows are few and small for the work that they stand for, so tasks by their bytes would be too few."""
    return rows.repartition(groups, "__group").groupBy("__group")


def mine_subtrees(rows: DataFrame, options: Options, pairs, width: int, groups: int) -> DataFrame:
    """Walks the packed rows by their groups. The pair table goes along if it is shipped; without it results are the same."""
    return _by_group(rows, groups).applyInArrow(walker(options, pairs, width), RESULT)


def count_subtrees(rows: DataFrame, options: Options, pairs, width: int, groups: int) -> DataFrame:
    """visited, found of each group."""
    return _by_group(rows, groups).applyInArrow(counter(options, pairs, width), "visited long, found long")
