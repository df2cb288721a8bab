"""Exact Jaccard join of documents on word n-grams, with a count-vector R-tree, down to connected components.

A document is the set of its distinct n-gram hashes; documents with one set are one node. Two sets of similarity t share
one of their first ``n - ceil(t n) + 1`` elements under any common order, here: n-grams that very many documents hold come last,
the rest by hash. Documents meet in the blocks of such shared elements. The prefixes
are longer than that by a twentieth of n, so that similar sets share about as many elements, and a node with
fewer in blocks is let go.

1. Neighbours by size within a block make a thin set of pairs; each node's likeliest pair is verified, and the
   components of what holds are found. Most copies are settled here, with one verification each.
2. Where a block still holds more than one component, an R-tree over its nodes' count vectors (number of elements per hash
   group) bounds overlaps by sums of coordinate minima, for boxes and then for points. Only pairs across components go
   down the tree; what survives is verified on the sets. No link between components is missed, and none within one is needed.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.llm.common import components, stage
from provgraph.llm.wordkernel import batches, distinct, give_back, window_arrays

GROUPS = 256
HEAD = 6  # a posting shows its node's first tokens, by which a pair is left to its first common block
REGION = np.uint64(3 << 61)  # n-grams below this hash are counted over all documents when the order is made
_U64 = np.uint64


def need(nx: np.ndarray, ny: np.ndarray, percent: int) -> np.ndarray:
    """Least overlap of sets of these sizes with similarity percent / 100."""
    return -(-(percent * (nx.astype(np.int64) + ny)) // (100 + percent))


def shared_least(n: int) -> int:
    """Elements of the prefixes that a set of n must share with each similar one; grows with n."""
    return 1 + n // 20


def prefix_size(n: int, percent: int) -> int:
    """Sets of the similarity share at least the smaller ``shared_least`` of the two within their prefixes."""
    return n - -(-percent * n // 100) + shared_least(n)


def node_id(sorted_hashes: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(sorted_hashes.tobytes(), digest_size=8).digest(), "little", signed=True)


def _sets(texts: list[bytes], k: int) -> Iterator[np.ndarray]:
    h, begin, _, _ = window_arrays(texts, k, True, True)
    for a, b in zip(begin[:-1].tolist(), begin[1:].tolist(), strict=True):
        yield distinct(h[a:b])


MARKED = 24  # bits of a part's number; above them stands what tells the pieces of a hot token's block apart


class Outbox:
    """Gathers (hash, payload columns) and lays them out by the hash's leading bits as one binary row per part.

    A token that comes more than ``split`` times in a buffer is hot: its entries go out as a row of their own, with one of 127 numbers
    above the part's, so that no task gets all of them; the part itself gets one entry of zeros that says so.
    """

    def __init__(self, bits: int, kinds: tuple[type, ...], flush: int = 500_000, split: int = 5_000):
        self.bits, self.kinds, self.flush, self.split = bits, kinds, flush, split
        self.held: list[tuple[np.ndarray, ...]] = []
        self.n = 0

    def add(self, h: np.ndarray, *cols: np.ndarray) -> bool:
        self.held.append((h, *cols))
        self.n += len(h)
        return self.n >= self.flush

    def take(self) -> pa.RecordBatch:
        h, *cols = (np.concatenate(x) for x in zip(*self.held, strict=True)) if self.held else (np.zeros(0, _U64), *(np.zeros(0, k) for k in self.kinds))
        self.held, self.n = [], 0
        order = np.argsort(h)
        h = h[order]
        cols = [c[order].astype(k) for c, k in zip(cols, self.kinds, strict=True)]
        token = h >> _U64(32 - self.bits)
        first = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1]))) if len(h) else np.zeros(0, np.int64)
        many = np.diff(np.append(first, len(h)))
        cold, rows, parts = np.repeat(many <= self.split, many), [], []
        piece = 1 + int(h[:: max(1, len(h) // 64)].sum(dtype=_U64) % _U64(127)) << MARKED
        for a, n in zip(first[many > self.split].tolist(), many[many > self.split].tolist(), strict=True):
            parts.append(piece | int(h[a] >> _U64(64 - self.bits)))
            rows.append([(h[a : a + n] << _U64(self.bits) >> _U64(32)).astype(np.uint32).tobytes(), *(c[a : a + n].tobytes() for c in cols)])
        if rows:
            cold[first[many > self.split]] = True
            for c in cols:
                c[first[many > self.split]] = 0
            h, cols = h[cold], [c[cold] for c in cols]
        low = (h << _U64(self.bits) >> _U64(32)).astype(np.uint32)
        part = (h >> _U64(64 - self.bits)).astype(np.int64)
        at = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1]))) if len(part) else np.zeros(0, np.int64)
        ends = np.append(at[1:], len(part))[: len(at)]
        rows += [[x[a:b].tobytes() for x in (low, *cols)] for a, b in zip(at, ends, strict=True)]
        parts += part[at].tolist()
        n_cols = 1 + len(cols)
        del h, order, cols, low, token
        give_back()
        return pa.RecordBatch.from_arrays([pa.array(parts, pa.int32()), *(pa.array([r[c] for r in rows], pa.binary()) for c in range(n_cols))], ["part", "low", *(f"c{i}" for i in range(n_cols - 1))])


def place_of(t: pa.Table) -> tuple[int, bool]:
    """The part of an exchanged group, and whether it is a piece of a hot token's block."""
    part = t.column("part")[0].as_py()
    return part & ((1 << MARKED) - 1), part >> MARKED > 0


def part_bits(rows: int, each: int = 8_000) -> int:
    return max(4, min(24, math.ceil(math.log2(max(1, rows / each)))))


def _column(t: pa.Table, name: str, kind: type) -> np.ndarray:
    return np.frombuffer(b"".join(t.column(name).to_pylist()), kind)


def frequent(docs: DataFrame, k: int, bits: int, least: int = 16, most: int = 1 << 20) -> np.ndarray:
    """Leading 32 + bits bits of the n-grams (below REGION) that ``least`` or more documents hold; the ``most`` commonest if more."""

    def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        box = Outbox(bits, ())
        for _, texts in batches(it, "t"):
            for s in _sets(texts, k):
                if box.add(s[: np.searchsorted(s, REGION)]):
                    yield box.take()
        yield box.take()

    def count(t: pa.Table) -> pa.Table:
        v, n = np.unique(_column(t, "low", np.uint32), return_counts=True)
        hot = n >= least
        return pa.table({"key": pa.array((v[hot].astype(np.int64)) | place_of(t)[0] << 32, pa.int64()), "n": pa.array(n[hot], pa.int64())})

    rows = docs.select("t").mapInArrow(emit, "part int, low binary").groupBy("part").applyInArrow(count, "key long, n long")
    return np.array(sorted(r["key"] for r in rows.orderBy(F.desc("n"), "key").limit(most).collect()), np.int64)


def signatures(docs: DataFrame, hot: np.ndarray, k: int, percent: int, bits: int) -> DataFrame:
    """(id, key, n, node, prefix, vec, head) of each row; head: the prefix's first tokens, as blocks() names them."""
    shared = docs.sparkSession.sparkContext.broadcast(hot)  # at most ``most`` of frequent()

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hot = shared.value
        for b, texts in batches(it, "t"):
            n, node, prefix, vec, head = [], [], [], [], []
            for s in _sets(texts, k):
                n.append(len(s))
                node.append(node_id(s) if len(s) else 0)
                if not len(s):
                    prefix.append(b"")
                    vec.append(b"")
                    head.append(b"")
                    continue
                p = prefix_size(len(s), percent)
                if len(hot):
                    low = s[: np.searchsorted(s, REGION)]
                    key = (low >> _U64(32 - bits)).astype(np.int64)
                    at = np.minimum(np.searchsorted(hot, key), len(hot) - 1)
                    late = np.zeros(len(s), bool)
                    late[: len(low)] = hot[at] == key
                    order = s if not late.any() else np.concatenate([s[~late], s[late]])
                else:
                    order = s
                prefix.append(order[:p].tobytes())
                head.append((order[: min(p, HEAD)] >> _U64(32 - bits)).astype(np.int64).tobytes())
                v = np.bincount((s & _U64(GROUPS - 1)).astype(np.int64), minlength=GROUPS)
                vec.append(v.astype(np.uint8 if v.max() < 256 else np.uint32).tobytes())
            yield pa.RecordBatch.from_arrays([b.column("i"), b.column("key"), pa.array(n, pa.int32()), pa.array(node, pa.int64()), pa.array(prefix, pa.binary()), pa.array(vec, pa.binary()), pa.array(head, pa.binary())], ["id", "key", "n", "node", "prefix", "vec", "head"])

    kind = docs.schema["i"].dataType.simpleString()
    return docs.mapInArrow(run, f"id {kind}, key long, n int, node long, prefix binary, vec binary, head binary")


def differing(flags: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """In how many bits the bitmaps of the pairs differ; a bitmap is a 64-bit number of each of ``flags``."""
    total = np.zeros(len(x), np.uint16)
    for f in flags:
        total += np.bitwise_count((f[x] ^ f[y]).view(np.uint64))
    return total.astype(np.int64)


def _feasible(low: np.ndarray, n: np.ndarray, at: np.ndarray | None, percent: int, most: int = 64, flags: list[np.ndarray] | None = None) -> np.ndarray:
    """Which postings (sorted by token) have a partner in their block by size and, if given, position.

    What follows the first common element is all that two sets can share besides it, so a pair may be left to the block of
    that element: there ``n - position`` of both must reach what they need. Without bitmaps, blocks of over ``most`` are kept whole.
    """
    cut = np.flatnonzero(np.concatenate(([True], low[1:] != low[:-1], [True]))) if len(low) else np.zeros(1, int)
    size = np.diff(cut)
    keep = np.zeros(len(low), bool) if flags is not None else np.repeat(size > most, size)

    def mark(x: np.ndarray, y: np.ndarray) -> None:
        ok = 100 * np.minimum(n[x], n[y]) >= percent * np.maximum(n[x], n[y])
        x, y = x[ok], y[ok]
        least = need(n[x], n[y], percent)
        if at is not None:
            ok = np.minimum(n[x] - at[x], n[y] - at[y]) >= least
            x, y, least = x[ok], y[ok], least[ok]
        if flags is not None:  # bitmaps that differ in d bits belong to sets that differ in d elements at least
            ok = n[x] + n[y] - differing(flags, x, y) >= 2 * least
            x, y = x[ok], y[ok]
        keep[x] = True
        keep[y] = True

    small = np.flatnonzero((size > 1) & (size <= most))
    weight = np.cumsum(size[small].astype(np.int64) ** 2) // 200_000
    for group in np.unique(weight):
        part = small[weight == group]
        own = np.arange(size[part].sum()) + np.repeat(cut[part] - np.concatenate([[0], np.cumsum(size[part])[:-1]]), size[part])
        i, j = _small_blocks(size[part])
        mark(own[i], own[j])
    if flags is not None:
        for k in np.flatnonzero(size > most):  # members by size, each against those up to its limit
            first, last = int(cut[k]), int(cut[k + 1])
            to = first + np.searchsorted(n[first:last], 100 * n[first:last] // percent, "right")
            for a in range(first, last, 32):
                width = to[a - first : a - first + 32] - np.arange(a, min(a + 32, last)) - 1
                x = np.repeat(np.arange(a, min(a + 32, last)), width)
                mark(x, x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(width) - width, width))
    return keep


def blocks(sig: DataFrame, bits: int, percent: int) -> DataFrame:
    """Rows (token, a, n, at, null) for block members that have one of their size, and (null, a, n, null, b) for neighbours by size."""

    def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        box, seen = Outbox(bits, (np.int64, np.int32, np.uint16)), set()
        for b in it:
            for n, node, prefix in zip(b.column("n").to_pylist(), b.column("node").to_pylist(), b.column("prefix").to_pylist(), strict=True):
                if not n or node in seen:
                    continue
                if len(seen) < 200_000:
                    seen.add(node)
                p = np.frombuffer(prefix, _U64)
                if box.add(p, np.full(len(p), node), np.full(len(p), n), np.minimum(np.arange(len(p)), 65535)):
                    yield box.take()
        yield box.take()

    def meet(t: pa.Table) -> pa.Table:
        low, node, n, at = _column(t, "low", np.uint32), _column(t, "c0", np.int64), _column(t, "c1", np.int32), _column(t, "c2", np.uint16)
        order = np.lexsort((node, n, low))
        low, node, n, at = low[order], node[order], n[order], at[order]
        keep = np.concatenate(([True], (low[1:] != low[:-1]) | (node[1:] != node[:-1]))) if len(low) else np.zeros(0, bool)
        part, piece = place_of(t)
        split = np.isin(low, low[n == 0]) | piece  # others of these blocks are elsewhere: none is ruled out here
        keep &= n > 0
        low, node, n, at, split = low[keep], node[keep], n[keep], at[keep], split[keep]
        keep = _feasible(low, n.astype(np.int64), None, percent) | split
        low, node, n, at, split = low[keep], node[keep], n[keep], at[keep], split[keep]
        same = low[1:] == low[:-1]
        many = np.concatenate(([False], same)) | np.concatenate((same, [False])) | split if len(low) else keep[keep]
        near = np.flatnonzero(same & (100 * n[:-1].astype(np.int64) >= percent * n[1:].astype(np.int64)))
        token = low[many].astype(np.int64) | part << 32
        k, m = len(token), len(near)
        return pa.table({
            "token": pa.array(np.concatenate([token, np.zeros(m, np.int64)]), mask=np.arange(k + m) >= k),
            "a": pa.array(np.concatenate([node[many], node[near]]), pa.int64()),
            "n": pa.array(np.concatenate([n[many], n[near]]), pa.int32()),
            "at": pa.array(np.concatenate([at[many], np.zeros(m, np.uint16)]).astype(np.int32), mask=np.arange(k + m) >= k),
            "b": pa.array(np.concatenate([np.zeros(k, np.int64), node[near + 1]]), mask=np.arange(k + m) < k),
        })

    return sig.select("n", "node", "prefix").mapInArrow(emit, "part int, low binary, c0 binary, c1 binary, c2 binary").groupBy("part").applyInArrow(meet, "token long, a long, n int, at int, b long")


def first_common(x: np.ndarray, y: np.ndarray, head: np.ndarray, at: np.ndarray, token: np.ndarray) -> np.ndarray:
    """Which pairs share none of their first HEAD tokens before this block's: a pair is left to the block of its first common token,
    where both are and where it passes each filter that it passes here."""
    keep = np.ones(len(x), bool)
    for s in range(0, len(x), 50_000):
        p, q = x[s : s + 50_000], y[s : s + 50_000]
        a, b, t, place = head[p], head[q], token[p], at[p]
        for i in range(head.shape[1]):
            mine = a[:, i]
            keep[s : s + 50_000] &= ~(((mine[:, None] == b).any(1)) & (mine >= 0) & (mine != t) & (place > i))
    return keep


@dataclass
class Postings:
    """Block members side by side: size, place in the prefix, count vector, component, first tokens, block's token, side of a split block."""

    n: np.ndarray
    at: np.ndarray
    vec: np.ndarray
    root: np.ndarray
    head: np.ndarray
    token: np.ndarray
    side: np.ndarray

    def take(self, i: np.ndarray) -> Postings:
        return Postings(self.n[i], self.at[i], self.vec[i], self.root[i], self.head[i], self.token[i], self.side[i])

    def passing(self, x: np.ndarray, y: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
        """The pairs of points that may have the overlap they need, the cheapest tests first."""
        ok = (self.root[x] != self.root[y]) & ((self.side[x] < 0) | (self.side[x] != self.side[y]))
        x, y = x[ok], y[ok]
        ok = 100 * np.minimum(self.n[x], self.n[y]) >= percent * np.maximum(self.n[x], self.n[y])
        x, y = x[ok], y[ok]
        ok = np.minimum(self.n[x] - self.at[x], self.n[y] - self.at[y]) >= need(self.n[x], self.n[y], percent)
        x, y = x[ok], y[ok]
        ok = first_common(x, y, self.head, self.at, self.token)
        x, y = x[ok], y[ok]
        ok = summed_minima(self.vec, x, self.vec, y) >= need(self.n[x], self.n[y], percent)
        return x[ok], y[ok]


def summed_minima(u: np.ndarray, i: np.ndarray, v: np.ndarray, j: np.ndarray) -> np.ndarray:
    parts = [np.minimum(u[i[k : k + 8_000]], v[j[k : k + 8_000]]).sum(1, dtype=np.int64) for k in range(0, len(i), 8_000)]
    return np.concatenate(parts) if parts else np.zeros(0, np.int64)


def tree_join(p: Postings, percent: int, leaf: int = 24, fan: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of one block that pass, by an R-tree joined with itself from its top boxes down.

    Points are packed by size, those of a component that fills a leaf beside each other; a box holds ``fan`` boxes of the level below.
    The overlap of two boxes' points is at most the sum of the minima of their upper corners.
    """
    _, which, count = np.unique(p.root, return_inverse=True, return_counts=True)
    order = np.lexsort((p.vec[:, 0], p.n, np.where(count[which] >= leaf, which + 1, 0)))
    s = p.take(order)
    levels, starts = [], np.arange(0, len(s.n), leaf)
    box = [f.reduceat(c, starts) for f, c in ((np.maximum, s.vec), (np.minimum, s.n), (np.maximum, s.n), (np.minimum, s.root), (np.maximum, s.root))]
    levels.append(box)
    while len(levels[-1][1]) > fan:
        starts = np.arange(0, len(levels[-1][1]), fan)
        levels.append([f.reduceat(c, starts) for f, c in zip((np.maximum, np.minimum, np.maximum, np.minimum, np.maximum), levels[-1], strict=True)])

    def meet(level: int, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        corner, least, most, r0, r1 = levels[level]
        ok = (100 * most[i] >= percent * least[j]) & (100 * most[j] >= percent * least[i]) & ~((r0[i] == r1[i]) & (r0[j] == r1[j]) & (r0[i] == r0[j]))
        i, j = i[ok], j[ok]
        ok = summed_minima(corner, i, corner, j) >= need(least[i], least[j], percent)
        return i[ok], j[ok]

    def children(i: np.ndarray, j: np.ndarray, width: int, total: int) -> tuple[np.ndarray, np.ndarray]:
        """All pairs, each once, of what is below the pairs of boxes (i <= j)."""
        a = (i[:, None, None] * width + np.arange(width)[None, :, None] + np.zeros((1, 1, width), np.int64)).ravel()
        b = (j[:, None, None] * width + np.arange(width)[None, None, :] + np.zeros((1, width, 1), np.int64)).ravel()
        ok = (a < total) & (b < total) & (a <= b)
        return a[ok], b[ok]

    top = len(levels) - 1
    i, j = np.triu_indices(len(levels[top][1]))
    stack, left, right = [(top, *meet(top, i, j))], [], []
    while stack:
        level, i, j = stack.pop()
        step = 64 if not level else 512
        if len(i) > step:
            stack.append((level, i[step:], j[step:]))
            i, j = i[:step], j[:step]
        if level:
            stack.append((level - 1, *meet(level - 1, *children(i, j, fan, len(levels[level - 1][1])))))
            continue
        x, y = children(i, j, leaf, len(s.n))
        x, y = s.passing(x[x < y], y[x < y], percent)
        left.append(order[x])
        right.append(order[y])
    none = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (none, none)


def _vectors(col: pa.ChunkedArray) -> np.ndarray:
    raw = col.to_pylist()
    if all(len(x) == GROUPS for x in raw):
        return np.frombuffer(b"".join(raw), np.uint8).reshape(-1, GROUPS)
    return np.array([np.frombuffer(x, np.uint8 if len(x) == GROUPS else np.uint32) for x in raw], np.int32).reshape(-1, GROUPS)


def _small_blocks(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All index pairs i < j within consecutive blocks of these sizes."""
    end = np.repeat(np.cumsum(sizes), sizes)
    later = end - np.arange(len(end)) - 1
    left = np.repeat(np.arange(len(end)), later)
    return left, left + 1 + np.arange(len(left)) - np.repeat(np.cumsum(later) - later, later)


def block_pairs(block: np.ndarray, p: Postings, percent: int, leaf: int = 24) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs that share a block and pass. A block that one leaf holds has no boxes above that: many are tested at once."""
    order = np.argsort(block, kind="stable")
    cut = np.flatnonzero(np.concatenate(([True], block[order][1:] != block[order][:-1], [True])))
    size = np.diff(cut)
    left, right = [], []
    for s, e in zip(cut[:-1][size > leaf], cut[1:][size > leaf], strict=True):
        own = order[s:e]
        x, y = tree_join(p.take(own), percent, leaf)
        left.append(own[x])
        right.append(own[y])
    small = np.flatnonzero((size <= leaf) & (size > 1))
    for start in range(0, len(small), 4096):
        part = small[start : start + 4096]
        own = order[np.concatenate([np.arange(cut[i], cut[i + 1]) for i in part])]
        i, j = _small_blocks(size[part])
        x, y = p.passing(own[i], own[j], percent)
        left.append(x)
        right.append(y)
    none = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (none, none)


def in_parts(members: DataFrame) -> DataFrame:
    """Rows (token, node, parts, ...) with ``block`` and ``side``: a token of several parts has a block for each part, in which all meet
    (side -1), and one for each pair of parts, in which those of different sides meet."""
    own = F.pmod(F.xxhash64("node"), "parts").cast("int")
    split = members.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    key = F.xxhash64("token", F.least("own", "other"), F.greatest("own", "other"))
    block, side = F.when(F.col("parts") == 1, F.col("token")).otherwise(key), F.when(F.col("own") == F.col("other"), F.lit(-1)).otherwise(F.col("own"))
    return split.withColumns({"block": block, "side": side}).drop("own", "other", "parts")


def cross_pairs(mixed: DataFrame, tasks: int, percent: int, thin: bool) -> DataFrame:
    """Candidate pairs (a, b) of different roots, from rows (token, parts, node, root, n, at, vec, head); ``thin``: each node's likeliest alone.

    A token of several ``parts`` has a block for each pair of parts, and they go to tasks of their own.
    """

    def join(t: pa.Table) -> pa.Table:
        node, block = t.column("node").to_numpy(), t.column("block").to_numpy()
        head = [h + b"\xff" * (8 * HEAD - len(h)) for h in t.column("head").to_pylist()]
        p = Postings(
            t.column("n").to_numpy().astype(np.int64), t.column("at").to_numpy().astype(np.int64), _vectors(t.column("vec")), t.column("root").to_numpy(),
            np.frombuffer(b"".join(head), np.int64).reshape(-1, HEAD), t.column("token").to_numpy(), t.column("side").to_numpy(),
        )
        x, y = block_pairs(block, p, percent)
        a, b = np.minimum(node[x], node[y]), np.maximum(node[x], node[y])
        order = np.lexsort((b, a))
        order = order[np.concatenate(([True], (a[order][1:] != a[order][:-1]) | (b[order][1:] != b[order][:-1])))] if len(order) else order
        x, y, a, b = x[order], y[order], a[order], b[order]
        score = summed_minima(p.vec, x, p.vec, y) / np.maximum(need(p.n[x], p.n[y], percent), 1)
        if thin and len(a):
            ends = np.concatenate([a, b])
            by = np.lexsort((np.concatenate([score, score]), ends))
            top = by[np.concatenate((ends[by][1:] != ends[by][:-1], [True]))] % len(a)
            keep = np.unique(top)
            a, b, score = a[keep], b[keep], score[keep]
        del p, head
        give_back()
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "score": pa.array(score, pa.float64())})

    split = in_parts(mixed)
    pairs = split.select("block", "token", "side", "node", "n", "at", "root", "vec", "head").groupBy(F.pmod(F.xxhash64("block"), F.lit(tasks)).alias("task")).applyInArrow(join, "a long, b long, score double")
    pairs = stage(pairs, "candidates")
    return _likeliest(pairs.groupBy("a", "b").agg(F.max("score").alias("score"))) if thin else pairs.select("a", "b").distinct()


def _likeliest(pairs: DataFrame) -> DataFrame:
    """Of pairs (a, b, score), each node's best one."""
    one = pairs.groupBy("a").agg(F.max_by("b", F.struct("score", "b")).alias("b")).select("a", "b")
    other = pairs.groupBy("b").agg(F.max_by("a", F.struct("score", "a")).alias("a")).select("a", "b")
    return one.union(other).distinct()


def _fine(s: np.ndarray) -> bytes:
    """Counts by as many hash groups as the set has elements, up to a power of two; one byte each where they fit."""
    v = np.bincount((s & _U64((1 << max(1, int(len(s) - 1).bit_length())) - 1)).astype(np.int64), minlength=1 << max(1, int(len(s) - 1).bit_length()))
    return (b"\1" + v.astype(np.uint8).tobytes()) if v.max() < 256 else b"\4" + v.astype(np.uint32).tobytes()


def _fine_bound(x: bytes, y: bytes) -> int:
    p, q = (np.frombuffer(z, np.uint8 if z[0] == 1 else np.uint32, offset=1) for z in (x, y))
    p, q = (p, q) if len(p) <= len(q) else (q, p)
    return int(np.minimum(p, q.reshape(-1, len(p)).sum(0)).sum())


def verify(pairs: DataFrame, docs: DataFrame, sig: DataFrame, k: int, percent: int, most: int = 1 << 20) -> DataFrame:
    """The pairs (a, b) whose sets have the similarity.

    The sets of the nodes concerned are made again from one text each, found by its hash: by a broadcast of at most
    ``most`` hashes, or by a join if there are more. A bound from finer counts comes before the sets themselves.
    """
    nodes = pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct()
    keys = stage(sig.filter("n > 0").join(nodes, "node", "left_semi").groupBy("node", "n").agg(F.min("key").alias("key")), "nodes")
    some = keys.select("key").distinct()
    texts = docs.join(F.broadcast(some) if keys.count() <= most else some, "key", "left_semi").select("t")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for _, texts in batches(it, "t"):
            out = {}
            for s in _sets(texts, k):
                if len(s) and (node := node_id(s)) not in seen:
                    out[node] = (s.tobytes(), _fine(s))
                    if len(seen) < 200_000:
                        seen.add(node)
            yield pa.RecordBatch.from_arrays([pa.array(list(out), pa.int64()), *(pa.array([v[c] for v in out.values()], pa.binary()) for c in (0, 1))], ["node", "elements", "fine"])

    sets = stage(texts.mapInArrow(run, "node long, elements binary, fine binary").join(keys, "node").dropDuplicates(["node"]).select("node", "n", "elements", "fine"), "sets")

    def with_(rows: DataFrame, *cols: str) -> DataFrame:
        for side in ("a", "b"):
            rows = rows.join(sets.select(F.col("node").alias(side), *(F.col(c).alias(f"{c}_{side}") for c in cols)), side)
        return rows

    def bound(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            x, y, n, m = (b.column(c).to_pylist() for c in ("fine_a", "fine_b", "n_a", "n_b"))
            keep = pa.array([(100 + percent) * _fine_bound(p, q) >= percent * (i + j) for p, q, i, j in zip(x, y, n, m, strict=True)], pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], ["a", "b"])

    def hold(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            good = []
            for x, y in zip(b.column("elements_a"), b.column("elements_b"), strict=True):
                p, q = np.frombuffer(x.as_buffer(), _U64), np.frombuffer(y.as_buffer(), _U64)
                p, q = (p, q) if len(p) <= len(q) else (q, p)
                common = int((q[np.minimum(np.searchsorted(q, p), len(q) - 1)] == p).sum())
                good.append(100 * common >= percent * (len(p) + len(q) - common))
            keep = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], ["a", "b"])

    likely = with_(pairs, "n", "fine").mapInArrow(bound, "a long, b long")
    return stage(with_(likely, "elements").mapInArrow(hold, "a long, b long"), "links")


def _supported(met: DataFrame, percent: int) -> DataFrame:
    """Members (node, n, token, ...) of nodes with as many shared elements as the least that their smallest similar set asks for."""
    least = F.lit(1) + F.expr(f"(({percent} * n + 99) div 100) div 20")  # shared_least() of the smallest size
    enough = met.groupBy("node", "n").agg(F.count(F.lit(1)).alias("m")).filter(F.col("m") >= least).select("node")
    return met.join(enough, "node", "left_semi")


def ngram_components(df: DataFrame, k: int = 5, percent: int = 75, id_col: str = "doc_id", text_col: str = "text", thin_rounds: int = 1, per_block: int = 20_000) -> DataFrame:
    """(id_col, n_shingles, component_id, text_key) of each row; component_id is the smallest identifier that links reach.

    Null and empty texts have no shingles and no links. Rows with one set of shingles are linked, whatever their
    identifiers; null identifiers are passed over unless a component has no other. Repeated rows are rows of one component. Sets
    are held as 64-bit hashes. ``text_key`` is the hash of the text, null as empty.
    """
    bits = part_bits(df.count())
    docs = df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).withColumn("key", F.xxhash64(F.coalesce("t", F.lit(""))))
    hot = frequent(docs, k, bits)
    sig = stage(signatures(docs, hot, k, percent, bits), "signatures")
    met = stage(blocks(sig, bits, percent), "blocks")
    met, near = stage(_supported(met.filter("b is null").select("token", F.col("a").alias("node"), "n", "at"), percent), "members"), met.filter("b is not null")
    # 1. each node's likeliest neighbour, by the number of blocks in which they are neighbours
    near = near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).groupBy("a", "b").agg(F.count(F.lit(1)).alias("score"))
    alive = met.select("node").distinct()
    near = _likeliest(near).join(alive.withColumnRenamed("node", "a"), "a", "left_semi").join(alive.withColumnRenamed("node", "b"), "b", "left_semi")
    links = verify(stage(near.select("a", "b"), "pairs"), docs, sig, k, percent)
    roots = stage(components(links.select(F.col("a").alias("u"), F.col("b").alias("v"))), "roots")
    # 2. across the components that a block still holds: likeliest pairs first, then every one that is left
    info = sig.filter("n > 0").select("node", "vec", "head").join(alive, "node", "left_semi").dropDuplicates(["node"])
    for thin in (*[True] * thin_rounds, False):
        held = met.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
        mixed = held.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.count(F.lit(1)).alias("m")).filter("lo <> hi")
        mixed = mixed.select("token", F.ceil(F.col("m") / F.lit(per_block)).cast("int").alias("parts"))
        held = stage(_supported(held.join(mixed, "token"), percent), "mixed")
        tasks = max(16, held.count() // 100_000)
        links = links.union(verify(stage(cross_pairs(held.join(info, "node"), tasks, percent, thin), "pairs"), docs, sig, k, percent))
        roots = stage(components(links.select(F.col("a").alias("u"), F.col("b").alias("v"))), "roots")
    rows = sig.select("id", "key", "n", "node").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = rows.filter("n > 0").groupBy("root").agg(F.min("id").alias("least"), F.count(F.lit(1)).alias("m")).filter("m > 1")
    out = rows.join(least, "root", "left")
    return out.select(F.col("id").alias(id_col), F.col("n").cast("long").alias("n_shingles"), F.when(F.col("n") > 0, F.coalesce("least", "id")).otherwise(F.col("id")).alias("component_id"), F.col("key").alias("text_key"))


def one_of_each(df: DataFrame, k: int = 5, percent: int = 75, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``df`` with one row of each component: that of the smallest identifier, or one of its repetitions.

    Rows without shingles, and components whose rows have no identifier, stay whole.
    """
    found = ngram_components(df, k, percent, id_col, text_col)
    free = (F.col("n_shingles") == 0) | F.col("component_id").isNull()
    least = found.filter(~free).groupBy("component_id").agg(F.min(F.struct(F.col(id_col).isNull().alias("none"), F.col(id_col).alias("i"), F.col("text_key").alias("key"))).alias("s"))
    stay = found.filter(free).select(F.col(id_col).alias("_i"), F.col("text_key").alias("_k"), F.lit(True).alias("_all")).distinct()
    stay = stay.union(least.select("s.i", "s.key", F.lit(False)))
    both = df.withColumn("_key", F.xxhash64(F.coalesce(F.col(text_col), F.lit("")))).join(stay, F.col(id_col).eqNullSafe(F.col("_i")) & (F.col("_key") == F.col("_k")))
    turn = F.row_number().over(Window.partitionBy("_i", "_k").orderBy("_all"))
    return both.withColumn("_turn", turn).filter(F.col("_all") | (F.col("_turn") == 1)).select(*df.columns)
