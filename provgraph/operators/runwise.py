"""Colour refinement of many small runs at once: each task holds whole runs and makes all their rounds on arrays.

One shuffle, by run, whatever the number of rounds. ``plans.choose`` says whether every run's edges fit a task; a graph with
a run that does not goes through ``grouping.refine``.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.schema import ProvGraph

_U64 = np.uint64
PER_TASK = 500_000
AT_ONCE = 200_000
RUN_EDGES = 2_000_000  # a run of so many takes a task some 1 GB


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U64(30))) * _U64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U64(27))) * _U64(0x94D049BB133111EB)
    return h ^ (h >> _U64(31))


def _named(values: pa.ChunkedArray, seed: str) -> np.ndarray:
    """A hash of each string that is the same in every task; null counts as a string of its own."""
    coded = values.combine_chunks().dictionary_encode()
    names = [hashlib.blake2b(f"{seed}:{x}".encode(), digest_size=8).digest() for x in (*coded.dictionary.to_pylist(), None)]
    return np.frombuffer(b"".join(names), _U64)[pc.fill_null(coded.indices, len(coded.dictionary)).to_numpy()]


def refined(run: np.ndarray, first: tuple[np.ndarray, np.ndarray], node: np.ndarray, way: np.ndarray, far: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Colours of nodes (in runs, with ``first`` colours) over views (node, way, far); a run stops when its number of colours stays."""
    a, b = first
    order = np.argsort(node, kind="stable")
    node, way, far = node[order], way[order], far[order]
    starts = np.flatnonzero(np.concatenate(([True], node[1:] != node[:-1]))) if len(node) else np.zeros(0, int)
    have, degree = node[starts], np.diff(np.append(starts, len(node))).astype(_U64)
    runs, which = np.unique(run, return_inverse=True)

    def colours() -> np.ndarray:
        by = np.lexsort((b, a, which))
        new = np.concatenate(([True], (which[by][1:] != which[by][:-1]) | (a[by][1:] != a[by][:-1]) | (b[by][1:] != b[by][:-1])))
        return np.bincount(which[by][new], minlength=len(runs))

    known, live = colours() if len(run) else np.zeros(0, int), np.ones(len(runs), bool)
    while live.any():
        sums = []
        for c, seed in ((a, 1), (b, 2)):
            item = _mix(_mix(c[far] + _U64(seed)) ^ way)
            total = np.zeros(len(run), _U64)
            if len(starts):
                total[have] = np.add.reduceat(item, starts) + _mix(degree + _U64(seed))
            sums.append(np.where(live[which], _mix(_mix(c) + total), c))
        a, b = sums
        now = colours()
        live &= now != known
        known = now
    return a, b


def colours(g: ProvGraph) -> DataFrame:
    """(run_id, node_id, node_type, c1, c2): stable colours of node types under the counted, labelled edges of both directions."""
    none = F.lit(None).cast("string")
    nodes = g.nodes.select("run_id", F.col("node_id").alias("x"), none.alias("y"), F.col("node_type").alias("what"), F.lit(True).alias("is_node"))
    edges = g.edges.select("run_id", F.col("src").alias("x"), F.col("dst").alias("y"), F.col("label").alias("what"), F.lit(False).alias("is_node"))
    rows = nodes.unionByName(edges)
    kind = rows.schema["run_id"].dataType.simpleString()

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in it if b.num_rows]
        if not held:
            return
        t = pa.Table.from_batches(held)
        is_node = t.column("is_node")
        n, e = t.filter(is_node), t.filter(pc.invert(is_node))
        keys = [pc.binary_join_element_wise(x.column("run_id").cast(pa.string()), x.column(c).cast(pa.string()), "\0") for x, c in ((n, "x"), (e, "x"), (e, "y"))]
        code = pa.chunked_array([k for key in keys for k in key.chunks], pa.string()).combine_chunks().dictionary_encode().indices.to_numpy()
        at, src, dst = code[: len(n)], code[len(n) : len(n) + len(e)], code[len(n) + len(e) :]
        place = np.full(int(code.max()) + 1, -1)
        place[at] = np.arange(len(n))
        src, dst = place[src], place[dst]
        ok = (src >= 0) & (dst >= 0)  # an end that is no node has no colour
        out, in_ = (_named(e.column("what"), s) for s in ("out", "in"))
        a, b = refined(
            n.column("run_id").combine_chunks().dictionary_encode().indices.to_numpy(), tuple(_named(n.column("what"), s) for s in ("1", "2")),
            np.concatenate([src[ok], dst[ok]]), np.concatenate([out[ok], in_[ok]]), np.concatenate([dst[ok], src[ok]]),
        )
        made = pa.table([n.column("run_id"), n.column("x"), n.column("what"), pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["run_id", "node_id", "node_type", "c1", "c2"])
        yield from made.to_batches(max_chunksize=50_000)

    parts = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), math.ceil(rows.count() / PER_TASK))
    return rows.repartition(parts, "run_id").mapInArrow(run, f"run_id {kind}, node_id string, node_type string, c1 long, c2 long")


def _whole_runs(it: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Rows sorted by run, with the number of rows of their run in ``n``, in tables of whole runs of ``AT_ONCE`` rows or a little more."""
    held, rows = [], 0
    for b in it:
        held.append(b)
        rows += b.num_rows
        if rows < AT_ONCE:
            continue
        t = pa.Table.from_batches(held)
        n, cut, last = t.column("n").to_numpy(), 0, 0
        while (last := cut) < len(n) and cut + n[cut] <= len(n):
            cut += int(n[cut])
        held, rows = t.slice(last).to_batches(), len(n) - last
        if last:
            yield t.slice(0, last)
    if rows:
        yield pa.Table.from_batches(held)


def _seen(node: np.ndarray, src: np.ndarray, dst: np.ndarray, out: np.ndarray, in_: np.ndarray, sides: tuple[str, ...] = ("out", "in")) -> tuple[np.ndarray, ...]:
    """Views of names' hashes to ``sides``: each row's name, then of each view its own name, a row of its far end and its way; last each
    name's degree.

    Ends that are no node do not count; of a name with several rows each does.
    """
    names, at, times = np.unique(node, return_inverse=True, return_counts=True)
    by = np.argsort(at, kind="stable")
    starts = np.concatenate(([0], np.cumsum(times)[:-1])).astype(int)
    ends = [np.minimum(np.searchsorted(names, x), max(len(names) - 1, 0)) for x in (src, dst)]
    ok = (names[ends[0]] == src) & (names[ends[1]] == dst) if len(names) else np.zeros(len(src), bool)
    s, d = ends[0][ok], ends[1][ok]
    views = {"out": (s, d, out[ok]), "in": (d, s, in_[ok])}
    near, far, way = (np.concatenate(x) for x in zip(*(views[side] for side in sides), strict=True))
    k = times[far]
    first = np.cumsum(k) - k
    row = by[np.repeat(starts[far] - first, k) + np.arange(int(k.sum()))]
    near, way = np.repeat(near, k), np.repeat(way, k)
    return at, near, row, way, np.bincount(near, minlength=len(names)).astype(_U64)


def _sums(c: np.ndarray, seen: tuple[np.ndarray, ...], seed: np.uint64) -> np.ndarray:
    """For each row the multiset of (way, value of the far end) of its name."""
    at, near, row, way, degree = seen
    total = np.zeros(len(degree), _U64)
    np.add.at(total, near, _mix(_mix(c + seed)[row] ^ way))
    return _mix(total + _mix(degree + seed))[at]


def _rows(g: ProvGraph, *more: str) -> DataFrame:
    """(run_id, x, y, what, is_node, n) of nodes and edges as numbers, and columns of nodes; n is the number of rows of the run.

    Rows meet by run, in the order of runs; where the graph is dealt out by run already, nothing is shuffled. A name that is
    null is no end's.
    """
    name = lambda c, null: F.when(F.col(c).isNull(), F.lit(null).cast("long")).otherwise(F.xxhash64("run_id", c))
    word = lambda c: F.xxhash64(F.coalesce(F.col(c), F.lit("")))
    nodes = g.nodes.select("run_id", name("node_id", 0).alias("x"), F.lit(0).cast("long").alias("y"), word("node_type").alias("what"), F.lit(True).alias("is_node"), *more)
    edges = g.edges.select("run_id", name("src", 1).alias("x"), name("dst", 1).alias("y"), word("label").alias("what"), F.lit(False).alias("is_node"))
    return nodes.unionByName(edges, allowMissingColumns=True).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("run_id")))


def one_hop(g: ProvGraph) -> DataFrame:
    """(run_id, nodes, edges, f1, f2) of runs with nodes: their sizes, and two sums over one-hop node hashes without direction."""
    rows = _rows(g)
    kind = rows.schema["run_id"].dataType.simpleString()

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_runs(it):
            n, is_node = t.column("n").to_numpy(), t.column("is_node").to_numpy()
            heads = [0]
            while (nxt := heads[-1] + int(n[heads[-1]])) < len(n):
                heads.append(nxt)
            which = np.repeat(np.arange(len(heads)), n[heads])[is_node]
            x, y, what = (t.column(c).to_numpy().view(_U64) for c in ("x", "y", "what"))
            type_, label = what[is_node], what[~is_node]
            seen = _seen(x[is_node], x[~is_node], y[~is_node], label, label)
            sums = []
            for seed in (_U64(1), _U64(2)):
                total = np.zeros(len(heads), _U64)
                np.add.at(total, which, _mix(_mix(type_ ^ seed) + _sums(type_, seen, seed)))
                sums.append(pa.array(total.view(np.int64)))
            size = np.bincount(which, minlength=len(heads))
            made = pa.table([t.column("run_id").take(pa.array(heads)), pa.array(size), pa.array(n[heads] - size), *sums], ["run_id", "nodes", "edges", "f1", "f2"])
            yield from made.filter(pa.array(size > 0)).to_batches()

    return rows.mapInArrow(run, f"run_id {kind}, nodes long, edges long, f1 long, f2 long")


def _classes(a: np.ndarray, b: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of rows of runs ``which`` the number of their colour in their run, and a row of each."""
    by = np.lexsort((b, a, which))
    new = np.concatenate(([True], (which[by][1:] != which[by][:-1]) | (a[by][1:] != a[by][:-1]) | (b[by][1:] != b[by][:-1])))
    number = np.empty(len(by), np.int64)
    number[by] = np.cumsum(new) - 1
    return number, by[new]


def refine(g: ProvGraph, init: DataFrame, sides: tuple[str, ...], counted: bool, max_rounds: int | None = None) -> DataFrame:
    """(run_id, node_id, c1, c2): what ``grouping.refine`` says, from the colours ``init``, with all rounds of a run in its task. A run
    stops at its own fixpoint or after ``max_rounds``."""
    rows = _rows(ProvGraph(init.withColumn("node_type", F.lit("")), g.edges), "node_id", "c1", "c2")
    kind = rows.schema["run_id"].dataType.simpleString()

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_runs(it):
            n, is_node = t.column("n").to_numpy(), t.column("is_node").to_numpy()
            if not is_node.any():
                continue
            heads = [0]
            while (nxt := heads[-1] + int(n[heads[-1]])) < len(n):
                heads.append(nxt)
            which = np.repeat(np.arange(len(heads)), n[heads])[is_node]
            x, y, what = (t.column(c).to_numpy().view(_U64) for c in ("x", "y", "what"))
            label, nodes = what[~is_node], t.filter(pa.array(is_node)).select(["run_id", "node_id", "c1", "c2"])
            seen = _seen(x[is_node], x[~is_node], y[~is_node], _mix(label + _U64(1)), _mix(label + _U64(2)), sides)
            at, near, row, way, _ = seen
            ways, way_no = np.unique(way, return_inverse=True)
            a, b = (nodes.column(c).to_numpy().view(_U64) for c in ("c1", "c2"))
            number, first = _classes(a, b, which)
            known, live, k = np.bincount(which[first], minlength=len(heads)), np.ones(len(heads), bool), 0
            while live.any() and (max_rounds is None or k < max_rounds):
                if not counted:  # each way and colour once for a name
                    once = np.unique((near * len(ways) + way_no) * len(first) + number[row])
                    rest, c = np.divmod(once, len(first))
                    own, w = np.divmod(rest, max(len(ways), 1))
                    seen = (at, own, first[c], ways[w], np.bincount(own, minlength=len(seen[4])).astype(_U64))
                a, b = (np.where(live[which], _mix(_mix(c) + _sums(c, seen, _U64(seed))), c) for c, seed in ((a, 1), (b, 2)))
                number, first = _classes(a, b, which)
                now = np.bincount(which[first], minlength=len(heads))
                live &= now != known
                known, k = now, k + 1
            made = pa.table([nodes.column("run_id"), nodes.column("node_id"), pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["run_id", "node_id", "c1", "c2"])
            yield from made.to_batches(max_chunksize=50_000)

    return rows.mapInArrow(run, f"run_id {kind}, node_id string, c1 long, c2 long")


def together(g: ProvGraph, rounds: int) -> DataFrame:
    """(node_id, c1, c2, round): colours of node types after ``rounds`` rounds under the counted, labelled edges of both directions, equal
    across runs (round null). Besides, what colours there were after the last two rounds (round), at the last one with their least node
    of some runs."""

    def colours_of(r: int, pair: tuple[np.ndarray, np.ndarray], names: pa.Array | None) -> pa.Table:
        c1, c2 = (pa.array(c.view(np.int64)) for c in pair)
        if names is None:
            t = pa.table([c1, c2], ["c1", "c2"]).group_by(["c1", "c2"]).aggregate([])
            return pa.table([pa.nulls(len(t), pa.string()), t.column("c1"), t.column("c2"), pa.array([r] * len(t), pa.int32())], ["node_id", "c1", "c2", "round"])
        t = pa.table([names, c1, c2, pa.nulls(len(names), pa.int32())], ["node_id", "c1", "c2", "round"])
        by = np.lexsort((pc.rank(names, sort_keys="ascending", tiebreaker="first").to_numpy(), *pair))
        a, b = (c[by] for c in pair)
        least = t.take(pa.array(by[np.concatenate(([True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])))]))
        return pa.concat_tables([t, least.set_column(3, "round", pa.array([r] * len(least), pa.int32()))])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _whole_runs(it):
            is_node = t.column("is_node").to_numpy()
            if not is_node.any():
                continue
            x, y, what = (t.column(c).to_numpy().view(_U64) for c in ("x", "y", "what"))
            label = what[~is_node]
            seen = _seen(x[is_node], x[~is_node], y[~is_node], _mix(label + _U64(1)), _mix(label + _U64(2)))
            now = before = tuple(_mix(what[is_node] ^ _U64(seed)) for seed in (1, 2))
            for _ in range(rounds):
                before, now = now, tuple(_mix(_mix(c) + _sums(c, seen, _U64(seed))) for c, seed in zip(now, (1, 2), strict=True))
            yield from colours_of(rounds - 1, before, None).to_batches()
            yield from colours_of(rounds, now, t.column("node_id").filter(pa.array(is_node)).combine_chunks()).to_batches(max_chunksize=50_000)

    return _rows(g, "node_id").mapInArrow(run, "node_id string, c1 long, c2 long, round int")
