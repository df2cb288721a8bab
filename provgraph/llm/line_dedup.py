"""Line dedup by an exact set-similarity join.

A line is the set of its distinct words, A-Z in lower case; lines with one set are one class, which stands where its first line
does, by document identifier and line number. Words are ordered by rarity: by a count sketch over all lines, of
fixed size, then by hash, so any error of the sketch costs time only. Classes whose first ``n - ceil(t n) + 1`` words
share one meet in that word's block; sizes and the word's positions rule out most pairs, and bitmaps, whose differences bound
those of the sets, most pairs of strangers. A pair is left to the block of its first common word. Classes are settled in rounds: each
class's likeliest neighbour is verified first, then the best two earlier classes of each task, then, for classes that had more
than these and are still open, every earlier one. A line goes if an earlier line has its set, or one similar to it.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.common import stage
from provgraph.llm.ngram_join import Outbox, _column, _feasible, _likeliest, _small_blocks, differing, first_common, in_parts, need, part_bits, place_of
from provgraph.llm.wordkernel import batches, distinct, give_back, joined, mix, words

CELLS = 1 << 20
HEAD = 4
_U64 = np.uint64


class Lines:
    """The lines of a batch of texts: for each line with words its text, number, class, and its words in order."""

    def __init__(self, texts: list[bytes], rarity: np.ndarray | None):
        data, at = joined(texts)
        w, starts, _ = words(data, True)
        ends = np.flatnonzero(np.frombuffer(data, np.uint8) == 10)
        line = np.searchsorted(ends, starts)
        first = np.searchsorted(ends, at[:-1])  # each text's first line
        self.n_lines = np.diff(np.append(first, len(ends)))
        cell = (w & _U64(CELLS - 1)).astype(np.int64)
        # by line, then rarity, then hash; in one number where the slice's lines fit 14 bits. That has 28 bits of the hash: where
        # words of one line agree in these, the whole hashes decide
        rare = np.zeros(len(w), np.int64) if rarity is None else np.minimum(rarity[cell], (1 << 22) - 1).astype(np.int64)
        order = None
        if len(ends) < 1 << 14:
            key = (line.astype(_U64) << _U64(50)) | (rare.astype(_U64) << _U64(28)) | (w >> _U64(36))
            order = np.argsort(key)
            if ((key[order][1:] == key[order][:-1]) & (w[order][1:] != w[order][:-1])).any():
                order = None
        if order is None:
            order = np.lexsort((w, rare, line))
        w, line = w[order], line[order]
        keep = np.concatenate(([True], (w[1:] != w[:-1]) | (line[1:] != line[:-1]))) if len(w) else np.zeros(0, bool)
        self.words, line = w[keep], line[keep]
        self.begin = np.flatnonzero(np.concatenate(([True], line[1:] != line[:-1]))) if len(line) else np.zeros(0, np.int64)
        self.size = np.diff(np.append(self.begin, len(line)))
        whole = line[self.begin]
        self.text = np.searchsorted(first, whole, "right") - 1
        self.number = whole - first[self.text]
        total = np.add.reduceat(mix(self.words), self.begin) if len(self.begin) else np.zeros(0, _U64)
        self.node = mix(total + self.size.astype(_U64) * _U64(0x9E3779B97F4A7C15)).view(np.int64)


def rarity(docs: DataFrame, shards: int = 16) -> np.ndarray:
    """How often the words of each hash cell occur, over all lines; CELLS numbers."""

    def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CELLS, np.int64)
        for _, texts in batches(it, "t"):
            total += np.bincount((words(joined(texts)[0], True)[0] & _U64(CELLS - 1)).astype(np.int64), minlength=CELLS)
        yield pa.RecordBatch.from_arrays([pa.array(range(shards), pa.int32()), pa.array([x.astype(np.uint32).tobytes() for x in total.reshape(shards, -1)], pa.binary())], ["shard", "counts"])

    def add(t: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x, np.uint32).astype(np.int64) for x in t.column("counts").to_pylist())
        return pa.table({"shard": pa.array([t.column("shard")[0].as_py()], pa.int32()), "counts": pa.array([np.minimum(total, 2**32 - 1).astype(np.uint32).tobytes()], pa.binary())})

    rows = docs.select("t").mapInArrow(emit, "shard int, counts binary").groupBy("shard").applyInArrow(add, "shard int, counts binary").collect()
    return np.concatenate([np.frombuffer(r["counts"], np.uint32) for r in sorted(rows, key=lambda r: r["shard"])]) if rows else np.zeros(CELLS, np.uint32)


def classes(docs: DataFrame, counts: np.ndarray, percent: int) -> DataFrame:
    """(i, line, node, n, w0 to w3, prefix) of each line with words; the size, the bitmap and the prefix, as 32-bit hashes, only where a
    task sees the class first, else null and empty. w0 to w3 have one of 256 bits set for each word."""
    shared = docs.sparkSession.sparkContext.broadcast(counts)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, seen = shared.value, np.zeros(0, np.int64)
        for b, texts in batches(it, "t"):
            x = Lines(texts, counts)
            if not len(x.node):
                continue
            new = np.zeros(len(x.node), bool)
            new[np.unique(x.node, return_index=True)[1]] = True
            if len(seen):
                new &= seen[np.minimum(np.searchsorted(seen, x.node), len(seen) - 1)] != x.node
            if len(seen) < 1_000_000:
                seen = distinct(np.concatenate([seen, x.node[new]]))
            p = np.where(new, x.size + (-percent * x.size // 100) + 1, 0)
            at = np.arange(p.sum()) + np.repeat(x.begin - (np.cumsum(p) - p), p)
            offsets = np.concatenate([[0], np.cumsum(p * 4)]).astype(np.int32)
            place = x.words & _U64(255)
            wide = [np.bitwise_or.reduceat(np.where(place >> _U64(6) == _U64(k), _U64(1) << (place & _U64(63)), _U64(0)), x.begin).view(np.int64) for k in range(4)]
            prefix = pa.Array.from_buffers(pa.binary(), len(p), [None, pa.py_buffer(offsets), pa.py_buffer((x.words[at] >> _U64(32)).astype(np.uint32).tobytes())])
            yield pa.RecordBatch.from_arrays([b.column("i").take(pa.array(x.text)), pa.array(x.number, pa.int32()), pa.array(x.node, pa.int64()), pa.array(x.size, pa.int32(), mask=~new), *(pa.array(w, pa.int64(), mask=~new) for w in wide), prefix], ["i", "line", "node", "n", "w0", "w1", "w2", "w3", "prefix"])

    kind = docs.schema["i"].dataType.simpleString()
    return docs.select("i", "t").mapInArrow(run, f"i {kind}, line int, node long, n int, w0 long, w1 long, w2 long, w3 long, prefix binary")


def blocks(lines: DataFrame, bits: int, percent: int) -> DataFrame:
    """Rows (token, a, n, at, null) for block members that have a possible partner, by bitmaps folded to 128 bits too, and
    (null, a, ..., b) for neighbours by size."""

    def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        box = Outbox(bits, (np.int64, np.int32, np.uint16, np.int64, np.int64))
        for b in it:
            raw = b.column("prefix").to_pylist()
            size = np.fromiter((len(x) // 4 for x in raw), np.int64, len(raw))
            place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
            p = np.frombuffer(b"".join(raw), np.uint32).astype(_U64)
            if box.add(mix(p), np.repeat(b.column("node").to_numpy(), size), np.repeat(b.column("n").to_numpy(), size), np.minimum(place, 65535), *(np.repeat(b.column(f"w{k}").to_numpy() | b.column(f"w{k + 2}").to_numpy(), size) for k in (0, 1))):
                yield box.take()
        yield box.take()

    def meet(t: pa.Table) -> pa.Table:
        low, node, n, at = _column(t, "low", np.uint32), _column(t, "c0", np.int64), _column(t, "c1", np.int32), _column(t, "c2", np.uint16)
        flags = [_column(t, "c3", np.int64), _column(t, "c4", np.int64)]
        if len(n) and n.max() < 1 << 16:  # by block, size and class in one number; two classes that share 16 bits may leave a repeated one, which meets itself in vain
            order = np.argsort(low.astype(_U64) << _U64(32) | n.astype(_U64) << _U64(16) | node.view(_U64) & _U64(0xFFFF))
        else:
            order = np.lexsort((node, n, low))
        keep = order[np.concatenate(([True], (low[order][1:] != low[order][:-1]) | (node[order][1:] != node[order][:-1])))] if len(low) else order
        low, node, n, at, flags = low[keep], node[keep], n[keep].astype(np.int64), at[keep], [f[keep] for f in flags]
        part, piece = place_of(t)
        split = np.isin(low, low[n == 0]) | piece  # others of these blocks are elsewhere: none is ruled out here
        keep = (_feasible(low, n, at, percent, 256, flags) | split) & (n > 0)
        low, node, n, at = low[keep], node[keep], n[keep], at[keep]
        same = (low[1:] == low[:-1]) & (100 * n[:-1] >= percent * n[1:])
        near = np.flatnonzero(same)
        token = low.astype(np.int64) | part << 32
        k, m = len(token), len(near)
        pair = np.arange(k + m) >= k
        give_back()
        return pa.table({
            "token": pa.array(np.concatenate([token, np.zeros(m, np.int64)]), mask=pair),
            "a": pa.array(np.concatenate([node, node[near]]), pa.int64()),
            "n": pa.array(np.concatenate([n, np.zeros(m, np.int64)]).astype(np.int32), mask=pair),
            "at": pa.array(np.concatenate([at, np.zeros(m, np.uint16)]).astype(np.int32), mask=pair),
            "b": pa.array(np.concatenate([np.zeros(k, np.int64), node[near + 1]]), mask=~pair),
        })

    rows = lines.filter("octet_length(prefix) > 0").select("node", "n", "w0", "w1", "w2", "w3", "prefix").mapInArrow(emit, "part int, low binary, c0 binary, c1 binary, c2 binary, c3 binary, c4 binary")
    return rows.groupBy("part").applyInArrow(meet, "token long, a long, n int, at int, b long")


def earlier_pairs(held: DataFrame, tasks: int, percent: int, bits: int, most: int | None = None) -> DataFrame:
    """(a, b, more): b open and later than a, in one block, not ruled out; from rows (token, block, side, node, n, at, w0 to w3, head, i,
    line, open).

    (i, line): where the class comes first, null first. head: the class's first words, by which a pair is left to its first common
    block. With ``most``, a task gives each b its best so many; ``more`` says that it had others.
    """

    def join(t: pa.Table) -> pa.Table:
        token, block, side, node, n, at, line, open_ = (t.column(c).to_numpy() for c in ("token", "block", "side", "node", "n", "at", "line", "open"))
        flags = [t.column(f"w{k}").to_numpy() for k in range(4)]
        raw = t.column("head").to_pylist()
        known = np.array([len(x) // 4 for x in raw])[:, None] > np.arange(HEAD)
        head = np.frombuffer(b"".join(x.ljust(4 * HEAD, b"\0") for x in raw), np.uint32).astype(_U64)
        head = np.where(known, (mix(head) >> _U64(32 - bits)).astype(np.int64).reshape(-1, HEAD), -1)
        doc = pc.rank(t.column("i").combine_chunks(), sort_keys="ascending", null_placement="at_start", tiebreaker="dense").to_numpy()
        order = np.argsort(block, kind="stable")
        cut = np.flatnonzero(np.concatenate(([True], block[order][1:] != block[order][:-1], [True])))
        size, found = np.diff(cut), []
        ready = np.logical_or.reduceat(open_[order], cut[:-1]) if len(order) else np.zeros(0, bool)

        def take(x: np.ndarray, y: np.ndarray) -> None:
            later = (doc[x] < doc[y]) | (doc[x] == doc[y]) & (line[x] < line[y])
            p, q = np.where(later, x, y), np.where(later, y, x)
            ok = open_[q] & ((doc[x] != doc[y]) | (line[x] != line[y])) & ((side[x] < 0) | (side[x] != side[y]))
            p, q = p[ok], q[ok]
            least = need(n[p], n[q], percent)
            ok = (np.minimum(n[p] - at[p], n[q] - at[q]) >= least) & ((n[p] != n[q]) | (least < n[p]))
            p, q, least = p[ok], q[ok], least[ok]
            common = n[p].astype(np.int64) + n[q] - differing(flags, p, q)
            ok = common >= 2 * least
            p, q, spare = p[ok], q[ok], (common - 2 * least)[ok]
            ok = first_common(p, q, head, at, token)
            found.append((p[ok], q[ok], spare[ok]))

        small = np.flatnonzero((size <= 512) & ready)
        budget = np.cumsum(size[small].astype(np.int64) ** 2) // 300_000
        for g in np.unique(budget):
            part = small[budget == g]
            own = order[np.concatenate([np.arange(cut[k], cut[k + 1]) for k in part])]
            x, y = _small_blocks(size[part])
            take(own[x], own[y])
        for k in np.flatnonzero((size > 512) & ready):  # by size: each member against those up to its limit
            own = order[cut[k] : cut[k + 1]]
            own = own[np.argsort(n[own], kind="stable")]
            to = np.searchsorted(n[own], 100 * n[own].astype(np.int64) // percent, "right")
            for a in range(0, len(own), 16):
                width = to[a : a + 16] - np.arange(a, min(a + 16, len(own))) - 1
                x = np.repeat(np.arange(a, min(a + 16, len(own))), width)
                y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(width) - width, width)
                take(own[x], own[y])
        p, q, spare = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 3
        a, b = node[p], node[q]
        by = np.lexsort((a, -spare, b))
        a, b = a[by], b[by]
        keep = np.concatenate(([True], (a[1:] != a[:-1]) | (b[1:] != b[:-1]))) if len(a) else np.zeros(0, bool)
        a, b, more = a[keep], b[keep], np.zeros(int(keep.sum()), bool)
        if most is not None and len(b):
            first = np.flatnonzero(np.concatenate(([True], b[1:] != b[:-1])))
            many = np.diff(np.append(first, len(b)))
            more = np.repeat(many > most, many)
            keep = np.arange(len(b)) - np.repeat(first, many) < most
            a, b, more = a[keep], b[keep], more[keep]
        give_back()
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "more": pa.array(more, pa.bool_())})

    return held.groupBy(F.pmod(F.xxhash64("block"), F.lit(tasks)).alias("task")).applyInArrow(join, "a long, b long, more boolean")


def _hold(percent: int, kind: type):
    def hold(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            good = []
            for x, y in zip(b.column("ea").to_pylist(), b.column("eb").to_pylist(), strict=True):
                p, q = np.sort(np.frombuffer(x, kind)), np.sort(np.frombuffer(y, kind))
                # words that collide count as one word more in common, never as one less
                common = int(np.minimum(np.searchsorted(q, p, "right") - np.searchsorted(q, p, "left"), 1).sum())
                good.append((100 + percent) * common >= percent * (len(p) + len(q)))
            keep = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column("a").filter(keep), b.column("b").filter(keep)], ["a", "b"])

    return hold


def chosen(texts: list[bytes], want: list[list[dict] | None]) -> tuple[Lines, np.ndarray, list[tuple[int, int]]]:
    """The wanted lines (line, node) of each text, alone; which of them are of the class that was asked for, as rows that share an
    identifier may differ; and each one's text and number."""
    parts, node, place = [], [], []
    for k, (text, own) in enumerate(zip(texts, want, strict=True)):
        lines = text.split(b"\n") if own else []
        for w in own or ():
            if w["line"] < len(lines):
                parts.append(lines[w["line"]])
                node.append(w["node"])
                place.append((k, w["line"]))
    x = Lines(parts, None)
    return x, x.node == np.array(node, np.int64)[x.text], [place[t] for t in x.text.tolist()]


def verify(pairs: DataFrame, docs: DataFrame, first: DataFrame, percent: int, most: int = 1 << 20) -> DataFrame:
    """The pairs (a, b) of classes that are similar; words are taken from the documents where the classes come first."""
    nodes = stage(first.join(pairs.select(F.col("a").alias("node")).union(pairs.select("b")).distinct(), "node", "left_semi").select("node", "f"), "nodes")
    want = nodes.groupBy(F.col("f.i").alias("k")).agg(F.collect_list(F.struct("f.line", "node")).alias("want"))  # at most a document's lines
    texts = docs.join(F.broadcast(want) if nodes.count() <= most else want, F.col("i").eqNullSafe(F.col("k"))).select("t", "want")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, "t"):
            x, ok, _ = chosen(texts, b.column("want").to_pylist())
            at = np.flatnonzero(ok)
            yield pa.RecordBatch.from_arrays([pa.array(x.node[at], pa.int64()), pa.array([x.words[x.begin[k] : x.begin[k] + x.size[k]].tobytes() for k in at], pa.binary())], ["node", "elements"])

    sets = stage(texts.mapInArrow(run, "node long, elements binary").dropDuplicates(["node"]), "sets")
    both = pairs
    for side in ("a", "b"):
        both = both.join(sets.select(F.col("node").alias(side), F.col("elements").alias(f"e{side}")), side)
    return both.select("a", "b", "ea", "eb").mapInArrow(_hold(percent, np.uint64), "a long, b long")


def later_lines(docs: DataFrame, percent: int, per_block: int = 20_000) -> DataFrame:
    """(i, gone array<struct<line, node>>) of the identifiers with lines to remove, from (i, t)."""
    rows = docs.count()
    bits = part_bits(rows, 8_000)
    lines = stage(classes(docs, rarity(docs), percent), "lines")
    cols = ("n", "w0", "w1", "w2", "w3")
    first = lines.groupBy("node").agg(F.min(F.struct("i", "line")).alias("f"), F.count(F.lit(1)).alias("m"), *(F.min(c).alias(c) for c in cols), F.max(F.substring("prefix", 1, 4 * HEAD)).alias("head"))
    first = stage(first, "classes")
    met = stage(blocks(lines, bits, percent), "blocks")
    near = met.filter("b is not null").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).groupBy("a", "b").agg(F.count(F.lit(1)).alias("score"))
    near = stage(near, "near")
    links = _likeliest(near)
    members = met.filter("b is null").select("token", F.col("a").alias("node"), "n", "at")
    hot = stage(members.groupBy("token").agg(F.ceil(F.count(F.lit(1)) / F.lit(per_block)).cast("int").alias("parts")).filter("parts > 1"), "hot")
    members = members.join(F.broadcast(hot) if hot.count() <= 1 << 20 else hot, "token", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    # what all rounds need to know of the classes that have a possible partner
    known = stage(first.drop("m").join(met.select(F.col("a").alias("node")).union(near.select("b")).distinct(), "node", "left_semi"), "known")

    def later(pairs: DataFrame) -> DataFrame:
        """(a, b), b the later one, without those whose bitmaps differ in more bits than similar sets do in words."""
        both = pairs.select("a", "b")
        for side in ("a", "b"):
            both = both.join(known.select(F.col("node").alias(side), *(F.col(c).alias(f"{c}_{side}") for c in ("f", *cols))), side)
        differ = sum((F.bit_count(F.col(f"w{k}_a").bitwiseXOR(F.col(f"w{k}_b"))) for k in range(4)), F.lit(0))
        total = F.col("n_a").cast("long") + F.col("n_b")
        least = F.ceil(percent * total / F.lit(100 + percent))
        turn = F.col("f_a") < F.col("f_b")
        return both.filter((F.col("f_a") != F.col("f_b")) & (total - differ >= 2 * least)).select(F.when(turn, F.col("a")).otherwise(F.col("b")).alias("a"), F.when(turn, F.col("b")).otherwise(F.col("a")).alias("b"))

    def round_(open_: DataFrame, of: DataFrame, most: int | None) -> tuple[DataFrame, DataFrame]:
        """Pairs of the classes (node, open) of ``open_`` in the blocks ``of``, and the classes that a verified one settles."""
        held = of.join(known.drop("n"), "node").join(open_, "node", "left")
        held = in_parts(held).select("token", "block", "side", "node", "n", "at", "w0", "w1", "w2", "w3", "head", F.col("f.i").alias("i"), F.col("f.line").alias("line"), "open")
        pairs = stage(earlier_pairs(held.withColumn("open", F.coalesce("open", F.lit(most is not None))), tasks, percent, bits, most), "pairs")
        return pairs, stage(verify(pairs.select("a", "b").distinct(), docs, known, percent).select(F.col("b").alias("node")).distinct(), "settled")

    tasks = max(16, met.count() // 100_000)
    settled = stage(verify(stage(later(links), "links"), docs, known, percent).select(F.col("b").alias("node")).distinct(), "settled")
    pairs, sure = round_(settled.withColumn("open", F.lit(False)), members, 2)
    settled = settled.union(sure)
    rest = stage(pairs.filter("more").select(F.col("b").alias("node")).distinct().join(settled, "node", "left_anti"), "rest")
    if not rest.isEmpty():
        tokens = members.join(rest, "node", "left_semi").select("token").distinct()
        settled = settled.union(round_(rest.withColumn("open", F.lit(True)), members.join(tokens, "token", "left_semi"), None)[1])
    flagged = settled.distinct().withColumn("similar", F.lit(True))
    repeated = first.select("node", "f", "m").join(flagged, "node", "left").filter("m > 1 or similar").select("node", "f", "similar")
    gone = lines.select("i", "line", "node").join(repeated, "node").filter(F.col("similar").isNotNull() | ~F.struct("i", "line").eqNullSafe(F.col("f")))
    return gone.groupBy("i").agg(F.collect_list(F.struct("line", "node")).alias("gone"))


def remove_lines(df: DataFrame, percent: int = 75, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``df`` with its texts without later matches, and with added columns n_lines and n_removed (replaced if there).

    Lines end at line feeds; those without words stay. Order is by identifier, null first, then line number; rows that share an
    identifier have the same places, so a line is no later match of the same-numbered line of such a row. Null text stays null.
    A text all of whose lines go is empty. Other columns are passed on. Matches are judged on the input. An empty table
    stays empty.
    """
    docs = df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"))
    gone = stage(later_lines(docs, percent), "gone").withColumnRenamed("i", "_gone_i").withColumnRenamed("gone", "_gone")
    base = df.drop(*({"n_lines", "n_removed"} & set(df.columns)))
    both = base.join(gone, F.col(id_col).eqNullSafe(F.col("_gone_i")), "left").drop("_gone_i")
    names = base.columns
    at = names.index(text_col)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, text_col):
            gone, null, out, counts, removed = b.column("_gone").to_pylist(), b.column(text_col).is_null().to_pylist(), [], [], []
            _, ok, place = chosen(texts, gone)
            drop: dict[int, set[int]] = {}
            for (k, n), good in zip(place, ok.tolist(), strict=True):
                if good:
                    drop.setdefault(k, set()).add(n)
            for k, text in enumerate(texts):
                lost = drop.get(k, ())
                counts.append(text.count(b"\n") + 1)
                removed.append(len(lost))
                if lost:
                    text = b"\n".join(s for n, s in enumerate(text.split(b"\n")) if n not in lost)
                out.append(None if null[k] else text)
            cols = [pa.array(out, pa.binary()).cast(pa.string()) if n == at and drop else b.column(n) for n in range(len(names))]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(counts, pa.int64()), pa.array(removed, pa.int64())], [*names, "n_lines", "n_removed"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema)
    return both.mapInArrow(run, f"{kinds}, n_lines long, n_removed long")
