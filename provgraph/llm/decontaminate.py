"""Benchmark decontamination: size-partitioned MinHash containment search, verified by exact shingle containment.

Items are partitioned by their number of shingles, with a ratio of 1.5 between the ends of a part. For a part whose
largest item has M shingles, a document is seen as overlapping stretches of at most about 1.25 M + 8 shingles, one of which
holds any passage of M; so the similarity of an item to the stretch that holds it has a lower bound whatever
the document's length, and the number of hash functions is what makes a miss as rare as ``miss``. One agreeing
minimum makes a candidate. Candidates are counted exactly on the shingle sets.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.common import stage
from provgraph.llm.wordkernel import batches, distinct, window_arrays

RATIO = 1.5


class ItemIndex:
    """Signatures of a block of items, by size part."""

    def __init__(self, ids: list[int], texts: list[str], k: int, percent: int, miss: float, seed: int = 11):
        h, begin, _, _ = window_arrays([(t or "").encode() for t in texts], k, True, True)
        sets = [distinct(h[a:b]) for a, b in zip(begin[:-1], begin[1:], strict=True)]
        self.items = [(i, s) for i, s in zip(ids, sets, strict=True) if len(s)]
        self.k, self.percent = k, percent
        sizes = np.array([len(s) for _, s in self.items], np.int64)
        base = 1 if not len(sizes) else int(max(1, min(8, sizes.min() // 4)))
        self.parts: list[tuple[int, int, np.ndarray]] = []  # level, blocks in a stretch, items; blocks of a level: base << level shingles
        self.base, self.levels, worst = base, 0, 1.0
        part = np.floor(np.log(np.maximum(sizes, 1)) / math.log(RATIO)).astype(int)
        for p in np.unique(part):
            members = np.flatnonzero(part == p)
            most, q, least = int(sizes[members].max()), int(sizes[members].min()), percent / 100
            level = max(0, int(math.log2(max(1, most // 4 / base))))
            span = math.ceil(most / (base << level)) + 1
            self.parts.append((level, span, members))
            self.levels = max(self.levels, level + 1)
            worst = min(worst, least * q / (span * (base << level) + (1 - least) * q))
        self.functions = max(1, math.ceil(math.log(miss) / math.log(1 - worst))) if worst < 1 else 1
        rng = np.random.Generator(np.random.PCG64(seed))
        self.mult = rng.integers(1, 2**63, self.functions, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.minima: list[list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = []  # by function and part: bitmap of low bits, values, their items
        for m in self.mult:
            own = []
            for _, _, members in self.parts:
                v = np.array([(self.items[i][1] * m).min() for i in members], np.uint64)
                order = np.argsort(v)
                bitmap = np.zeros(1 << 16, bool)
                bitmap[(v & np.uint64(0xFFFF)).astype(np.int64)] = True
                own.append((bitmap, v[order], members[order]))
            self.minima.append(own)

    def candidates(self, h: np.ndarray, begin: np.ndarray) -> set[tuple[int, int]]:
        """(text, item) pairs of which a stretch and the item agree in a minimum."""
        size, found, starts, owner = np.diff(begin), set(), [], []
        if not size.sum() or not self.parts:
            return found
        for level in range(self.levels):  # where a level's blocks begin, in the level below
            step = self.base if not level else 2
            blocks = -(-size // step)
            first = np.concatenate([[0], np.cumsum(blocks)])
            below = begin if not level else np.concatenate([[0], np.cumsum(size)])
            starts.append(np.repeat(below[:-1], blocks) + (np.arange(first[-1]) - np.repeat(first[:-1], blocks)) * step)
            owner.append(np.repeat(np.arange(len(size)), blocks))
            size = blocks
        top = np.iinfo(np.uint64).max
        for m, own in zip(self.mult, self.minima, strict=True):
            fine, lows = h * m, []
            for at in starts:
                fine = np.minimum.reduceat(fine, at)
                lows.append(fine)
            for (level, span, _), (bitmap, values, members) in zip(self.parts, own, strict=True):
                low, have = lows[level], 1
                while have < span:  # minima over ``span`` blocks from each on; past a text's end they only add candidates
                    step = min(have, span - have)
                    low = np.minimum(low, np.concatenate([low[step:], np.full(min(step, len(low)), top)]))
                    have += step
                hit = np.flatnonzero(bitmap[(low & np.uint64(0xFFFF)).astype(np.int64)])
                if len(hit):
                    lo, hi = np.searchsorted(values, low[hit], "left"), np.searchsorted(values, low[hit], "right")
                    for k in np.flatnonzero(hi > lo):
                        found.update((int(owner[level][hit[k]]), int(i)) for i in members[lo[k] : hi[k]])
        return found


def _hits(index: ItemIndex, texts: list[bytes]) -> list[list[tuple[int | None, int]]]:
    """For each text the items in it: (identifier, containment in percent, floored)."""
    h, begin, _, _ = window_arrays(texts, index.k, True, True)
    hits: list[list[tuple[int | None, int]]] = [[] for _ in texts]
    sets: dict[int, np.ndarray] = {}
    for doc, item in index.candidates(h, begin):
        if begin[doc] == begin[doc + 1]:
            continue
        if doc not in sets:
            sets[doc] = distinct(h[begin[doc] : begin[doc + 1]])
        own, (name, want) = sets[doc], index.items[item]
        n = int((own[np.minimum(np.searchsorted(own, want), len(own) - 1)] == want).sum())
        if 100 * n >= index.percent * len(want):
            hits[doc].append((name, 100 * n // len(want)))
    return hits


def _indexes(df: DataFrame, items: DataFrame, k: int, percent: int, miss: float, item_id: str, item_text: str, block: int) -> Iterator[tuple[Broadcast, bool]]:
    """Broadcast indexes of the items, ``block`` at a time, one at least, and whether it is the only one. Each is destroyed when the next is asked for."""
    held: list = []
    rows, before = items.select(F.col(item_id).cast("long").alias("i"), F.col(item_text).alias("t")).toLocalIterator(), None

    def send(own: list) -> Broadcast:
        return df.sparkSession.sparkContext.broadcast(ItemIndex([x["i"] for x in own], [x["t"] for x in own], k, percent, miss))

    for r in rows:
        if len(held) == block:
            before = send(held)
            yield before, False
            before.destroy()
            held = []
        held.append(r)
    yield send(held), before is None


def drop_contaminated(df: DataFrame, items: DataFrame, k: int = 5, percent: int = 75, miss: float = 1e-6, text_col: str = "text", item_id: str = "item_id", item_text: str = "text", block: int = 20_000) -> DataFrame:
    """The rows of ``df`` that hold no item, as find_items() says. With several blocks of items the rows left are written after each, so
    that one index at a time is in memory."""
    for shared, only in _indexes(df, items, k, percent, miss, item_id, item_text, block):

        def run(it: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for b, texts in batches(it, text_col):
                yield b.filter(pa.array([not x for x in _hits(shared.value, texts)]))

        df = df.mapInArrow(run, df.schema)
        df = df if only else stage(df, "clean")
    return df


def find_items(df: DataFrame, items: DataFrame, k: int = 5, percent: int = 75, miss: float = 1e-6, id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text", block: int = 20_000) -> DataFrame:
    """(id_col, contaminated, n_items, item_ids, best_percent) of each row of ``df``.

    An item is in a text if at least ``percent`` of its distinct k-word shingles are; words are lower-cased A-Z and a text with
    fewer than k words is one shingle. Items without words are in nothing. ``item_ids``: ascending, null ones
    left out; ``n_items`` counts all. ``best_percent``: the largest containment found among these, floored. Null text is empty.
    Items are taken in blocks of ``block`` against all rows, one index at a time; with no item nothing is contaminated. Equal item
    rows count each. Clashing names in other columns do not matter: only the named ones are read.
    """
    kind = df.schema[id_col].dataType.simpleString()
    docs, found = df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")), None
    for shared, only in _indexes(df, items, k, percent, miss, item_id, item_text, block):
        if not only and found is None:  # rows need a name that all blocks agree on
            docs = stage(docs.withColumn("u", F.monotonically_increasing_id()), "rows")
        name = docs.columns[-1] if not only else "i"

        def run(it: Iterator[pa.RecordBatch], shared=shared, name=name, only=only) -> Iterator[pa.RecordBatch]:
            for b, texts in batches(it, "t"):
                hits = _hits(shared.value, texts)
                cols = [b.column(name), pa.array([len(x) for x in hits], pa.int64()), pa.array([sorted(i for i, _ in x if i is not None) for x in hits], pa.list_(pa.int64())), pa.array([max((p for _, p in x), default=0) for x in hits], pa.int64())]
                yield pa.RecordBatch.from_arrays(cols if only else [c.filter(pa.array([bool(x) for x in hits])) for c in cols], ["id", "n", "ids", "best"])

        got = docs.mapInArrow(run, f"id {kind if only else 'long'}, n long, ids array<long>, best long")
        if only:
            break
        found = stage(got, "items") if found is None else found.union(stage(got, "items"))
    if found is not None:  # each row's findings from all blocks of items
        sums = found.groupBy("id").agg(F.sum("n").alias("n"), F.array_sort(F.flatten(F.collect_list("ids"))).alias("ids"), F.max("best").alias("best"))
        got = docs.select("i", "u").join(sums.withColumnRenamed("id", "u"), "u", "left")
        got = got.select(F.col("i").alias("id"), F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("ids", F.array().cast("array<bigint>")).alias("ids"), F.coalesce("best", F.lit(0)).alias("best"))
    return got.select(F.col("id").alias(id_col), (F.col("n") > 0).alias("contaminated"), F.col("n").alias("n_items"), F.array_join("ids", ",").alias("item_ids"), F.col("best").alias("best_percent"))
