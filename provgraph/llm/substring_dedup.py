"""Repeated passages across documents, located by sharded automata.

1. Anchors: of the 5-word hashes in each 13-word window the least is its anchor, so equal windows have equal anchors and a
   document has about a fifth as many anchors as words. Anchors are brought together by hash; those of two documents mark candidates.
2. Candidate windows alone are brought together. Windows that agree in two hashes are confirmed as one phrase, whose owner is
   the first document that holds it; every later document learns its phrases and their owners. What a task holds several times
   is combined there, so a hot passage adds one row a buffer, not one a document.
3. Documents form shards of some megabytes. A shard's phrases are compiled into an Aho-Corasick automaton over word numbers: of each
   document's confirmed windows as few as cover the same words. All its documents are streamed whole, and each occurrence of a
   phrase with an earlier owner goes, whichever document brought the phrase. An automaton's size follows its shard's text,
   whatever the corpus holds.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import compress

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.common import stage, whole_id
from provgraph.llm.ngram_join import _column, part_bits
from provgraph.llm.wordkernel import _combine, batches, distinct, give_back, joined, mix, words

ANCHOR = 5
_U64 = np.uint64


def _least(g: np.ndarray, span: int) -> np.ndarray:
    """Minimum over ``span`` consecutive values, at each start."""
    have = 1
    while have < span:
        step = min(have, span - have)
        g = np.minimum(g[:-step], g[step:]) if len(g) > step else g[:0]
        have += step
    return g


def _anchors(texts: list[bytes], window: int) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """For each text the anchor of every window, in order; all word hashes and where each text's words begin."""
    data, at = joined(texts)
    w, starts, _ = words(data)
    cut = np.searchsorted(starts, at)
    low = _least(_combine(w, ANCHOR), window - ANCHOR + 1)
    return [low[a : max(a, b - window + 1)] for a, b in zip(cut[:-1], cut[1:], strict=True)], w, cut


def _full(h: np.ndarray, bits: int) -> np.ndarray:
    """The part of a hash that tells entries apart: its first 48 + bits bits, at most all."""
    return (h if bits >= 16 else h >> _U64(16 - bits) << _U64(16 - bits)).view(np.int64)


def _keys(t: pa.Table, bits: int) -> np.ndarray:
    """The same of a part's entries, put together from the part and two columns."""
    rest = _column(t, "low", np.uint32).astype(_U64) << _U64(16) | _column(t, "c0", np.uint16).astype(_U64)
    rest = rest << _U64(16 - bits) if bits <= 16 else rest >> _U64(bits - 16)
    return (rest | _U64(t.column("part")[0].as_py()) << _U64(64 - bits)).view(np.int64)


_LISTS = pa.schema([("id", pa.int64()), ("keys", pa.binary()), ("owners", pa.binary())])


def _lists(keys: np.ndarray, docs: np.ndarray, owners: np.ndarray | None) -> list[pa.Array]:
    """Arrays of _LISTS, one entry per document."""
    order = np.argsort(docs, kind="stable")
    docs = docs[order]
    at = np.flatnonzero(np.concatenate(([True], docs[1:] != docs[:-1]))) if len(docs) else np.zeros(0, int)
    ends = np.append(at[1:], len(docs))[: len(at)]
    cut = lambda c: pa.array([c[order[a:b]].tobytes() for a, b in zip(at, ends, strict=True)], pa.binary())
    return [pa.array(docs[at], pa.int64()), cut(keys), pa.nulls(len(at), pa.binary()) if owners is None else cut(owners)]


class _Exchange:
    """Gathers (hash, document, check) and lays them out by the hash's leading bits, one row per part.

    What several documents of a buffer hold goes out once, with the least of them; the lists of the documents that thereby
    know already (for anchors all of them, for windows the later ones) are rows of negative parts, dealt out by document.
    """

    NAMES = ("part", "low", "c0", "c1", "c2", "id", "keys", "owners")
    DDL = "part int, low binary, c0 binary, c1 binary, c2 binary, id long, keys binary, owners binary"

    def __init__(self, bits: int, owned: bool, flush: int = 500_000):
        self.bits, self.owned, self.flush = bits, owned, flush
        self.held: list[tuple[np.ndarray, ...]] = []
        self.n = 0

    def add(self, h: np.ndarray, doc: np.ndarray, check: np.ndarray) -> bool:
        self.held.append((h, doc, check))
        self.n += len(h)
        return self.n >= self.flush

    def take(self) -> pa.RecordBatch:
        h, doc, check = (np.concatenate(x) for x in zip(*self.held, strict=True)) if self.held else (np.zeros(0, _U64), np.zeros(0, np.int64), np.zeros(0, np.uint32))
        self.held, self.n = [], 0
        order = np.argsort(h)
        h, doc, check = h[order], doc[order], check[order]
        new = np.concatenate(([True], (h[1:] != h[:-1]) | (check[1:] != check[:-1]))) if len(h) else np.zeros(0, bool)
        first = np.flatnonzero(new)
        least = np.minimum.reduceat(doc, first) if len(first) else doc
        own = np.repeat(least, np.diff(np.append(first, len(h))))
        known = doc > own
        if not self.owned and len(first):
            known = np.repeat(np.logical_or.reduceat(known, first), np.diff(np.append(first, len(h))))
        ids, keys, owners = _lists(_full(h[known], self.bits), doc[known], own[known] if self.owned else None)
        h, check = h[first], check[first]
        part = (h >> _U64(64 - self.bits)).astype(np.int64)
        at = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1]))) if len(part) else np.zeros(0, int)
        ends = np.append(at[1:], len(part))[: len(at)]
        cols = [(h << _U64(self.bits) >> _U64(32)).astype(np.uint32), (h << _U64(self.bits) << _U64(32) >> _U64(48)).astype(np.uint16), least, check if self.owned else check[:0]]
        rows = [pa.array([c[a:b].tobytes() for a, b in zip(at, ends, strict=True)] + [None] * len(ids), pa.binary()) for c in cols]
        dealt = -1 - (ids.to_numpy() & ((1 << self.bits) - 1))
        none = pa.nulls(len(at), pa.binary())
        del h, doc, check, order, own
        give_back()
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate([part[at], dealt]), pa.int32()), *rows, pa.concat_arrays([pa.nulls(len(at), pa.int64()), ids]), pa.concat_arrays([none, keys]), pa.concat_arrays([none, owners])], self.NAMES)


def _meet(bits: int, owned: bool):
    """Lists for the documents of a part: of anchors that two documents hold, or of windows that an earlier one holds."""

    def meet(t: pa.Table) -> pa.Table:
        if t.column("part")[0].as_py() < 0:
            return t.select(["id", "keys", "owners"]).cast(_LISTS)
        key, doc = _keys(t, bits), _column(t, "c1", np.int64)
        check = _column(t, "c2", np.uint32) if owned else np.zeros(len(key), np.uint32)
        order = np.lexsort((doc, check, key))
        key, doc, check = key[order], doc[order], check[order]
        first = np.flatnonzero(np.concatenate(([True], (key[1:] != key[:-1]) | (check[1:] != check[:-1])))) if len(key) else np.zeros(0, int)
        many = np.diff(np.append(first, len(key)))
        owner = np.repeat(doc[first], many)
        keep = doc > owner
        if not owned and len(first):
            keep = np.repeat(np.logical_or.reduceat(keep, first), many)
        out = pa.table(_lists(key[keep], doc[keep], owner[keep] if owned else None), schema=_LISTS)
        give_back()
        return out

    return meet


def shared_anchors(docs: DataFrame, window: int, bits: int) -> DataFrame:
    """(id, keys binary) for the anchors that rows of at least two identifiers hold; several rows per id."""

    def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        box = _Exchange(bits, False)
        for b, texts in batches(it, "t"):
            for i, a in zip(b.column("i").to_pylist(), _anchors(texts, window)[0], strict=True):
                if i is not None and len(a):
                    a = distinct(a)
                    if box.add(a, np.full(len(a), i), np.zeros(len(a), np.uint32)):
                        yield box.take()
        yield box.take()

    return docs.mapInArrow(emit, _Exchange.DDL).groupBy("part").applyInArrow(_meet(bits, False), "id long, keys binary, owners binary").select("id", "keys")


def _sha(parts: list[bytes]) -> str:
    return hashlib.sha256(b" ".join(parts)).hexdigest()


def candidates(docs: DataFrame, anchors: DataFrame, window: int, bits: int) -> DataFrame:
    """(i, n_words, sha, t, passages) of every row: t and passages only where a window has a shared anchor, else the digest."""
    lists = anchors.groupBy("id").agg(F.collect_list("keys").alias("lists"))
    both = docs.join(lists, docs["i"] == lists["id"], "left").select("i", "t", "lists")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, "t"):
            lists = b.column("lists").to_pylist()
            rows = []
            for text, low, mine in zip(texts, _anchors(texts, window)[0], lists, strict=True):
                parts = text.split()
                at = np.zeros(0, int)
                if mine and len(low):
                    mine = np.sort(np.frombuffer(b"".join(mine), np.int64))
                    key = _full(low, bits)
                    at = np.flatnonzero(mine[np.minimum(np.searchsorted(mine, key), len(mine) - 1)] == key)
                if not len(at):
                    rows.append((len(parts), _sha(parts), None, None))
                    continue
                cut = np.flatnonzero(np.diff(at) > 1)
                runs = zip(at[np.append(0, cut + 1)].tolist(), at[np.append(cut, len(at) - 1)].tolist(), strict=True)
                rows.append((len(parts), None, text, b"\n".join(b" ".join(parts[s : e + window]) for s, e in runs)))
            kinds = (pa.int64(), pa.string(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([b.column("i"), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))], ["i", "n_words", "sha", "t", "passages"])

    return both.mapInArrow(run, "i long, n_words long, sha string, t binary, passages binary")


def _check(w: np.ndarray, window: int) -> np.ndarray:
    """A second hash of every window of ``window`` words, by sums of differently mixed words at their places."""
    n = len(w) - window + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    total = np.zeros(n, _U64)
    for j in range(window):
        total += mix(w[j : j + n] ^ _U64(0x5851F42D4C957F2D * (j + 1) & 0xFFFFFFFFFFFFFFFF))
    return (total >> _U64(32)).astype(np.uint32)


def recurring(held: DataFrame, window: int, bits: int) -> DataFrame:
    """(id, keys binary, owners binary): candidate windows of ``id`` that an earlier ``owner`` holds, confirmed by a
    second hash; several rows per id. The least owner that any of a shard's documents is told of a window is earlier than each of these."""

    def emit(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        box = _Exchange(bits, True)
        for b, passages in batches(it, "passages"):
            lines = [own.split(b"\n") for own in passages]
            data, at = joined([x for own in lines for x in own])
            w, starts, _ = words(data)
            cut = np.searchsorted(starts, at)
            size = np.maximum(np.diff(cut) - window + 1, 0)
            own = np.arange(size.sum()) + np.repeat(cut[:-1] - (np.cumsum(size) - size), size)
            doc = np.repeat(np.repeat(b.column("i").to_numpy(), [len(x) for x in lines]), size)
            if box.add(_combine(w, window)[own], doc, _check(w, window)[own]):
                yield box.take()
        yield box.take()

    return held.mapInArrow(emit, _Exchange.DDL).groupBy("part").applyInArrow(_meet(bits, True), "id long, keys binary, owners binary")


def _cover(at: np.ndarray, window: int) -> list[int]:
    """Of window starts, ascending, as few as cover the same words."""
    chosen: list[int] = []
    ahead = np.append(at[1:], -1).tolist()
    for a, after in zip(at.tolist(), ahead, strict=True):
        # needed if the next one leaves a gap after what is covered
        covered = chosen[-1] + window if chosen else -1
        if a + window > covered and (after < 0 or after > max(covered, a)):
            chosen.append(a)
    return chosen


def _locate(window: int, bits: int, shard: int = 4 << 20):
    """Removes from each text what the automaton of its shard finds with an earlier owner."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, "t", shard):
            docs, keys, owners = (b.column(c).to_pylist() for c in ("i", "keys", "owners"))
            data, at = joined(texts)
            w, starts, _ = words(data)
            cut = np.searchsorted(starts, at)
            h = _combine(w, window)
            number = (w >> _U64(32)).astype(np.int64)
            phrases: dict[int, int] = {}  # whole hash -> least owner
            place: dict[int, int] = {}
            for k, (a, z) in enumerate(zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True)):
                if not keys[k] or z - a < window:
                    continue
                known, who = (np.frombuffer(b"".join(x[k]), np.int64) for x in (keys, owners))
                order = np.lexsort((who, known))
                known, who = known[order], who[order]
                mine = _full(h[a : z - window + 1], bits)
                found = np.minimum(np.searchsorted(known, mine), len(known) - 1)
                for j in _cover(np.flatnonzero(known[found] == mine), window):
                    whole, owner = int(h[a + j]), int(who[found[j]])
                    if whole not in phrases:
                        place[whole] = a + j
                    phrases[whole] = min(owner, phrases.get(whole, owner))
            auto = ahocorasick.Automaton(ahocorasick.STORE_INTS, ahocorasick.KEY_SEQUENCE)
            hashes, first = np.fromiter(phrases, _U64, len(phrases)), np.fromiter(phrases.values(), np.int64, len(phrases))
            for n, whole in enumerate(phrases):
                auto.add_word(tuple(number[place[whole] : place[whole] + window].tolist()), n)
            if phrases:
                auto.make_automaton()
            rows = []
            for i, t, a, z in zip(docs, texts, cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                p = t.split()
                hits = list(auto.iter(tuple(number[a:z].tolist()))) if phrases and i is not None and z - a >= window else []
                if hits:
                    end, n = np.array(hits, np.int64).T
                    start = end - window + 1
                    start = start[(h[a + start] == hashes[n]) & (first[n] < i)]  # numbers have 32 bits, so the whole hash is compared
                    gone = np.zeros(len(p) + 1, np.int32)
                    np.add.at(gone, start, 1)
                    np.add.at(gone, start + window, -1)
                    out = np.cumsum(gone[:-1]) > 0
                    if out.any():
                        rows.append((len(p), int(out.sum()), _sha(list(compress(p, (~out).tolist())))))
                        continue
                rows.append((len(p), 0, _sha(p)))
            cols = [pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.string()), strict=True)]
            del auto, phrases, place, number, h, w
            yield pa.RecordBatch.from_arrays([b.column("i"), *cols], ["i", "n_words", "n_removed", "sha"])

    return run


def remove_repeats(df: DataFrame, window: int = 13, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id_col, n_words, n_removed, kept_sha256) of each row. Identifiers are whole numbers of any width, else a TypeError.

    A word goes if some window of ``window`` words over it also starts in a row with a smaller identifier. Null text has
    no words. Rows that share an identifier are not earlier than each other. A row with a null identifier is
    neither earlier nor later than any other and keeps all its words. Other columns are not read.
    """
    kind = df.schema[id_col].dataType.simpleString()
    docs = df.select(whole_id(df, id_col).alias("i"), F.col(text_col).alias("t"))
    bits = part_bits(df.count(), 16_000)
    base = stage(candidates(docs, shared_anchors(docs, window, bits), window, bits), "candidates")
    held = base.filter("passages is not null").select("i", "passages")
    needs = recurring(held, window, bits).groupBy(F.col("id").alias("i")).agg(F.collect_list("keys").alias("keys"), F.collect_list("owners").alias("owners"))
    found = base.filter("passages is not null").select("i", "t").join(needs, "i", "left")
    located = found.mapInArrow(_locate(window, bits), "i long, n_words long, n_removed long, sha string")
    rest = base.filter("passages is null").select("i", "n_words", F.lit(0).cast("long").alias("n_removed"), "sha")
    return located.union(rest).select(F.col("i").cast(kind).alias(id_col), "n_words", "n_removed", F.col("sha").alias("kept_sha256"))
