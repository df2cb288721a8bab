"""Best-fit packing of tokenised documents by a linear grouping scheme.

Lengths are bounded by the capacity, so the whole packing problem is the histogram of piece lengths: at most
``capacity`` numbers, whatever the corpus holds. The driver plans on it. Large lengths, in descending order, form groups
of equal cardinality and are rounded up to their group's largest; configurations of these few sizes are chosen by column
generation; actual lengths replace the rounded ones; what is left, and all small lengths, go best-fit into the
remaining room. The plan is a list of runs (length, first rank, how many, first sequence, offset), and
each piece finds its place by its rank among the pieces of its length.
"""

from __future__ import annotations

import math
import zlib
from bisect import insort
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cache
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.llm.common import stage
from provgraph.llm.wordkernel import batches

END_ID = 1


class ChunkTokenizer:
    """Token ids of whole texts, put together from those of white-space-free chunks, which are remembered.

    The tokenizer collapses white space to a blank that no token holds, and neither its case mapping nor its
    composition of accents reaches across one, so chunks between ASCII white space are independent. At about ``most`` bytes the
    memory of chunks starts anew. The tokenizer maps letters to lower case anyway, so A-Z are mapped at once; and a full stop or comma
    after an ASCII letter ends a chunk as a token of its own.
    """

    ENTRY = 200  # bytes that the tables hold for a chunk besides its own and its ids

    def __init__(self, path: str, most: int = 64 << 20):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.most = most
        self.forget()

    def forget(self) -> None:
        self.place: dict[bytes, int] = {}
        self.ids, self.start, self.size = np.zeros(1 << 18, np.uint32), np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64)
        self.used = self.bytes = 0

    def _learn(self, new: set[bytes]) -> None:
        stopped = [c for c in new if c[-1] in b".," and len(c) > 1 and 97 <= c[-2] <= 122]
        cores = {c[:-1] for c in stopped}
        cores.update(c[-1:] for c in stopped)
        new = list(new.difference(stopped).union(c for c in cores if c not in self.place))
        self._encode(new)
        if stopped:
            n, core, end = len(self.place), *(np.fromiter(map(self.place.__getitem__, x), np.int64, len(stopped)) for x in ([c[:-1] for c in stopped], [c[-1:] for c in stopped]))
            size = self.size[core] + self.size[end]
            total = int(size.sum())
            self._make_room(total, len(stopped))
            at = self.used + np.cumsum(size) - size
            self.start[n : n + len(stopped)], self.size[n : n + len(stopped)] = at, size
            for part, to in ((core, at), (end, at + self.size[core])):
                many = self.size[part]
                step = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                self.ids[np.repeat(to, many) + step] = self.ids[np.repeat(self.start[part], many) + step]
            self.place.update(zip(stopped, range(n, n + len(stopped)), strict=True))
            self.bytes += sum(map(len, stopped)) + self.ENTRY * len(stopped) + 4 * total
            self.used += total

    def _make_room(self, ids: int, entries: int) -> None:
        while len(self.ids) < self.used + ids:
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        while len(self.start) < len(self.place) + entries:
            self.start, self.size = (np.concatenate([x, np.zeros_like(x)]) for x in (self.start, self.size))

    def _encode(self, new: list[bytes]) -> None:
        got = [e.ids for e in self.tokenizer.encode_batch_fast([c.decode("utf-8", "replace") for c in new], add_special_tokens=False)]
        size = np.fromiter(map(len, got), np.int64, len(got))
        flat = np.fromiter(chain.from_iterable(got), np.uint32, int(size.sum()))
        n = len(self.place)
        self._make_room(len(flat), len(new))
        self.ids[self.used : self.used + len(flat)] = flat
        self.start[n : n + len(new)] = self.used + np.cumsum(size) - size
        self.size[n : n + len(new)] = size
        self.place.update(zip(new, range(n, n + len(new)), strict=True))
        self.bytes += sum(map(len, new)) + self.ENTRY * len(new) + 4 * len(flat)
        self.used += len(flat)

    def encode(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and where each text's begin (one more entry for the end)."""
        chunks = [t.lower().split() for t in texts]
        flat = list(chain.from_iterable(chunks))
        if self.bytes > self.most:
            self.forget()
        at = np.fromiter(map(self.place.get, flat, repeat(-1)), np.int64, len(flat))
        if len(missing := np.flatnonzero(at < 0)):
            absent = [flat[i] for i in missing.tolist()]
            self._learn(set(absent))
            at[missing] = np.fromiter(map(self.place.__getitem__, absent), np.int64, len(absent))
        size = self.size[at]
        end = np.concatenate([[0], np.cumsum(size)])
        index = np.arange(end[-1]) + np.repeat(self.start[at] - end[:-1], size)
        return self.ids[index], end[np.concatenate([[0], np.cumsum([len(c) for c in chunks])])]


@cache
def _tokenizer(path: str) -> ChunkTokenizer:
    """One for each worker process, which serves many tasks."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    return ChunkTokenizer(path)


def pieces(df: DataFrame, tokenizer_path: str, capacity: int = 4096, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """Each text's ids and the end id, cut into pieces of ``capacity`` only where longer."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = _tokenizer(tokenizer_path)
        for b, texts in batches(it, "t"):
            ids, cut = tok.encode(texts)
            rows: list[tuple] = []
            for doc, a, z in zip(b.column("i").to_pylist(), cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                own = np.append(ids[a:z], np.uint32(END_ID)).astype("<u4")
                for k, s in enumerate(range(0, len(own), capacity)):
                    p = own[s : s + capacity]
                    rows.append((doc, k, s, len(p), zlib.crc32(p.tobytes()), *([p.tolist()] if with_ids else [])))
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (b.column("i").type, pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64())), strict=False)], names)

    names = [id_col, "piece", "start", "length", "ids_crc32", *(["ids"] if with_ids else [])]
    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(run, f"`{id_col}` {kind}, piece int, start long, length long, ids_crc32 long" + (", ids array<long>" if with_ids else ""))


@dataclass
class Plan:
    capacity: int
    sequences: int = 0
    runs: list[tuple[int, int, int, int, int]] = field(default_factory=list)  # length, first rank, how many, first sequence, offset
    room: dict[int, list[tuple[int, int]]] = field(default_factory=dict)  # free tokens -> (first sequence, how many)
    sizes: list[int] = field(default_factory=list)  # the keys of room, ascending
    rank: dict[int, int] = field(default_factory=dict)

    def open(self, n: int) -> int:
        self.sequences += n
        return self.sequences - n

    def put(self, length: int, n: int, first: int, offset: int) -> None:
        r = self.rank.get(length, 0)
        self.runs.append((length, r, n, first, offset))
        self.rank[length] = r + n

    def leave(self, free: int, first: int, n: int) -> None:
        if free and n:
            if free not in self.room:
                self.room[free] = []
                insort(self.sizes, free)
            self.room[free].append((first, n))

    def best_fit(self, length: int, n: int) -> None:
        from bisect import bisect_left

        while n:
            at = bisect_left(self.sizes, length)
            if at == len(self.sizes):
                each = self.capacity // length
                full, rest = divmod(n, each)
                for bins, items in ((full, each), (1, rest)):
                    if bins and items:
                        first = self.open(bins)
                        for j in range(items):
                            self.put(length, bins, first, j * length)
                        self.leave(self.capacity - items * length, first, bins)
                return
            free = self.sizes[at]
            first, have = self.room[free].pop()
            if not self.room[free]:
                del self.room[free], self.sizes[at]
            take = min(n, have)
            self.put(length, take, first, self.capacity - free)
            self.leave(free - length, first, take)
            self.leave(free, first + take, have - take)
            n -= take


def _configurations(sizes: list[int], demand: list[int], capacity: int, rounds: int = 600) -> list[tuple[np.ndarray, int]]:
    """(how many of each size, how often), by column generation over the fractional covering problem, rounded down."""
    k = len(sizes)
    s, d = np.array(sizes), np.array(demand, float)
    basis = np.diag((capacity // s).astype(float))
    for _ in range(rounds):
        try:
            y = np.linalg.solve(basis.T, np.ones(k))
        except np.linalg.LinAlgError:
            break
        value, pick = np.zeros(capacity + 1), np.full(capacity + 1, -1)
        for c in range(int(s.min()), capacity + 1):  # the most valuable configuration at these prices
            fit = s <= c
            v = np.where(fit, y + value[c - np.minimum(s, c)], 0)
            g = int(v.argmax())
            value[c], pick[c] = (v[g], g) if v[g] > value[c - 1] else (value[c - 1], -1)
        if value[capacity] <= 1 + 1e-6:
            break
        column, c = np.zeros(k), capacity
        while c > 0:
            if pick[c] < 0:
                c -= 1
            else:
                column[pick[c]] += 1
                c -= s[pick[c]]
        x, into = np.linalg.solve(basis, d), np.linalg.solve(basis, column)
        ratio = np.where(into > 1e-9, x / np.where(into > 1e-9, into, 1), np.inf)
        basis[:, int(ratio.argmin())] = column
    x = np.linalg.solve(basis, d)
    return [(basis[:, j].astype(int), int(x[j] + 1e-9)) for j in range(k) if x[j] >= 1]


def plan_packing(counts: dict[int, int], capacity: int = 4096, groups: int = 40, small: float = 1 / 8, unit: int = 8) -> Plan:
    """``counts``: how many pieces of each length (1 to ``capacity``)."""
    plan = Plan(capacity)
    if full := counts.get(capacity, 0):
        plan.put(capacity, full, plan.open(full), 0)
    large = [(n, counts[n]) for n in sorted(counts, reverse=True) if capacity * small < n < capacity]
    each = max(1, math.ceil(sum(c for _, c in large) / groups))
    members: list[list[list[int]]] = []  # by group: [length, how many], descending
    filled = each
    for length, c in large:
        while c:
            if filled == each:
                members.append([])
                filled = 0
            take = min(c, each - filled)
            members[-1].append([length, take])
            filled, c = filled + take, c - take
    units = capacity // unit
    sized: dict[int, list[list[int]]] = {}
    for m in members:  # groups that round up to one size are one
        sized.setdefault(math.ceil(m[0][0] / unit), []).extend(m)
    sizes = [z for z in sized if z <= units]
    if sizes:
        for config, times in _configurations(sizes, [sum(c for _, c in sized[z]) for z in sizes], units):
            state = [(plan.open(times), times, 0)]
            for g in np.flatnonzero(config):
                queue = sized[sizes[g]]
                for _ in range(config[g]):
                    after = []
                    for first, n, used in state:
                        while n:
                            if not queue:
                                after.append((first, n, used))
                                break
                            length, have = queue[0]
                            take = min(n, have)
                            plan.put(length, take, first, used)
                            after.append((first, take, used + length))
                            first, n = first + take, n - take
                            if take == have:
                                queue.pop(0)
                            else:
                                queue[0][1] -= take
                    state = after
            for first, n, used in state:
                plan.leave(capacity - used, first, n)
    rest: dict[int, int] = {n: c for n, c in counts.items() if n <= capacity * small}
    for queue in sized.values():
        for length, c in queue:
            rest[length] = rest.get(length, 0) + c
    for length in sorted(rest, reverse=True):
        plan.best_fit(length, rest[length])
    return plan


#: (share of the capacity up to which a length is small, number of groups) that are planned; the fewest sequences win.
SCHEMES = ((1 / 8, 20), (1 / 4, 10), (1 / 3, 10), (1 / 3, 40))


def place(cut: DataFrame, capacity: int = 4096, id_col: str = "doc_id", per_salt: int = 20_000) -> DataFrame:
    """Adds sequence_id and offset to pieces. Ranks within a length are counted in salted parts of about ``per_salt`` rows."""
    counts = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most ``capacity`` rows
    plan = min((plan_packing(counts, capacity, groups, small) for small, groups in SCHEMES), key=lambda p: p.sequences)
    runs = np.array(sorted(plan.runs), np.int64).reshape(-1, 5)
    shared = cut.sparkSession.sparkContext.broadcast((runs[:, 0] << 44 | runs[:, 1], runs))
    salts = F.create_map(*(x for n, c in counts.items() if c > per_salt for x in (F.lit(n), F.lit(math.ceil(c / per_salt)))) or (F.lit(-1), F.lit(1)))
    salted = cut.withColumn("salt", F.pmod(F.xxhash64(id_col, "piece", "ids_crc32"), F.coalesce(F.element_at(salts, F.col("length").cast("int")), F.lit(1))).cast("int"))
    base = salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("n"))
    base = base.select("length", "salt", (F.sum("n").over(Window.partitionBy("length").orderBy("salt")) - F.col("n")).alias("before"))
    order = Window.partitionBy("length", "salt").orderBy(id_col, "piece", "ids_crc32")
    ranked = salted.withColumn("rank", F.row_number().over(order)).join(base, ["length", "salt"]).withColumn("rank", F.col("rank") - 1 + F.col("before")).drop("before", "salt")
    names = ranked.columns

    def find(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, rows = shared.value
        for b in it:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            r = rows[np.searchsorted(keys, length << 44 | rank, "right") - 1]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(r[:, 3] + rank - r[:, 1]), pa.array(r[:, 4])], [*names, "sequence_id", "offset"])

    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ranked.schema)
    return ranked.mapInArrow(find, f"{kinds}, sequence_id long, offset long").drop("rank")


def pack(df: DataFrame, tokenizer_path: str, capacity: int = 4096, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """(id_col, piece, start, length, ids_crc32, sequence_id, offset) of every piece of every row.

    Null and empty texts are documents of the end id alone. Repeated rows are documents of their own. Null identifiers
    are kept. An empty table gives no rows. Only the two named columns are read.
    """
    cut = stage(pieces(df, tokenizer_path, capacity, id_col, text_col, with_ids), "pieces")
    out = place(cut, capacity, id_col)
    return out.select(id_col, "piece", "start", "length", "ids_crc32", "sequence_id", "offset", *(["ids"] if with_ids else []))


def sequences(placed: DataFrame) -> DataFrame:
    """(sequence_id, ids) with the pieces' ids in their places; a group holds at most ``capacity`` ids."""
    parts = placed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("parts"))
    return parts.select("sequence_id", F.flatten(F.transform("parts", lambda p: p["ids"])).alias("ids"))
