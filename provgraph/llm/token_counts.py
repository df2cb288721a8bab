"""Token counts that follow edits.

A text is cut into segments of white space and what follows it up to the next white space. No pre-token of the tokenizer
reaches from a visible character into white space after it, so a segment's tokens do not depend on its neighbours.
The leaves of a document's tree are runs of segments, and an inner node has the sum of its children.
An edit re-encodes the leaves that it touches and, as context, what the boundary needs: the segment that begins
before the edit and the one that ends after it. Sums on the paths to the root are updated.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.wordkernel import batches

_SEGMENT = re.compile(r"\s*\S+|\s+")


class SegmentCounter:
    """Number of tokens of a segment; those seen are remembered, up to ``most``."""

    def __init__(self, path: str, pattern: str, most: int = 400_000):
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.encoding = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.known: dict[str, int] = {}
        self.most, self.asked = most, 0

    def __call__(self, segments: Iterable[str]) -> list[int]:
        segments = list(segments)
        self.asked += len(segments)
        if len(self.known) > self.most:
            self.known.clear()
        new = [s for s in dict.fromkeys(segments) if s not in self.known]
        if new:
            self.known.update(zip(new, map(len, map(self.encoding.encode_ordinary, new)), strict=True))
        return [self.known[s] for s in segments]


class CountTree:
    """Segment tree over runs of about ``leaf`` segments; a Fenwick layout holds the sums of tokens and of characters."""

    def __init__(self, text: str, count: Callable[[Iterable[str]], list[int]], leaf: int = 64):
        self.count, self.leaf = count, leaf
        segments = _SEGMENT.findall(text)
        self.segments = len(segments)
        self._build(self._leaves(segments))

    def _leaves(self, segments: list[str]) -> list[tuple[str, int]]:
        sizes = self.count(segments)
        return [("".join(segments[a : a + self.leaf]), sum(sizes[a : a + self.leaf])) for a in range(0, len(segments), self.leaf)]

    def _build(self, leaves: list[tuple[str, int]]) -> None:
        self.leaves = leaves
        n = 1
        while n < len(leaves):
            n *= 2
        self.size, self.tree = n, [(0, 0)] * (2 * n)
        self.tree[n : n + len(leaves)] = [(len(t), c) for t, c in leaves]
        for i in range(n - 1, 0, -1):
            a, b = self.tree[2 * i], self.tree[2 * i + 1]
            self.tree[i] = (a[0] + b[0], a[1] + b[1])

    @property
    def tokens(self) -> int:
        return self.tree[1][1]

    @property
    def chars(self) -> int:
        return self.tree[1][0]

    @property
    def text(self) -> str:
        return "".join(t for t, _ in self.leaves)

    def _find(self, at: int) -> tuple[int, int]:
        """The leaf that holds character ``at`` and the offset in it."""
        i = 1
        while i < self.size:
            i *= 2
            if at >= self.tree[i][0]:
                at -= self.tree[i][0]
                i += 1
        return i - self.size, at

    def edit(self, start: int, end: int, new: str) -> int:
        """Replace characters ``start`` to ``end``; returns how many segments were encoded again."""
        start, end = max(0, min(start, self.chars)), max(0, min(end, self.chars))
        end = max(start, end)
        if not self.leaves:
            self._build(self._leaves(segments := _SEGMENT.findall(new)))
            return len(segments)
        # one character of context on each side: a segment goes on if it and its neighbour are both visible
        first, a = self._find(max(0, start - 1))
        last, _ = self._find(min(end, self.chars - 1))
        before = self.leaves[first - 1][0] if first else ""
        a += start - max(0, start - 1)
        middle = "".join(t for t, _ in self.leaves[first : last + 1])
        z = a + end - start
        changed = middle[:a] + new + middle[z:]
        if before and changed and not changed[0].isspace() or before and not changed:
            first -= 1
            changed = before + changed
        if last + 1 < len(self.leaves) and changed and changed[-1].isspace() | (not self.leaves[last + 1][0][0].isspace()):
            last += 1
            changed += self.leaves[last][0]
        segments = _SEGMENT.findall(changed)
        leaves = self._leaves(segments)
        if len(leaves) == last - first + 1:
            for k, (t, c) in enumerate(leaves):
                i = self.size + first + k
                self.leaves[first + k], self.tree[i] = (t, c), (len(t), c)
                while i > 1:
                    i //= 2
                    x, y = self.tree[2 * i], self.tree[2 * i + 1]
                    self.tree[i] = (x[0] + y[0], x[1] + y[1])
        else:
            self._build(self.leaves[:first] + leaves + self.leaves[last + 1 :])
        return len(segments)


def count_tokens(df: DataFrame, tokenizer_path: str, pattern: str, edits_col: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id_col, n_segments, n_tokens, n_tokens_edited, n_reencoded) of each row.

    ``edits_col``: array<struct<start:int,stop:int,new:string>>, applied one after the other, each in the coordinates that
    the ones before it left, clipped to the text; null or no column: no edits. Null text counts as empty, null ``new``
    as a deletion. Repeated rows are counted each on their own.
    """

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = SegmentCounter(tokenizer_path, pattern)
        for b, texts in batches(it, "t"):
            rows = []
            for raw, edits in zip(texts, b.column("e").to_pylist(), strict=True):
                tree = CountTree(raw.decode("utf-8", "replace"), counter)
                before, n, again = tree.tokens, tree.segments, 0
                for e in edits or []:
                    if e is not None:
                        again += tree.edit(e["start"] or 0, e["stop"] or 0, e["new"] or "")
                rows.append((n, before, tree.tokens, again))
            yield pa.RecordBatch.from_arrays([b.column("i"), *(pa.array(c, pa.int64()) for c in zip(*rows, strict=True))], [id_col, "n_segments", "n_tokens", "n_tokens_edited", "n_reencoded"])

    kind = df.schema[id_col].dataType.simpleString()
    edits = F.col(edits_col) if edits_col else F.lit(None).cast("array<struct<start:int,stop:int,new:string>>")
    return df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"), edits.alias("e")).mapInArrow(run, f"`{id_col}` {kind}, n_segments long, n_tokens long, n_tokens_edited long, n_reencoded long")


def stated_edits(text_col: str = "text"):
    """Three edits that depend on the text alone: a word inserted in the middle, the first tenth deleted, a line appended."""
    n = F.coalesce(F.length(text_col), F.lit(0))
    kind = "array<struct<start:int,stop:int,new:string>>"
    return F.array(
        F.struct((n / 2).cast("int").alias("start"), (n / 2).cast("int").alias("stop"), F.lit("edited ").alias("new")),
        F.struct(F.lit(0).alias("start"), (n / 10).cast("int").alias("stop"), F.lit("").alias("new")),
        F.struct((n + 7 - (n / 10).cast("int")).cast("int").alias("start"), (n + 7 - (n / 10).cast("int")).cast("int").alias("stop"), F.lit("\nThe end.").alias("new")),
    ).cast(kind)
