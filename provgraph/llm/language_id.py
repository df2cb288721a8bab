"""Language identification with blended-spectrum presence kernels.

k(x, z) counts the character n-grams (1 to ``orders``) present in both texts, divided by the geometric mean of
k(x, x) and k(z, z). A bounded sample of labelled rows gives landmarks and training rows; the Nyström map
K(x, L) K(L, L)^(-1/2) embeds a text, and one ridge regression per language (target 1 for its own rows, 0 for the rest)
scores it. Presence kernels are linear in the presence vector, so scoring a batch is one product of the presence matrix
with the folded weights, each row divided by sqrt(k(x, x)).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.llm.wordkernel import batches

OTHERS = 8  # codes 1 to 8: letters outside the alphabet, by blocks of 128 code points; 0: between words
_KNOWN = 0x30000  # code points below this are told apart


@dataclass
class KernelModel:
    alphabet: str
    labels: list[str]
    cells: np.ndarray  # the n-gram cells that occur in a landmark, ascending
    weights: np.ndarray  # one row per such cell, one column per label
    orders: int


def _codes(text: str, lut: np.ndarray) -> np.ndarray:
    c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    return lut[np.minimum(c, len(lut) - 1)]


@cache
def _lut(alphabet: str) -> np.ndarray:
    lut = np.zeros(_KNOWN + 1, np.int32)
    for i in range(_KNOWN):
        if chr(i).isalpha():
            lut[i] = 1 + (i >> 7) * 5 % OTHERS
    for i, ch in enumerate(alphabet):
        for x in {ch, ch.upper()}:
            if len(x) == 1 and ord(x) < _KNOWN:
                lut[ord(x)] = i + 1 + OTHERS
    lut[-1] = 1  # all higher code points
    return lut


def _cells(codes: np.ndarray, size: int, orders: int, mark: np.ndarray) -> np.ndarray:
    """Cells of the n-grams present, in ascending order. ``mark``: a scratch array of zeros, left as such."""
    at, grams = 0, codes
    for n in range(1, orders + 1):
        if n > 1:
            if len(codes) < n:
                break
            grams = grams[:-1] * size + codes[n - 1 :]
        mark[at + grams] = 1
        at += size**n
    found = np.flatnonzero(mark)
    mark[found] = 0
    return found


def _width(size: int, orders: int) -> int:
    return sum(size**n for n in range(1, orders + 1))


def _places(vocabulary: np.ndarray, width: int) -> np.ndarray:
    """Column of each cell; cells that no landmark has share a last column, whose weight is none."""
    place = np.full(width, len(vocabulary), np.int32)
    place[vocabulary] = np.arange(len(vocabulary))
    return place


def _presence(cells: list[np.ndarray], place: np.ndarray, columns: int) -> np.ndarray:
    """Presence rows divided by sqrt(k(x, x)), which counts all of a text's n-grams, also those of no landmark."""
    m = np.zeros((len(cells), columns + 1), np.float32)
    for r, c in enumerate(cells):
        if len(c):
            m[r, place[c]] = 1 / np.sqrt(len(c))
    return m[:, :columns]


def sample(df: DataFrame, label_col: str, text_col: str, id_col: str, per_label: int, most: int) -> list[tuple[str, str]]:
    """At most ``per_label`` (and in all ``most``) different labelled rows, those with the least hash of identifier and text.

    Rows that agree in these count once, however often they come, so that no more than ``most`` reach the driver.
    """
    have = df.filter(F.col(label_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(label_col).alias("y"), F.col(text_col).alias("t"), F.xxhash64(id_col, text_col).alias("h"))
    counts = {r["y"]: r["n"] for r in have.groupBy("y").agg(F.approx_count_distinct("h").alias("n")).orderBy(F.desc("n"), "y").limit(most).collect()}
    if not counts:
        return []
    want = max(1, min(per_label, most // len(counts)))
    # half as many again as wanted, and as the count may be wrong by; the rank then cuts
    share = F.create_map(*(x for y, n in counts.items() for x in (F.lit(y), F.lit(min(1.0, 1.8 * (want + 20) / max(n, 1))))))
    draw = F.pmod("h", F.lit(1 << 40)) / F.lit(float(1 << 40))
    drawn = have.filter(draw < F.coalesce(F.element_at(share, F.col("y")), F.lit(0.0))).groupBy("y", "h").agg(F.first("t").alias("t"))
    turn = F.row_number().over(Window.partitionBy("y").orderBy("h"))
    got = drawn.withColumn("turn", turn).filter(F.col("turn") <= want).collect()
    return [(r["y"], r["t"]) for r in sorted(got, key=lambda r: (r["y"], r["h"]))]


def fit(rows: list[tuple[str, str]], orders: int = 3, landmarks: int = 400, ridge: float = 1e-2, letters: int = 55) -> KernelModel:
    """``rows``: (label, text). Landmarks are taken evenly from the labels' rows.

    The ``letters`` that most rows have are told apart; further ones, as those of large scripts, by their blocks of code points alone.
    """
    labels = sorted({y for y, _ in rows})
    seen: dict[str, int] = {}
    for _, t in rows:
        for ch in set(t.lower()):
            if ch.isalpha() and ord(ch) < _KNOWN:
                seen[ch] = seen.get(ch, 0) + 1
    alphabet = "".join(sorted(sorted(seen, key=lambda ch: (-seen[ch], ch))[:letters]))
    size = len(alphabet) + 1 + OTHERS
    if not labels:
        return KernelModel("", [], np.zeros(0, np.int64), np.zeros((0, 0), np.float32), orders)
    lut, width = _lut(alphabet), _width(size, orders)
    mark = np.zeros(width, np.uint8)
    cells = [_cells(_codes(t, lut), size, orders, mark) for _, t in rows]
    every = max(1, len(rows) // landmarks)
    chosen = [i for y in labels for i in [j for j, (z, _) in enumerate(rows) if z == y][:: every]]

    vocabulary = np.unique(np.concatenate([cells[i] for i in chosen]))
    place = _places(vocabulary, width)

    def presence(idx: list[int]) -> np.ndarray:
        return _presence([cells[i] for i in idx], place, len(vocabulary))

    zl = presence(chosen)
    vals, vecs = np.linalg.eigh((zl @ zl.T).astype(np.float64))
    good = vals > 1e-6 * max(vals.max(), 1e-12)
    root = vecs[:, good] / np.sqrt(vals[good])  # K(L, L)^(-1/2)
    phi = np.vstack([presence(list(range(a, min(a + 64, len(rows))))) @ zl.T for a in range(0, len(rows), 64)]).astype(np.float64) @ root
    y = np.array([[float(z == lab) for lab in labels] for z, _ in rows])
    w = np.linalg.solve(phi.T @ phi + ridge * np.eye(phi.shape[1]), phi.T @ y)
    return KernelModel(alphabet, labels, vocabulary, (zl.T.astype(np.float64) @ (root @ w)).astype(np.float32), orders)


def predict(texts: list[str | None], model: KernelModel, block: int = 64) -> list[tuple[str, float]]:
    """(label or 'und', score in [0, 1]) of each text; the score is the winner's share after a softmax of the regressions."""
    lut, size = _lut(model.alphabet), len(model.alphabet) + 1 + OTHERS
    width = _width(size, model.orders)
    mark, place, out = np.zeros(width, np.uint8), _places(model.cells, width), []
    for a in range(0, len(texts), block):
        part = texts[a : a + block]
        cells, known = [np.zeros(0, np.int64)] * len(part), np.zeros(len(part), bool)
        for i, t in enumerate(part):
            if t:
                codes = _codes(t, lut)
                known[i] = bool(codes.any()) and (codes.max() > 1 or any(ch.isalpha() for ch in t))
                cells[i] = _cells(codes, size, model.orders, mark)
        if not model.labels:
            out += [("und", 0.0)] * len(part)
            continue
        s = np.exp(8 * (_presence(cells, place, len(model.cells)) @ model.weights).astype(np.float64).clip(-2, 2))
        s /= s.sum(1, keepdims=True)
        best = s.argmax(1)
        out += [(model.labels[b], float(s[i, b])) if known[i] else ("und", 0.0) for i, b in enumerate(best)]
    return out


def classify(df: DataFrame, model: KernelModel, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(id_col, lang_pred, score) of each row. Null or letterless text gives ('und', 0). Only these two columns are read."""
    shared = df.sparkSession.sparkContext.broadcast(model)  # at most a few MB: cells x labels of the sample's bound

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, "t"):
            got = predict([t.decode("utf-8", "replace") for t in texts], shared.value)
            yield pa.RecordBatch.from_arrays([b.column("i"), pa.array([x for x, _ in got], pa.string()), pa.array([s for _, s in got], pa.float64())], [id_col, "lang_pred", "score"])

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(run, f"`{id_col}` {kind}, lang_pred string, score double")


def keep_identified(df: DataFrame, model: KernelModel, text_col: str = "text") -> DataFrame:
    """The rows of ``df`` whose language can be told; null and letterless texts, and all if no language is known, are rejected."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, texts in batches(it, text_col):
            yield b.filter(pa.array([x != "und" for x, _ in predict([t.decode("utf-8", "replace") for t in texts], shared.value)]))

    return df.mapInArrow(run, df.schema)


def fitted(df: DataFrame, per_label: int = 300, most: int = 3000, orders: int = 3, landmarks: int = 400, ridge: float = 1e-2) -> KernelModel:
    """A model of at most ``per_label`` rows of each language and ``most`` in all, none of them held out."""
    return fit(sample(df.filter(~held_out()), "lang", "text", "doc_id", per_label, most), orders, landmarks, ridge)


def held_out(id_col: str = "doc_id"):
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(3)) == 1


def language_id(df: DataFrame, **bounds: float) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of each row.

    Fitted by ``fitted``, whose parameters ``bounds`` may set, never on the third of the identifiers set aside. Null
    identifiers count as the empty string in that choice. Repeated rows are predicted each on its own and alike. With no
    labelled row every text is 'und'.
    """
    return classify(df, fitted(df, **bounds)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
