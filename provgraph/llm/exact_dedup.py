"""Exact duplicates by a tree merge of sorted digest runs.

Each partition sorts its digests into runs, one per digest range. Runs of a range then meet in
binomial rounds (``fan_in`` 2; more make it k-nomial): source ``s`` goes to group ``s // fan_in`` until one run per range is left. A merge keeps,
for each verified digest, the identifier that stays, and how many rows share it. No task ever holds more than the
runs of one digest range, whose size follows ``rows_per_range`` whatever the copies do.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.llm.common import stage, whole_id

_RUN = "part int, src int, digests binary, checks binary, ids binary, uids binary, sizes binary"
_NONE = np.iinfo(np.int64).min  # stands for a null identifier; it loses to every other


def _fold(digests: np.ndarray, checks: np.ndarray, ids: np.ndarray, uids: np.ndarray, sizes: np.ndarray, largest: bool) -> list[np.ndarray]:
    """Sorted runs laid end to end -> one sorted run; equal digests fold only if their second digests agree as well."""
    order = np.lexsort((uids, ~ids if largest else np.where(ids == _NONE, np.iinfo(np.int64).max, ids), checks))
    order = order[np.argsort(digests[order], kind="stable")]
    d, c = digests[order], checks[order]
    new = np.concatenate(([True], (d[1:] != d[:-1]) | (c[1:] != c[:-1])))
    first = np.flatnonzero(new)
    return [d[first], c[first], ids[order][first], uids[order][first], np.add.reduceat(sizes[order], first)]


def _row(part: int, src: int, run: list[np.ndarray]) -> dict:
    return {"part": part, "src": src, "digests": run[0].tobytes(), "checks": run[1].tobytes(), "ids": run[2].tobytes(), "uids": run[3].tobytes(), "sizes": run[4].tobytes()}


_ARROW = pa.schema([("part", pa.int32()), ("src", pa.int32()), *((c, pa.binary()) for c in ("digests", "checks", "ids", "uids", "sizes"))])


def _leaf(parts: int, largest: bool, flush: int = 200_000):
    def runs(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def out() -> pa.RecordBatch:
            t = pa.Table.from_batches(held)
            d = np.frombuffer(b"".join(t.column("digest").to_pylist()), "S32")
            ids = t.column("id").fill_null(int(_NONE)).to_numpy()
            run = _fold(d, t.column("check").to_numpy(), np.maximum(ids, _NONE), t.column("uid").to_numpy(), np.ones(len(d), np.int64), largest)
            head = np.frombuffer(run[0].tobytes(), ">u4")[::8].astype(np.uint64)
            part = (head * np.uint64(parts) >> np.uint64(32)).astype(np.int64)
            cut = np.searchsorted(part, np.arange(parts + 1))
            src = t.column("src")[0].as_py()
            return pa.RecordBatch.from_pylist([_row(p, src, [x[cut[p] : cut[p + 1]] for x in run]) for p in range(parts) if cut[p + 1] > cut[p]], _ARROW)

        for b in it:
            if b.num_rows:
                held.append(b)
            if sum(x.num_rows for x in held) >= flush:
                yield out()
                held = []
        if held:
            yield out()

    return runs


def _unpack(t: pa.Table) -> list[np.ndarray]:
    kinds = (("digests", "S32"), ("checks", np.int64), ("ids", np.int64), ("uids", np.int64), ("sizes", np.int64))
    return [np.frombuffer(b"".join(t.column(c).to_pylist()), k) for c, k in kinds]


def _merge(fan_in: int, largest: bool):
    def merge(t: pa.Table) -> pa.Table:
        return pa.Table.from_pylist([_row(t.column("part")[0].as_py(), t.column("src")[0].as_py() // fan_in, _fold(*_unpack(t), largest))], _ARROW)

    return merge


def _groups(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in it:
        for i in range(b.num_rows):
            d, c, ids, uids, sizes = _unpack(pa.Table.from_batches([b.slice(i, 1)]))
            many = sizes > 1
            flat = d[many]
            raw = np.frombuffer(flat.tobytes(), np.uint8).reshape(-1, 32)
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes() for x in raw], pa.binary()), pa.array(c[many]), pa.array(ids[many], mask=ids[many] == _NONE), pa.array(uids[many]), pa.array(sizes[many])], ["digest", "check", "keep_id", "keep_uid", "group_size"])


def exact_dedup(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "largest", fan_in: int = 2, rows_per_range: int = 50_000) -> DataFrame:
    """One row per row of ``df``: (id_col, keep_id, group_size, kept, text_sha256).

    Identifiers are whole numbers of any width, else a TypeError. Null text counts as empty; a null identifier ranks below every other. Of rows that repeat both
    identifier and text exactly one is kept. Other columns, whatever their names, are not read. An empty table gives
    no rows. ``keep``: 'largest' or 'smallest' identifier. The second digest that confirms the
    first covers the text's length and another hash function.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = stage(
        df.select(whole_id(df, id_col).alias("id"), F.unhex(F.sha2(text, 256)).alias("digest"), F.xxhash64(F.octet_length(text), text).alias("check"))
        .withColumns({"uid": F.monotonically_increasing_id(), "src": F.spark_partition_id()}),
        "digests",
    )
    n, last = rows.agg(F.count(F.lit(1)), F.max("src")).first()
    largest, sources = keep == "largest", (last or 0) + 1
    parts = max(1, math.ceil(n / rows_per_range))
    runs = rows.mapInArrow(_leaf(parts, largest), _RUN)
    while sources > 1:
        runs = runs.groupBy("part", F.expr(f"src div {fan_in}").alias("to")).applyInArrow(_merge(fan_in, largest), _RUN)
        sources = math.ceil(sources / fan_in)
    # runs that one source flushed apart meet here if there was no round
    runs = runs if last else runs.groupBy("part").applyInArrow(_merge(fan_in, largest), _RUN)
    groups = runs.mapInArrow(_groups, "digest binary, check long, keep_id long, keep_uid long, group_size long")
    j = rows.join(groups, ["digest", "check"], "left")
    single, kind = F.col("group_size").isNull(), df.schema[id_col].dataType
    return j.select(
        F.col("id").cast(kind).alias(id_col),
        F.when(single, F.col("id")).otherwise(F.col("keep_id")).cast(kind).alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        (single | (F.col("uid") == F.col("keep_uid"))).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )
