"""Contents of containers: hashes, validation irrespective of names, chunking, and the de-duplicated store."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def validate(a: DataFrame, b: DataFrame, key: str = "hash") -> DataFrame:
    """(run_id, key, status) of files (run_id, path, content_hash): 'matched', 'missing', 'extra' or, by path, 'changed'.

    By hash, contents are compared as multisets: the k-th copy of a content meets the k-th.
    """
    if key == "path":
        j = a.select("run_id", "path", F.col("content_hash").alias("x"), F.lit(1).alias("l")).join(b.select("run_id", "path", F.col("content_hash").alias("y"), F.lit(1).alias("r")), ["run_id", "path"], "full")
        status = F.when(F.col("r").isNull(), "missing").when(F.col("l").isNull(), "extra").when(F.col("x").eqNullSafe(F.col("y")), "matched").otherwise("changed")
        return j.select("run_id", F.col("path").alias("key"), status.alias("status"))
    x, y = (f.groupBy("run_id", "content_hash").agg(F.count(F.lit(1)).alias(n)) for f, n in ((a, "p"), (b, "q")))
    j = x.join(y, ["run_id", "content_hash"], "full").select("run_id", F.col("content_hash").alias("key"), F.coalesce("p", F.lit(0)).alias("p"), F.coalesce("q", F.lit(0)).alias("q"))
    many = F.flatten(F.array(F.array_repeat(F.lit("matched"), F.least("p", "q").cast("int")), F.array_repeat(F.lit("missing"), F.greatest(F.col("p") - F.col("q"), F.lit(0)).cast("int")), F.array_repeat(F.lit("extra"), F.greatest(F.col("q") - F.col("p"), F.lit(0)).cast("int"))))
    return j.select("run_id", "key", F.explode(many).alias("status"))


def dedup_files(files: DataFrame) -> DataFrame:
    """(file_id, content_hash, stored_as): the least file of each content stands for it."""
    f = files.select("file_id", F.sha2(F.coalesce("content", F.lit("")), 256).alias("content_hash"))
    return f.join(f.groupBy("content_hash").agg(F.min("file_id").alias("stored_as")), "content_hash").select("file_id", "content_hash", "stored_as")


def cut_points(data: bytes, avg: int = 1024, least: int = 256, most: int = 8192, window: int = 64) -> list[int]:
    """Ends of chunks: where the rolling hash of the last ``window`` bytes has its low bits set, not before ``least`` nor after ``most``."""
    buf, n = np.frombuffer(data, np.uint8).astype(np.uint64), len(data)
    if not n:
        return []
    table = np.random.Generator(np.random.PCG64(7)).integers(0, 2**63, 256, dtype=np.uint64)
    base = np.uint64(0x9E3779B97F4A7C15)
    with np.errstate(over="ignore"):
        h = np.zeros(n, np.uint64)
        vals = table[buf.astype(np.int64)]
        for j in range(min(window, n)):  # the byte j places back, weighed by base ** j
            h[j:] += vals[: n - j] * np.power(base, np.uint64(j), dtype=np.uint64)
    mask = np.uint64((1 << max(1, avg.bit_length() - 1)) - 1) << np.uint64(20)
    marks = np.flatnonzero((h & mask) == mask) + 1
    out, at = [], 0
    while at < n:
        k = int(np.searchsorted(marks, at + least))
        end = min(int(marks[k]) if k < len(marks) else n, at + most, n)
        out.append(end)
        at = end
    return out


def chunk(files: DataFrame, mode: str = "content", size: int = 1024, least: int = 256, most: int = 8192, window: int = 64) -> DataFrame:
    """(run_id, file_id, ord, chunk_hash, len, data) of files (run_id, file_id, content). An empty file has no chunk.

    'content': cut by a rolling hash over UTF-8 bytes; 'fixed': blocks of ``size`` characters; 'line': lines.
    """
    f = files.select("run_id", "file_id", F.coalesce("content", F.lit("")).alias("content"))
    if mode == "content":

        def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in it:
                rows = []
                for r, f, t in zip(b.column("run_id").to_pylist(), b.column("file_id").to_pylist(), b.column("content").to_pylist(), strict=True):
                    data, at = t.encode(), 0
                    for k, end in enumerate(cut_points(data, size, least, most, window)):
                        rows.append((r, f, k, hashlib.sha256(data[at:end]).hexdigest(), end - at, data[at:end]))
                        at = end
                cols = list(zip(*rows, strict=True)) or [()] * 6
                kinds = (b.schema.field("run_id").type, b.schema.field("file_id").type, pa.int32(), pa.string(), pa.int32(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["run_id", "file_id", "ord", "chunk_hash", "len", "data"])

        kinds = {c: f.schema[c].dataType.simpleString() for c in ("run_id", "file_id")}
        return f.mapInArrow(run, f"run_id {kinds['run_id']}, file_id {kinds['file_id']}, ord int, chunk_hash string, len int, data binary")
    if mode == "fixed":
        blocks = F.regexp_extract_all("content", F.lit(f"(?s).{{1,{size}}}"), F.lit(0))  # one pass; a substring each would start at the text's first character
        pieces = f.filter(F.length("content") > 0).select("run_id", "file_id", F.posexplode(blocks).alias("ord", "piece"))
    else:
        pieces = f.select("run_id", "file_id", F.posexplode(F.split("content", "\n")).alias("ord", "piece"))
    return pieces.select("run_id", "file_id", "ord", F.sha2("piece", 256).alias("chunk_hash"), F.length("piece").alias("len"), F.col("piece").cast("binary").alias("data"))


def store(chunks: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Unique chunks (chunk_hash, len, data) and recipes (run_id, file_id, ord, chunk_hash)."""
    unique = chunks.groupBy("chunk_hash").agg(F.first("len").alias("len"), F.first("data").alias("data"))
    return unique, chunks.select("run_id", "file_id", "ord", "chunk_hash")


def restore(unique: DataFrame, recipes: DataFrame, sep: str = "") -> DataFrame:
    """(run_id, file_id, content) from chunks and recipes; ``sep`` joins lines again. Bytes are joined before they are decoded."""
    parts = recipes.join(unique.select("chunk_hash", "data"), "chunk_hash").groupBy("run_id", "file_id").agg(F.array_sort(F.collect_list(F.struct("ord", F.hex("data").alias("x")))).alias("p"))
    glue = F.hex(F.lit(sep)) if sep else F.lit("")
    joined = F.array_join(F.transform("p", lambda x: x["x"]), "") if not sep else F.concat_ws("", F.flatten(F.transform("p", lambda x: F.array(glue, x["x"]))))
    text = F.decode(F.unhex(joined if not sep else F.expr("substring(g, 1 + 2 * %d)" % len(sep.encode()))), "UTF-8")
    return parts.withColumn("g", joined).select("run_id", "file_id", text.alias("content"))


def ingest(known: DataFrame, chunks: DataFrame) -> DataFrame:
    """Chunks of a new run that the store (chunk_hash) does not have yet, each once."""
    return chunks.join(known.select("chunk_hash"), "chunk_hash", "left_anti").dropDuplicates(["chunk_hash"])


def dedup_ratio(chunks: DataFrame) -> DataFrame:
    """(chunks, unique_chunks, total_len, kept_len, ratio)."""
    c = chunks.groupBy("chunk_hash").agg(F.count(F.lit(1)).alias("n"), F.first("len").alias("len"))
    t = c.agg(F.sum("n").alias("chunks"), F.count(F.lit(1)).alias("unique_chunks"), F.sum(F.col("n") * F.col("len")).alias("total_len"), F.sum("len").cast("long").alias("kept_len"))
    return t.withColumn("ratio", F.round(1 - F.col("kept_len") / F.col("total_len"), 6))


def copies(files: DataFrame) -> DataFrame:
    """(file_id, content_hash, copy_no): the copies of each content in order."""
    f = files.select("file_id", F.sha2(F.coalesce("content", F.lit("")), 256).alias("content_hash"))
    return f.withColumn("copy_no", F.row_number().over(Window.partitionBy("content_hash").orderBy("file_id")))
