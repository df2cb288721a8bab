"""Shared plumbing: table access, intermediate tables in the shared folder, connected components."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

_MADE: list[tuple[SparkSession, str]] = []
_OWN: dict[str, str] = {}  # by application, where spark.checkpoint.dir is unset


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir. Where it is unset, a local one in local mode, else an error."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = _OWN.get(spark.sparkContext.applicationId) or "file://" + tempfile.mkdtemp(prefix="shared-")
        _OWN[spark.sparkContext.applicationId] = base
    return base.rstrip("/")


def stage(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _MADE.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Lets Spark hand rows to Python ``rows`` at a time, unless the session says otherwise than its default of 10000: texts and sets
    of that many rows would be held several times over, on both sides."""
    if spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000":
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(rows))


def made() -> int:
    """How many tables have been staged so far."""
    return len(_MADE)


def discard(mark: int) -> None:
    """Deletes the tables staged since ``made()`` said ``mark``, when what was computed from them has been written."""
    while len(_MADE) > mark:
        remove(*_MADE.pop())


def whole_id(df: DataFrame, name: str) -> Column:
    """The identifier column as long; others than whole numbers are refused, as ranges and packed arrays need longs."""
    if not isinstance(df.schema[name].dataType, IntegralType):
        raise TypeError(f"{name}: identifiers must be whole numbers, not {df.schema[name].dataType.simpleString()}")
    return F.col(name).cast("long")


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder of the shared file system."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def _clean() -> None:
    for spark, path in _MADE:
        try:
            if spark.sparkContext._jsc is not None:
                remove(spark, path)
        except Exception:  # the session has ended: nothing left to ask
            return


atexit.register(_clean)


def components(edges: DataFrame, small: int = 500_000) -> DataFrame:
    """(node, root) for the nodes of ``edges(u, v)`` longs; root is the smallest node of the component.

    Alternates the large-star and small-star contractions; each is a grouped minimum and a
    join, so a hub needs no list of its neighbours. State is written to the shared folder each round until it stays the same. With at
    most ``small`` edges, counted, the minima are broadcast instead of shuffled.
    """
    edges = stage(edges.select("u", "v").filter("u <> v").distinct(), "cc")
    few = edges.count() <= small

    def both(e: DataFrame) -> DataFrame:
        return e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))

    def star(nb: DataFrame, large: bool) -> DataFrame:
        side = nb if large else nb.filter("v < u")
        low = side.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        j = side.join(F.broadcast(low) if few else low, "u")
        out = j.filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")) if large else j.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        return out.filter("u <> v")

    nodes = both(edges).select(F.col("u").alias("node")).distinct()
    e, seen = edges, None
    while True:  # to the fixpoint: links only move to smaller nodes, so it is reached
        new = star(both(star(both(e), True)), False).distinct()
        e = stage(new.coalesce(4) if few else new, "cc")
        key = e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
        if key == seen:
            break
        seen = key
    root = e.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("root"))
    return nodes.join(root, "node", "left").select("node", F.coalesce("root", "node").alias("root"))
