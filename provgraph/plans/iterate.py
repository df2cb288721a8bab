"""Driver loops whose plans stay small: each round's state is written to the shared folder, and one number comes back."""

from __future__ import annotations

import atexit
import re
import tempfile
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

_MADE: list[tuple[SparkSession, str]] = []
_OWN: dict[str, str] = {}  # by application, where spark.checkpoint.dir is unset


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir. Where it is unset, a local folder of our own in local mode, else an error: executors would not share it."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        base = _OWN.get(spark.sparkContext.applicationId) or "file://" + tempfile.mkdtemp(prefix="rounds-")
        _OWN[spark.sparkContext.applicationId] = base
    return base.rstrip("/")


def materialize(df: DataFrame, label: str = "state") -> DataFrame:
    """Write and reread: no lineage beyond this point, and any executor may be lost afterwards."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path, compression="zstd")
    _MADE.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def _delete(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def drop(df: DataFrame) -> None:
    """Delete what ``materialize`` wrote for ``df``, which nothing reads any more."""
    mine = {f.rsplit("/", 1)[0] for f in df.inputFiles()}
    for made in [m for m in _MADE if any(x.endswith(m[1].split(":", 1)[-1].lstrip("/")) for x in mine)]:
        _delete(*made)
        _MADE.remove(made)


def release(spark: SparkSession) -> None:
    """Let the shuffle files of finished jobs go: Spark deletes them once the driver's collector has seen that nothing refers to them."""
    spark.sparkContext._jvm.System.gc()


def _clean() -> None:
    for spark, path in _MADE:
        try:
            if spark.sparkContext._jsc is not None:
                _delete(spark, path)
        except Exception:  # the session has ended
            return


atexit.register(_clean)


@dataclass
class Rounds:
    """What a loop did: (round, metric, seconds)."""

    log: list[tuple[int, int, float]] = field(default_factory=list)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.log or [], "round int, metric long, seconds double")


def fixpoint(state: DataFrame, step: Callable[[DataFrame, int], DataFrame], metric: Callable[[DataFrame], int], done: Callable[[int, int], bool], max_rounds: int | None = None, label: str = "state", rounds: Rounds | None = None) -> DataFrame:
    """Repeat ``step`` until ``done(metric before, metric after)`` or ``max_rounds``."""
    state = materialize(state, label)
    before, k = metric(state), 0
    while max_rounds is None or k < max_rounds:
        began, old = time.time(), state
        state = materialize(step(old, k), label)
        after, k = metric(state), k + 1
        drop(old)
        if rounds is not None:
            rounds.log.append((k, after, time.time() - began))
        if done(before, after):
            break
        before = after
    return state
