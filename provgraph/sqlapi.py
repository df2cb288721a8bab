"""The methods by name from SQL: views, scalar functions and table functions for exploring small graphs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from provgraph.operators.content import cut_points
from provgraph.schema import ProvGraph


class ProvClosure:
    """(run_id, node_id, hops): what edges (run_id, src, dst) reach from a seed, for a table partitioned by run."""

    def __init__(self):
        self.next: dict[str, list[str]] = {}
        self.run, self.seed = None, None

    def eval(self, row, seed: str):
        self.run, self.seed = row["run_id"], seed
        self.next.setdefault(row["src"], []).append(row["dst"])

    def terminate(self):
        if self.run is None:
            return
        seen, front, hops = {self.seed}, [self.seed], 0
        while front:
            for v in front:
                yield self.run, v, hops
            front = sorted({w for v in front for w in self.next.get(v, [])} - seen)
            seen.update(front)
            hops += 1


class ProvChunks:
    """(ord, start, stop): content-defined chunks of a text, in bytes."""

    def eval(self, text: str, avg: int):
        at = 0
        for k, end in enumerate(cut_points((text or "").encode(), avg)):
            yield k, at, end
            at = end


@F.pandas_udf(T.IntegerType())
def rolling_cuts(text: pd.Series) -> pd.Series:
    """Number of content-defined chunks of each text."""
    return text.map(lambda t: len(cut_points((t or "").encode()))).astype("int32")


def multiset_udaf():
    """A grouped-aggregate twin of the built-in multiset hash, for comparison only."""

    @F.pandas_udf(T.StringType())
    def total(h: pd.Series) -> str:
        return str(sum(int(x) for x in h))

    return total


def register(spark: SparkSession, g: ProvGraph | None = None, accesses: DataFrame | None = None) -> None:
    """Views prov_nodes, prov_edges and prov_accesses; functions prov_label, short_path and crosses; table functions prov_closure and prov_chunks."""
    if g is not None:
        g.nodes.createOrReplaceTempView("prov_nodes")
        g.edges.createOrReplaceTempView("prov_edges")
    if accesses is not None:
        accesses.createOrReplaceTempView("prov_accesses")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION prov_label(op STRING) RETURNS STRING RETURN CASE op WHEN 'read' THEN 'used' WHEN 'written' THEN 'wasGeneratedBy' WHEN 'spawned' THEN 'wasInformedBy' END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION short_path(p STRING) RETURNS STRING RETURN substring_index(p, '/', -2)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION crosses(b TIMESTAMP_NTZ, e TIMESTAMP_NTZ) RETURNS BOOLEAN RETURN coalesce(b <= e, true)")
    spark.udtf.register("prov_closure", F.udtf(ProvClosure, returnType="run_id long, node_id string, hops int"))
    spark.udtf.register("prov_chunks", F.udtf(ProvChunks, returnType="ord int, start int, stop int"))
