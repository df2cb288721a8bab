"""Schemas of provenance graphs, and the pair of DataFrames that is one."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NODES = "run_id long, node_id string, node_type string, kind string, label string, pid long, t_begin timestamp_ntz, t_end timestamp_ntz, size_bytes long, content_hash string, attrs map<string,string>"
EDGES = "run_id long, src string, dst string, label string, t_begin timestamp_ntz, t_end timestamp_ntz, n long"
ACCESS = "run_id long, seq long, ts timestamp_ntz, actor string, op string, object string, dur_us long"

ACTIVITY, ENTITY = "activity", "entity"
USED, GENERATED, INFORMED = "used", "wasGeneratedBy", "wasInformedBy"
#: The node types at the ends of a stored edge, dependent to dependee.
ENDS = {USED: (ACTIVITY, ENTITY), GENERATED: (ENTITY, ACTIVITY), INFORMED: (ACTIVITY, ACTIVITY)}
#: Audited label to stored label, and whether the ends change places.
TRACE_LABELS = {"read": (USED, True), "written": (GENERATED, True), "spawned": (INFORMED, True)}


@dataclass(frozen=True)
class ProvGraph:
    """Nodes and edges of one or many runs. Edges point from what depends to what it depends on."""

    nodes: DataFrame
    edges: DataFrame

    def run(self, run_id: int) -> ProvGraph:
        return ProvGraph(self.nodes.filter(F.col("run_id") == run_id), self.edges.filter(F.col("run_id") == run_id))


def nodes_of(df: DataFrame) -> DataFrame:
    """``df`` with the columns of NODES, nulls where it has none."""
    return _shaped(df, NODES)


def edges_of(df: DataFrame) -> DataFrame:
    return _shaped(df, EDGES)


def _shaped(df: DataFrame, ddl: str) -> DataFrame:
    cols = [c.split(" ", 1) for c in ddl.split(", ")]
    return df.select(*((F.col(n) if n in df.columns else F.lit(None)).cast(t).alias(n) for n, t in cols))
