"""One entry to all summarizations, with one shape of result."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.operators import collapse, grouping
from provgraph.schema import ProvGraph

GROUPINGS = {"ancestry": grouping.ancestry, "ancestry_degree": grouping.ancestry_degree, "relationship": grouping.relationship, "attributes": grouping.by_attributes}
METHODS = ("collapse", *GROUPINGS)


def summarize(g: ProvGraph, method: str = "collapse", **how) -> tuple[DataFrame, DataFrame]:
    """Nodes (run_id, group_id, node_type, size) and edges (run_id, src, dst, label, n) of the summary by one of METHODS.

    ``how`` goes to the method. A composite of the collapsing counts all nodes that were merged into it, over all steps, and edges
    inside it are gone; groupings keep them as loops.
    """
    if method in GROUPINGS:
        return grouping.summary_graph(g, GROUPINGS[method](g, **how))
    if method != "collapse":
        raise ValueError(f"no summarization {method!r}; there are {', '.join(METHODS)}")
    q, merges = collapse.summarize(g, **how)
    inside = collapse.resolve(merges).groupBy("run_id", "group_id").agg(F.count(F.lit(1)).alias("merged"))
    nodes = q.nodes.select("run_id", F.col("node_id").alias("group_id"), "node_type").join(inside, ["run_id", "group_id"], "left")
    return nodes.select("run_id", "group_id", "node_type", (1 + F.coalesce("merged", F.lit(0))).alias("size")), q.edges.select("run_id", "src", "dst", "label", "n")
