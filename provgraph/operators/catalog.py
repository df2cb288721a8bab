"""The run store: namespaces, runs with increasing numbers, listing, export by token, and repeats of stored runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.operators import replay
from provgraph.schema import EDGES, ENTITY, NODES, ProvGraph


BLOCK = 1000


class Catalog:
    """Runs under a folder, as Parquet partitioned by namespace and block of ``BLOCK`` runs."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _read(self, what: str) -> DataFrame:
        jvm, p = self.spark.sparkContext._jvm, f"{self.path}/{what}"
        at = jvm.org.apache.hadoop.fs.Path(p)
        ddl = (NODES if what == "nodes" else EDGES) + ", ns string, block long"
        if not at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(at):
            return self.spark.createDataFrame([], ddl)
        return self.spark.read.schema(ddl).parquet(p)

    def last(self, ns: str) -> int:
        """The namespace's last run, -1 if it has none."""
        r = self._read("nodes").filter(F.col("ns") == ns).agg(F.max("run_id")).first()[0]
        return -1 if r is None else r

    def record(self, ns: str, g: ProvGraph) -> int:
        """Stores a graph as the namespace's next run and returns its number."""
        run = self.last(ns) + 1
        self._write(ns, ProvGraph(*(x.withColumn("run_id", F.lit(run).cast("long")) for x in (g.nodes, g.edges))))
        return run

    def record_all(self, ns: str, g: ProvGraph) -> int:
        """Stores every run of a graph, its number added to the first free one, by one job; returns the last run's number."""
        base = self.last(ns) + 1
        self._write(ns, ProvGraph(*(x.withColumn("run_id", F.col("run_id") + base) for x in (g.nodes, g.edges))))
        return self.last(ns)

    def _write(self, ns: str, g: ProvGraph) -> None:
        for what in ("edges", "nodes"):  # the nodes, by which runs are listed, come last
            df = getattr(g, what).withColumns({"ns": F.lit(ns), "block": F.expr(f"run_id div {BLOCK}")})
            df.write.mode("append").partitionBy("ns", "block").parquet(f"{self.path}/{what}")

    def list(self) -> DataFrame:
        """(ns, run_id, nodes, begun)."""
        return self._read("nodes").groupBy("ns", "run_id").agg(F.count(F.lit(1)).alias("nodes"), F.min("t_begin").alias("begun"))

    def show(self, ns: str, run: int | None = None) -> ProvGraph:
        """A stored run, the last by default."""
        run = self.last(ns) if run is None else run
        own = (F.col("ns") == ns) & (F.col("block") == run // BLOCK) & (F.col("run_id") == run)
        return ProvGraph(*(self._read(x).filter(own).drop("ns", "block") for x in ("nodes", "edges")))

    def repeat(self, ns: str, run: int | None = None, procs: list[str] | None = None, given: list[str] | dict[str, str] | None = None) -> DataFrame:
        """What a repeat does: with ``given`` inputs, the actions of a modified repeat; with ``procs``, the sub-container's nodes; else every node.

        ``given`` names changed inputs, or maps inputs to the files that take their place: these bear the action 'given', beside the
        inputs that they replace. An input that the run does not have is refused.
        """
        g = self.show(ns, run)
        if given:
            old = sorted(given)
            found = {r[0] for r in g.nodes.filter(F.col("node_id").isin(old)).select("node_id").distinct().collect()}  # at most as many as are given
            if missing := [x for x in old if x not in found]:
                raise ValueError(f"no inputs of this run: {', '.join(missing)}")
            seeds = g.nodes.filter(F.col("node_id").isin(old)).select("run_id", "node_id")
            out = replay.modified(g, seeds)
            if isinstance(given, dict):
                put = F.create_map(*(F.lit(x) for pair in sorted(given.items()) for x in pair))
                out = out.unionByName(seeds.select("run_id", F.element_at(put, F.col("node_id")).alias("node_id"), F.lit(ENTITY).alias("node_type"), F.lit("given").alias("action")))
            return out
        sub = replay.sub_container(g, replay.select(g, ids=procs)) if procs else g
        return sub.nodes.select("run_id", "node_id", "node_type", F.lit("rerun").alias("action"))

    def token(self, ns: str, run: int) -> str:
        """A digest of the run's nodes and edges, whatever their order and partitions."""
        g = self.show(ns, run)
        sums = [x.agg(F.count(F.lit(1)), *(F.sum(F.xxhash64(F.lit(s), *cols).cast("decimal(20,0)")) for s in (1, 2))).first() for x, cols in ((g.nodes, ("node_id", "node_type")), (g.edges, ("src", "dst", "label")))]
        import hashlib

        return hashlib.sha256(repr([tuple(map(str, r)) for r in sums]).encode()).hexdigest()[:16]

    def export(self, ns: str, run: int, path: str) -> str:
        """Copies a run to a folder named by its token; returns the token."""
        token, g = self.token(ns, run), self.show(ns, run)
        for what in ("nodes", "edges"):
            getattr(g, what).write.mode("overwrite").parquet(f"{path}/{token}/{what}")
        return token

    @staticmethod
    def open(spark: SparkSession, path: str, token: str) -> ProvGraph:
        return ProvGraph(spark.read.schema(NODES).parquet(f"{path}/{token}/nodes"), spark.read.schema(EDGES).parquet(f"{path}/{token}/edges"))
