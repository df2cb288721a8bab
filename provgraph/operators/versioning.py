"""Overwrite hazards and file versions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from provgraph.operators import reach
from provgraph.schema import ENTITY, GENERATED, INFORMED, USED, ProvGraph, edges_of


#: Readers or writers of a file that meet in one task as a group, writers in one array, and tasks that make pairs for each shuffle partition.
GROUP, ARRAY, SPREAD = 4096, 512, 4


def hazards(g: ProvGraph) -> DataFrame:
    """(run_id, reader, file, writer): ``writer`` last begins a write of ``file`` after ``reader`` first began to read it.

    One sort of each file numbers its writers from the latest on and tells each reader how many of them are later: those with the
    lowest numbers. Groups of readers meet groups of writers, so that many tasks make the pairs of one file; writers travel in arrays.
    """
    used, parts = F.col("label") == USED, SPREAD * int(g.edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    acc = g.edges.filter(F.col("label").isin(USED, GENERATED)).select("run_id", F.when(used, F.col("dst")).otherwise(F.col("src")).alias("file"), F.when(used, F.col("src")).otherwise(F.col("dst")).alias("p"), (~used).cast("int").alias("write"), "t_begin")
    acc = acc.groupBy("run_id", "file", "p", "write").agg(F.when(F.col("write") == 0, F.min("t_begin")).otherwise(F.max("t_begin")).alias("t")).dropna()
    order = Window.partitionBy("run_id", "file").orderBy("t", F.col("write").desc(), "p")  # of one time, writes come first: they are not later
    seen, whole = order.rowsBetween(Window.unboundedPreceding, 0), order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    # later: the writers after a row, which is a writer's number; earlier: the readers up to it, which is a reader's number
    acc = acc.select("run_id", "file", "p", "write", (F.sum("write").over(whole) - F.sum("write").over(seen)).alias("later"), F.sum(1 - F.col("write")).over(seen).alias("earlier"))
    group = lambda n: F.floor(n / GROUP).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), group(n - 1)))
    readers = acc.filter("write = 0 and later > 0").select("run_id", "file", group(F.col("earlier") - 1).alias("rs"), every(F.col("later")).alias("ws"), F.col("p").alias("reader"), "later")
    named = F.transform(F.array_sort(F.collect_list(F.struct("later", "p"))), lambda x: x["p"])
    arrays = acc.filter("write = 1 and earlier > 0").groupBy("run_id", "file", F.floor(F.col("later") / ARRAY).alias("k")).agg(F.max("earlier").alias("earlier"), F.min("later").alias("first"), named.alias("writers"))
    arrays = arrays.select("run_id", "file", every(F.col("earlier")).alias("rs"), group(F.col("first")).alias("ws"), "first", "writers")
    keys = ["run_id", "file", "rs", "ws"]
    met = readers.repartition(parts, *keys).join(arrays.repartition(parts, *keys), keys).filter("first < later")
    pairs = met.select("run_id", "reader", "file", (F.col("later") - F.col("first")).alias("most"), F.posexplode("writers").alias("i", "writer"))
    return pairs.filter("i < most and reader <> writer").select("run_id", "reader", "file", "writer")


def hazard_counts(g: ProvGraph) -> DataFrame:
    """(run_id, file, n): the number of hazards of each file, by one sorted pass and without pairs."""
    r = g.edges.filter(F.col("label") == USED).groupBy("run_id", F.col("dst").alias("file"), F.col("src").alias("p")).agg(F.min("t_begin").alias("t"))
    w = g.edges.filter(F.col("label") == GENERATED).groupBy("run_id", F.col("src").alias("file"), F.col("dst").alias("p")).agg(F.max("t_begin").alias("t"))
    return counts_of(r, w)


def counts_of(r: DataFrame, w: DataFrame) -> DataFrame:
    """The same from first reads and last writes (run_id, file, p, t), one row per process and file in each."""
    both = r.withColumn("write", F.lit(0)).unionByName(w.withColumn("write", F.lit(1)))
    after = Window.partitionBy("run_id", "file").orderBy(F.col("t").desc()).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    later = F.sum("write").over(after) - F.sum("write").over(Window.partitionBy("run_id", "file", "t"))
    counted = both.withColumn("later", later).filter("write = 0").groupBy("run_id", "file").agg(F.sum("later").alias("n"))
    own = r.alias("r").join(w.alias("w"), ["run_id", "file", "p"]).filter("w.t > r.t").groupBy("run_id", "file").agg(F.count(F.lit(1)).alias("own"))
    return counted.join(own, ["run_id", "file"], "left").select("run_id", "file", (F.col("n") - F.coalesce("own", F.lit(0))).alias("n")).filter("n > 0")


def bind(g: ProvGraph) -> DataFrame:
    """(run_id, process, file, label, t_begin, t_end, n, version) of every access.

    The k-th write of a file makes version k; a read sees the version of the writes that began strictly before it.
    """
    acc = g.edges.filter(F.col("label").isin(USED, GENERATED))
    write = F.col("label") == GENERATED
    acc = acc.select("run_id", F.when(write, F.col("dst")).otherwise(F.col("src")).alias("process"), F.when(write, F.col("src")).otherwise(F.col("dst")).alias("file"), "label", "t_begin", "t_end", "n", write.cast("int").alias("w"))
    order = Window.partitionBy("run_id", "file").orderBy("t_begin", "w", "process", "t_end").rowsBetween(Window.unboundedPreceding, 0)
    return acc.withColumn("version", F.sum("w").over(order)).drop("w")


def version_files(g: ProvGraph, scope: str = "all", drop_readback: bool = False) -> ProvGraph:
    """Files replaced by their versions ``file#k``; version 0 is the initial content.

    ``scope='hazard'`` versions only files with a hazard. ``drop_readback`` leaves out a process's reads of a version that
    it wrote itself.
    """
    b = bind(g)
    if drop_readback:
        own = b.filter(F.col("label") == GENERATED).select("run_id", "file", "process", "version").distinct()
        b = b.filter(F.col("label") == GENERATED).unionByName(b.filter(F.col("label") == USED).join(own, ["run_id", "file", "process", "version"], "left_anti").select(*b.columns))
    name = F.concat("file", F.lit("#"), F.col("version").cast("string"))
    if scope == "hazard":
        hot = hazard_counts(g).select("run_id", "file").withColumn("hot", F.lit(True))
        b = b.join(hot, ["run_id", "file"], "left")
        name = F.when(F.col("hot"), name).otherwise(F.col("file"))
    b = b.withColumn("v", name)
    write = F.col("label") == GENERATED
    files = edges_of(b.select("run_id", F.when(write, F.col("v")).otherwise(F.col("process")).alias("src"), F.when(write, F.col("process")).otherwise(F.col("v")).alias("dst"), "label", "t_begin", "t_end", "n"))
    touched = b.select("run_id", F.col("file").alias("node_id"), "v").distinct()
    zero = b.select("run_id", F.col("file").alias("node_id"), F.when(F.endswith("v", F.lit("#0")) | (F.col("v") == F.col("file")), F.col("v")).otherwise(F.concat("file", F.lit("#0"))).alias("v")).distinct()
    versions = touched.union(zero).distinct()
    kept = g.nodes.join(versions.select("run_id", "node_id").distinct(), ["run_id", "node_id"], "left_anti")
    new = g.nodes.join(versions, ["run_id", "node_id"]).withColumn("node_id", F.col("v")).select(*g.nodes.columns)
    rest = g.edges.filter(~F.col("label").isin(USED, GENERATED))
    return ProvGraph(kept.select(*g.nodes.columns).unionByName(new), files.unionByName(edges_of(rest)))


def split_processes(g: ProvGraph) -> ProvGraph:
    """Processes cut into segments, a new one at each read that follows a write, linked later to earlier.

    A spawn counts as a write of the parent and as the first read of the child. With versioned files no cycle is left.
    """
    e = g.edges.withColumn("_id", F.struct("src", "dst", "label", "t_begin", "t_end"))
    ends = F.explode(F.array(
        F.struct(F.col("src").alias("p"), F.lit("src").alias("side"), F.when(F.col("label") == GENERATED, None).otherwise(F.lit(0)).alias("w")),
        F.struct(F.col("dst").alias("p"), F.lit("dst").alias("side"), F.when(F.col("label") == USED, None).otherwise(F.lit(1)).alias("w")),
    ))
    acts = e.select("run_id", "_id", "t_begin", "label", ends.alias("x")).select("run_id", "_id", "t_begin", "x.*").filter("w is not null")
    w = Window.partitionBy("run_id", "p").orderBy("t_begin", "w", "_id")
    acts = acts.withColumn("cut", ((F.col("w") == 0) & (F.coalesce(F.lag("w").over(w), F.lit(0)) == 1)).cast("int"))
    acts = acts.withColumn("seg", F.sum("cut").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    seg = acts.select("run_id", "_id", "side", "p", "seg")
    for side in ("src", "dst"):
        s = seg.filter(F.col("side") == side).select("run_id", "_id", F.concat("p", F.lit("#"), "seg").alias(f"s_{side}"))
        e = e.join(s, ["run_id", "_id"], "left").withColumn(side, F.coalesce(f"s_{side}", side)).drop(f"s_{side}")
    count = seg.groupBy("run_id", "p").agg(F.max("seg").alias("last"))
    chain = count.filter("last > 0").select("run_id", "p", F.explode(F.sequence(F.lit(1), F.col("last").cast("int"))).alias("k"))
    links = edges_of(chain.select("run_id", F.concat("p", F.lit("#"), "k").alias("src"), F.concat("p", F.lit("#"), F.col("k") - 1).alias("dst"), F.lit(INFORMED).alias("label"), F.lit(1).alias("n")))
    nodes = g.nodes.join(count.withColumnRenamed("p", "node_id"), ["run_id", "node_id"], "left")
    many = F.when(F.col("last").isNull(), F.array("node_id")).otherwise(F.transform(F.sequence(F.lit(0), F.col("last").cast("int")), lambda k: F.concat("node_id", F.lit("#"), k)))
    nodes = nodes.withColumn("node_id", F.explode(many)).select(*g.nodes.columns)
    return ProvGraph(nodes, edges_of(e).unionByName(links))


def prepare(g: ProvGraph, on_cycle: str = "version") -> ProvGraph | tuple[ProvGraph, DataFrame]:
    """'raise' on a cycle; 'version' files and split processes; 'rerun': the graph and its cores, each run again as one."""
    if on_cycle == "raise":
        if not reach.on_cycles(g).isEmpty():
            raise ValueError("the trace has a cycle")
        return g
    return split_processes(version_files(g)) if on_cycle == "version" else (g, reach.cyclic_cores(g))


def overhead(g: ProvGraph, v: ProvGraph) -> DataFrame:
    """(run_id, nodes_added, edges_added, versions)."""
    a = g.nodes.groupBy("run_id").agg(F.count(F.lit(1)).alias("n0"))
    b = v.nodes.groupBy("run_id").agg(F.count(F.lit(1)).alias("n1"), F.count_if((F.col("node_type") == ENTITY) & F.col("node_id").contains("#")).alias("versions"))
    c, d = (x.edges.groupBy("run_id").agg(F.count(F.lit(1)).alias(n)) for x, n in ((g, "e0"), (v, "e1")))
    j = a.join(b, "run_id").join(c, "run_id").join(d, "run_id")
    return j.select("run_id", (F.col("n1") - F.col("n0")).alias("nodes_added"), (F.col("e1") - F.col("e0")).alias("edges_added"), "versions")
