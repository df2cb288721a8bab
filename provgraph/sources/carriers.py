"""The given tables as provenance graphs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from provgraph.schema import ACTIVITY, ENTITY, GENERATED, INFORMED, USED, ProvGraph, edges_of, nodes_of


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _id(prefix: str, *cols: str) -> Column:
    return F.concat(F.lit(prefix), F.concat_ws("_", *(F.col(c).cast("string") for c in cols)))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def star(spark: SparkSession, sf_dir: str, upto: int = 3) -> ProvGraph:
    """A dated batch workflow of the order tables; ``upto``: cumulative sub-task 0 to 3.

    0: regions and nations; 1: customers and suppliers; 2: orders and parts; 3: shipments.
    """
    t = {n: table(spark, sf_dir, n) for n in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")}
    lines = t["lineitem"].repartition("l_orderkey")

    def nodes(df: DataFrame, prefix: str, kind: str, key: str, label: Column, type_: str = ACTIVITY, **more: Column) -> DataFrame:
        return nodes_of(df.select(F.lit(0).alias("run_id"), _id(prefix, key).alias("node_id"), F.lit(type_).alias("node_type"), F.lit(kind).alias("kind"), label.alias("label"), *(c.alias(k) for k, c in more.items())))

    def edges(df: DataFrame, src: Column, dst: Column, label: str, by: tuple[str, ...], begin: Column | None = None, end: Column | None = None) -> DataFrame:
        """One edge per pair of ends, which are named after the columns ``by``: rows meet by these as numbers, and by names where an end has none."""
        times = [(F.lit(None) if x is None else x).cast("timestamp_ntz").alias(c) for x, c in ((begin, "b"), (end, "e"))]
        ends, agg = (src.alias("src"), dst.alias("dst")), (F.min("b").alias("t_begin"), F.max("e").alias("t_end"), F.count(F.lit(1)).alias("n"))
        named = src.isNotNull() & dst.isNotNull()
        e = df.filter(named).select(*by, *times).groupBy(*by).agg(*agg).select(*ends, "t_begin", "t_end", "n")
        e = e.unionByName(df.filter(~named).select(*ends, *times).groupBy("src", "dst").agg(*agg))
        return e.select(F.lit(0).alias("run_id"), "src", "dst", F.lit(label).alias("label"), "t_begin", "t_end", "n")

    n = [nodes(t["region"], "r:", "region", "r_regionkey", F.col("r_name")), nodes(t["nation"], "n:", "nation", "n_nationkey", F.col("n_name"))]
    e = [edges(t["nation"], _id("n:", "n_nationkey"), _id("r:", "n_regionkey"), INFORMED, ("n_nationkey", "n_regionkey"))]
    if upto >= 1:
        n += [nodes(t["customer"], "c:", "customer", "c_custkey", F.col("c_mktsegment")), nodes(t["supplier"], "s:", "supplier", "s_suppkey", F.col("s_name"))]
        e += [edges(t["customer"], _id("c:", "c_custkey"), _id("n:", "c_nationkey"), INFORMED, ("c_custkey", "c_nationkey")), edges(t["supplier"], _id("s:", "s_suppkey"), _id("n:", "s_nationkey"), INFORMED, ("s_suppkey", "s_nationkey"))]
    if upto >= 2:
        cls = F.when(F.col("p_type").startswith("PROMO"), "program").otherwise("dependency")
        n += [
            nodes(t["orders"], "o:", "order", "o_orderkey", F.col("o_orderstatus"), t_begin=F.col("o_orderdate"), t_end=F.col("o_orderdate")),
            nodes(t["part"], "p:", "part", "p_partkey", F.col("p_brand"), ENTITY, size_bytes=F.col("p_size").cast("long"), attrs=F.create_map(F.lit("class"), cls)),
        ]
        used = lines.select("l_orderkey", "l_partkey").join(t["orders"].select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
        e += [edges(t["orders"], _id("o:", "o_orderkey"), _id("c:", "o_custkey"), INFORMED, ("o_orderkey", "o_custkey")), edges(used, _id("o:", "l_orderkey"), _id("p:", "l_partkey"), USED, ("l_orderkey", "l_partkey"), F.col("o_orderdate"), F.col("o_orderdate"))]
    if upto >= 3:
        x = F.concat(F.lit("x:"), F.col("l_orderkey"), F.lit("_"), F.col("l_linenumber"))
        # an order without key has lines without a name, which are one
        ship = lines.select("l_orderkey", F.when(F.col("l_orderkey").isNotNull(), F.col("l_linenumber")).alias("l_linenumber"), "l_suppkey", "l_shipdate")
        once = ship.groupBy("l_orderkey", "l_linenumber").agg(F.min("l_shipdate").alias("b"), F.max("l_shipdate").alias("e")).withColumn("x", x)
        n.append(nodes_of(once.select(F.lit(0).alias("run_id"), F.col("x").alias("node_id"), F.lit(ENTITY).alias("node_type"), F.lit("shipment").alias("kind"), F.lit(None).alias("label"), F.col("b").alias("t_begin"), F.col("e").alias("t_end"), F.create_map(F.lit("class"), F.lit("data")).alias("attrs"))))
        e += [edges(ship, _id("s:", "l_suppkey"), x, USED, ("l_orderkey", "l_linenumber", "l_suppkey"), F.col("l_shipdate"), F.col("l_shipdate")), edges(ship, x, _id("o:", "l_orderkey"), GENERATED, ("l_orderkey", "l_linenumber"), F.col("l_shipdate"), F.col("l_shipdate"))]
    return ProvGraph(_union(n), edges_of(_union(e)))  # no two of these have an edge in common


def audit_accesses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table as an audit log: ACCESS rows of daily processes."""
    return accesses_of(table(spark, sf_dir, "events"))


def accesses_of(events: DataFrame) -> DataFrame:
    op = F.when(F.col("event_type").isin("view", "click"), "read").when(F.col("event_type") == "purchase", "written").when(F.col("event_type") == "signup", "spawned").otherwise("failed")
    day = F.date_format("ts", "yyyy-MM-dd")
    actor = F.concat(F.lit("d:"), F.col("user_id").cast("string"), F.lit(":"), day)
    obj = F.when(op == "spawned", F.concat(F.lit("t:"), F.col("event_id").cast("string"))).otherwise(F.concat(F.lit("f:"), F.get_json_object("props", "$.k")))
    return events.select(F.lit(0).cast("long").alias("run_id"), F.col("event_id").alias("seq"), "ts", actor.alias("actor"), op.alias("op"), obj.alias("object"), F.round(F.col("value") * 1_000_000).cast("long").alias("dur_us"))


def order_runs(spark: SparkSession, sf_dir: str) -> ProvGraph:
    """One run per order: its process, a sub-process per supplier, and the parts that each used, as copies of the run. Lines are dealt
    out by run as numbers, so that what goes by run afterwards stays where it is."""
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    li = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("run_id"), "l_suppkey", "l_partkey").repartition(parts, "run_id").distinct()
    o = F.concat(F.lit("o:"), F.col("run_id"))
    s = F.concat(F.lit("s:"), F.col("run_id"), F.lit("|"), F.col("l_suppkey"))
    p = F.concat(F.lit("p:"), F.col("run_id"), F.lit("|"), F.col("l_suppkey"), F.lit("|"), F.col("l_partkey"))
    sub = li.select("run_id", "l_suppkey").distinct()

    def n(df: DataFrame, i: Column, type_: str, kind: str) -> DataFrame:
        return nodes_of(df.select("run_id", i.alias("node_id"), F.lit(type_).alias("node_type"), F.lit(kind).alias("kind")))

    nodes = _union([n(li.select("run_id").distinct(), o, ACTIVITY, "order"), n(sub, s, ACTIVITY, "supplier"), n(li, p, ENTITY, "part")])
    one = F.lit(1).alias("n")
    edges = _union([edges_of(sub.select("run_id", s.alias("src"), o.alias("dst"), F.lit(INFORMED).alias("label"), one)), edges_of(li.select("run_id", s.alias("src"), p.alias("dst"), F.lit(USED).alias("label"), one))])
    return ProvGraph(nodes, edges)


def conversation_runs(spark: SparkSession, sf_dir: str) -> ProvGraph:
    """One run per conversation: assistant turns are activities that use all earlier turns of others; a turn of another right
    after an assistant's is generated by it."""
    c = table(spark, sf_dir, "conversations").select(F.col("conv_id").alias("run_id"), "turn", "role")
    i = F.concat(F.lit("m:"), F.col("run_id"), F.lit("_"), F.col("turn"))
    nodes = nodes_of(c.select("run_id", i.alias("node_id"), F.when(F.col("role") == "assistant", ACTIVITY).otherwise(ENTITY).alias("node_type"), F.col("role").alias("kind")))
    a = c.filter("role = 'assistant'").select("run_id", F.col("turn").alias("at"))
    other = c.filter("role <> 'assistant'")
    used = a.join(other, "run_id").filter("turn < at").select("run_id", F.concat(F.lit("m:"), F.col("run_id"), F.lit("_"), F.col("at")).alias("src"), i.alias("dst"), F.lit(USED).alias("label"))
    before = c.withColumn("was", F.lag("role").over(Window.partitionBy("run_id").orderBy("turn"))).withColumn("w", F.lag("turn").over(Window.partitionBy("run_id").orderBy("turn")))
    made = before.filter("role <> 'assistant' and was = 'assistant'").select("run_id", i.alias("src"), F.concat(F.lit("m:"), F.col("run_id"), F.lit("_"), F.col("w")).alias("dst"), F.lit(GENERATED).alias("label"))
    return ProvGraph(nodes, edges_of(used.union(made).withColumn("n", F.lit(1))))


def page_links(spark: SparkSession, sf_dir: str) -> ProvGraph:
    """Pages as processes and the targets of their links as shared dependencies."""
    h = table(spark, sf_dir, "pages").select("page_id", F.explode(F.expr(r"""regexp_extract_all(html, 'href="([^"]*)"', 1)""")).alias("href")).distinct()
    nodes = nodes_of(table(spark, sf_dir, "pages").select(F.lit(0).alias("run_id"), _id("g:", "page_id").alias("node_id"), F.lit(ACTIVITY).alias("node_type"), F.lit("page").alias("kind"), F.col("url").alias("label")))
    dst = F.concat(F.lit("h:"), F.col("href"))
    targets = nodes_of(h.select("href").distinct().select(F.lit(0).alias("run_id"), dst.alias("node_id"), F.lit(ENTITY).alias("node_type"), F.lit("target").alias("kind"), F.col("href").alias("label")))
    return ProvGraph(nodes.unionByName(targets), edges_of(h.select(F.lit(0).alias("run_id"), _id("g:", "page_id").alias("src"), dst.alias("dst"), F.lit(USED).alias("label"), F.lit(1).alias("n"))))


def files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(run_id = container, file_id, path, content) of the documents."""
    return table(spark, sf_dir, "documents").select(F.col("source").alias("container"), F.concat(F.lit("f:"), F.col("doc_id")).alias("file_id"), F.col("doc_id"), F.col("lang"), F.col("text").alias("content"))


def rerun(g: ProvGraph, seed: int = 1, perturb: str | None = None, every: int = 10) -> ProvGraph:
    """The graph as another run would record it: other identifiers, other row order.

    ``perturb``: in runs whose identifier ``every`` divides, 'drop' removes the first edge, 'flip' changes its label, and 'move' lets
    the first and the last edge of use, if they share no end, change their far ends: no node sees another number of edges to nodes of a type.
    """
    new = lambda c: F.when(c.isNotNull(), F.md5(F.concat(F.lit(f"{seed}:"), c)))
    nodes = g.nodes.withColumn("node_id", new(F.col("node_id")))
    e = g.edges
    if perturb == "move":
        ends = e.filter((F.col("label") == USED) & (F.col("run_id") % every == 0)).groupBy("run_id").agg(F.min(F.struct("src", "dst")).alias("p"), F.max(F.struct("src", "dst")).alias("q"))
        ends = ends.filter("p.src <> q.src and p.dst <> q.dst")
        at = lambda x: (F.col("label") == USED) & (F.struct("src", "dst") == F.col(x))
        e = e.join(ends, "run_id", "left").withColumn("dst", F.when(at("p"), F.col("q.dst")).when(at("q"), F.col("p.dst")).otherwise(F.col("dst"))).select(*g.edges.columns)
    elif perturb:
        hit = (F.col("run_id") % every == 0) & (F.row_number().over(Window.partitionBy("run_id").orderBy("src", "dst", "label")) == 1)
        e = e.withColumn("_hit", hit)
        e = e.filter("not _hit") if perturb == "drop" else e.withColumn("label", F.when(F.col("_hit"), F.when(F.col("label") == USED, GENERATED).otherwise(USED)).otherwise(F.col("label")))
        e = e.drop("_hit")
    return ProvGraph(nodes, e.withColumn("src", new(F.col("src"))).withColumn("dst", new(F.col("dst"))))
