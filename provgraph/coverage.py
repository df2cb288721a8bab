"""One query for each category of relational and streaming operator that the methods lean on."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from provgraph import oracles as o
from provgraph import sqlapi
from provgraph.functions.paths import prov_label, short_path
from provgraph.operators import graph, temporal, trace
from provgraph.plans.choose import salted_counts
from provgraph.plans.iterate import materialize, shared_dir
from provgraph.queries import query
from provgraph.sources import carriers as c

_URL = r"^([a-z]+)://([^/?#]+)"


def _events(spark, d):
    return c.table(spark, d, "events")


@query("SELECT event_id, user_id FROM events WHERE event_type = 'purchase'")
def op_scan_prune(spark, d):
    return _events(spark, d).filter("event_type = 'purchase'").select("event_id", "user_id")


@query("SELECT CASE WHEN event_type IN ('view', 'click') THEN 'used' WHEN event_type = 'purchase' THEN 'wasGeneratedBy' WHEN event_type = 'signup' THEN 'wasInformedBy' END AS label, count(*) AS n FROM events GROUP BY 1")
def op_project_labels(spark, d):
    return c.audit_accesses(spark, d).groupBy(prov_label(F.col("op")).alias("label")).agg(F.count(F.lit(1)).alias("n"))


@query(r"""WITH h AS (SELECT DISTINCT unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) SELECT href FROM h WHERE NOT regexp_matches(href, '^/[^/]*$')""")
def op_filter_paths(spark, d):
    h = c.table(spark, d, "pages").select(F.explode(F.expr(r"""regexp_extract_all(html, 'href="([^"]*)"', 1)""")).alias("href")).distinct()
    return h.join(h.filter(F.col("href").rlike("^/[^/]*$")), "href", "left_anti")


_NATION_JOIN = "SELECT o_orderkey, c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey"


@query(_NATION_JOIN.replace("c_nationkey FROM", "n_name FROM") + " JOIN nation ON c_nationkey = n_nationkey")
def op_join_broadcast(spark, d):
    o_, cu, n = (c.table(spark, d, x) for x in ("orders", "customer", "nation"))
    return o_.join(cu, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("o_orderkey", "n_name")  # 25 rows, fixed


@query("SELECT o_orderstatus, p_brand, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def op_join_sortmerge(spark, d):
    li = c.table(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    j = li.join(c.table(spark, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).join(c.table(spark, d, "part").hint("merge"), F.col("l_partkey") == F.col("p_partkey"))
    return j.groupBy("o_orderstatus", "p_brand").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def op_join_shuffle_hash(spark, d):
    j = c.table(spark, d, "lineitem").select("l_orderkey").join(c.table(spark, d, "orders").hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    return j.groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_orderkey < 500)")
def op_join_semi(spark, d):
    return c.table(spark, d, "part").join(c.table(spark, d, "lineitem").filter("l_orderkey < 500"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@query("SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_orderkey < 500)")
def op_join_anti(spark, d):
    return c.table(spark, d, "part").join(c.table(spark, d, "lineitem").filter("l_orderkey < 500"), F.col("p_partkey") == F.col("l_partkey"), "left_anti").select("p_partkey")


def _by_flag(spark, d, how):
    """(p_partkey, l_returnflag): every part under every return flag, joined in the given way with all lines."""
    li = c.table(spark, d, "lineitem").select("l_partkey", "l_returnflag")
    pairs = c.table(spark, d, "part").select("p_partkey").crossJoin(li.select("l_returnflag").distinct())
    return pairs.join(li.withColumnRenamed("l_partkey", "p_partkey"), ["p_partkey", "l_returnflag"], how)


@query("SELECT p_partkey, l_returnflag FROM part, (SELECT DISTINCT l_returnflag FROM lineitem) f WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_partkey = p_partkey AND l.l_returnflag = f.l_returnflag)")
def op_join_semi_all(spark, d):
    """The parts that lines of each return flag use, over the whole table."""
    return _by_flag(spark, d, "left_semi")


@query("SELECT p_partkey, l_returnflag FROM part, (SELECT DISTINCT l_returnflag FROM lineitem) f WHERE NOT EXISTS (SELECT 1 FROM lineitem l WHERE l.l_partkey = p_partkey AND l.l_returnflag = f.l_returnflag)")
def op_join_anti_all(spark, d):
    """The parts that no line of a return flag uses, over the whole table."""
    return _by_flag(spark, d, "left_anti")


@query("WITH a AS (SELECT lang, count(*) AS x FROM documents WHERE source = 'src0' GROUP BY 1), b AS (SELECT lang, count(*) AS y FROM documents WHERE source = 'src1' GROUP BY 1) SELECT coalesce(a.lang, b.lang) AS lang, coalesce(x, 0) AS x, coalesce(y, 0) AS y FROM a FULL JOIN b ON a.lang = b.lang")
def op_join_full(spark, d):
    f = c.table(spark, d, "documents")
    a, b = (f.filter(F.col("source") == s).groupBy("lang").agg(F.count(F.lit(1)).alias(n)) for s, n in (("src0", "x"), ("src1", "y")))
    return a.join(b, "lang", "full").select("lang", F.coalesce("x", F.lit(0)).alias("x"), F.coalesce("y", F.lit(0)).alias("y"))


@query(o.AUDIT + ", r AS (SELECT * FROM acc WHERE op = 'read'), w AS (SELECT * FROM acc WHERE op = 'written') SELECT r.seq AS read_seq, w.seq AS write_seq FROM r JOIN w ON r.object = w.object WHERE r.actor <> w.actor AND r.ts <= w.ts AND epoch_us(w.ts) <= epoch_us(r.ts) + 86400000000")
def op_join_interval(spark, d):
    """Writes within a day after a read, by day buckets: each read looks into its own and the next one."""
    a = c.audit_accesses(spark, d).filter("op in ('read', 'written')")
    day = F.floor(F.timestamp_diff("SECOND", F.lit("1970-01-01").cast("timestamp_ntz"), "ts") / 86400)
    r = a.filter("op = 'read'").select(F.col("seq").alias("read_seq"), "object", F.col("actor").alias("reader"), F.col("ts").alias("rt"), F.explode(F.array(day, day + 1)).alias("bucket"))
    w = a.filter("op = 'written'").select(F.col("seq").alias("write_seq"), "object", "actor", "ts", day.alias("bucket"))
    ok = (F.col("reader") != F.col("actor")) & (F.col("rt") <= F.col("ts")) & (F.timestamp_diff("MICROSECOND", "rt", "ts") <= 86_400_000_000)
    return r.join(w, ["object", "bucket"]).filter(ok).select("read_seq", "write_seq")


@query(o.AUDIT + "SELECT r.seq, max(w.seq) AS writer_seq FROM acc r ASOF LEFT JOIN (SELECT * FROM acc WHERE op = 'written') w ON r.object = w.object AND r.ts > w.ts WHERE r.op = 'read' GROUP BY r.seq")
def op_join_asof(spark, d):
    """The last write before each read, by one sort per file."""
    a = c.audit_accesses(spark, d).filter("op in ('read', 'written')").withColumn("w", (F.col("op") == "written").cast("int"))
    order = Window.partitionBy("object").orderBy("ts", "w", "seq").rowsBetween(Window.unboundedPreceding, -1)
    return a.withColumn("writer_seq", F.last(F.when(F.col("w") == 1, F.col("seq")), ignorenulls=True).over(order)).filter("w = 0").select("seq", "writer_seq")


@query("WITH s AS (SELECT l_suppkey AS s, count(DISTINCT l_partkey) AS k FROM lineitem WHERE l_orderkey = 1 GROUP BY 1), t AS (SELECT l_suppkey AS s, count(DISTINCT l_partkey) AS k FROM lineitem WHERE l_orderkey = 2 GROUP BY 1) SELECT s.s AS a, t.s AS b FROM s JOIN t ON s.k = t.k")
def op_join_nested(spark, d):
    """Candidate pairs of equal degree between two small runs."""
    li = c.table(spark, d, "lineitem")
    a, b = (li.filter(F.col("l_orderkey") == k).groupBy(F.col("l_suppkey").alias(n)).agg(F.count_distinct("l_partkey").alias(f"k{n}")) for k, n in ((1, "a"), (2, "b")))
    return a.join(b, F.col("ka") == F.col("kb")).select("a", "b")


@query(
    """WITH s AS (SELECT l_orderkey, l_suppkey, count(DISTINCT l_partkey) AS degree FROM lineitem GROUP BY 1, 2), r AS (SELECT l_orderkey, degree, count(*) AS n FROM s GROUP BY 1, 2),
    h AS (SELECT degree, n, count(*) AS runs FROM r GROUP BY 1, 2)
    SELECT a.degree, a.n AS n_a, b.n AS n_b, (CASE WHEN a.n = b.n THEN a.runs::HUGEINT * (a.runs - 1) // 2 ELSE a.runs::HUGEINT * b.runs END)::DECIMAL(38, 0) AS run_pairs FROM h a JOIN h b ON a.degree = b.degree AND a.n <= b.n"""
)
def op_join_nested_all(spark, d):
    """Pairs of orders, over all of them, that hold ``n_a`` and ``n_b`` suppliers of one degree: each such pair has ``n_a * n_b`` candidates.

    Orders with as many suppliers of a degree are one class before the join, so its size does not grow with the number of orders.
    """
    s = c.table(spark, d, "lineitem").groupBy("l_orderkey", "l_suppkey").agg(F.count_distinct("l_partkey").alias("degree"))
    h = s.groupBy("l_orderkey", "degree").agg(F.count(F.lit(1)).alias("n")).groupBy("degree", "n").agg(F.count(F.lit(1)).cast("decimal(19,0)").alias("runs"))
    a, b = (h.select("degree", F.col("n").alias(f"n_{x}"), F.col("runs").alias(x)) for x in "ab")
    pairs = F.when(F.col("n_a") == F.col("n_b"), F.col("a") * (F.col("a") - 1) / 2).otherwise(F.col("a") * F.col("b"))
    return a.join(b, "degree").filter("n_a <= n_b").select("degree", "n_a", "n_b", pairs.cast("decimal(38,0)").alias("run_pairs"))


@query(o.ORDERS + ", x AS (SELECT src AS node_id, label, 1 AS o, 0 AS i FROM ord_e UNION ALL SELECT dst, label, 0, 1 FROM ord_e) SELECT node_id, label, sum(o)::BIGINT AS n_out, sum(i)::BIGINT AS n_in FROM x GROUP BY ALL")
def op_agg_degrees(spark, d):
    return graph.degrees(c.order_runs(spark, d)).drop("run_id")


@query(o.AUDIT + "SELECT strftime(ts, '%Y-%m-%d') AS day, count(DISTINCT actor) AS processes, count(DISTINCT object) AS files FROM acc GROUP BY 1")
def op_agg_distinct(spark, d):
    return c.audit_accesses(spark, d).groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count_distinct("actor").alias("processes"), F.count_distinct("object").alias("files"))


@query("SELECT event_type, count(*) AS n FROM events GROUP BY 1")
def op_agg_salted(spark, d):
    """Counts of few, hot keys, added up by many tasks first."""
    return salted_counts(_events(spark, d).select("event_type", "event_id"), ["event_type"])


@query(o.AUDIT + "SELECT CASE label WHEN 'used' THEN 'read' WHEN 'wasGeneratedBy' THEN 'written' ELSE 'spawned' END AS label, count(*) AS n, count(DISTINCT dst) AS starts FROM aud_e GROUP BY 1")
def op_trace_view(spark, d):
    """Stored edges as audited ones, from where information comes."""
    t = trace.to_trace(trace.from_accesses(c.audit_accesses(spark, d)).edges)
    return t.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("start").alias("starts"))


@query()
def op_agg_approx(spark, d):
    a = c.audit_accesses(spark, d)
    return a.agg(F.approx_count_distinct("actor").alias("about"), F.count_distinct("actor").alias("exact"), F.percentile_approx("dur_us", 0.5).alias("median_us"))


@query("SELECT source, lang, count(*) AS n, grouping(source) * 2 + grouping(lang) AS level FROM documents GROUP BY CUBE (source, lang)")
def op_agg_sets(spark, d):
    return c.table(spark, d, "documents").cube("source", "lang").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY 1")
def op_agg_pivot(spark, d):
    return c.table(spark, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).fillna(0)


@query("SELECT * FROM (SELECT s_nationkey, s_suppkey, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rank FROM supplier) WHERE rank <= 2")
def op_window_rank(spark, d):
    w = Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"), "s_suppkey")
    return c.table(spark, d, "supplier").select("s_nationkey", "s_suppkey", F.row_number().over(w).alias("rank")).filter("rank <= 2")


@query(o.AUDIT + "SELECT seq, sum(CASE WHEN op = 'written' THEN 1 ELSE 0 END) OVER w::BIGINT AS writes, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY object ORDER BY ts, seq)) AS gap_us, round(avg(dur_us) OVER (PARTITION BY object ORDER BY ts, seq ROWS BETWEEN 4 PRECEDING AND CURRENT ROW), 3) AS mean5 FROM acc WINDOW w AS (PARTITION BY object ORDER BY ts, seq ROWS UNBOUNDED PRECEDING)")
def op_window_frames(spark, d):
    w = Window.partitionBy("object").orderBy("ts", "seq")
    a = c.audit_accesses(spark, d)
    return a.select("seq", F.sum((F.col("op") == "written").cast("int")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("writes"), F.timestamp_diff("MICROSECOND", F.lag("ts").over(w), "ts").alias("gap_us"), F.round(F.avg("dur_us").over(w.rowsBetween(-4, 0)), 3).alias("mean5"))


@query("SELECT 'p:' || l_partkey AS file, count(DISTINCT l_orderkey) AS users FROM lineitem GROUP BY 1 ORDER BY users DESC, file LIMIT 10")
def op_topk_hubs(spark, d):
    n = c.table(spark, d, "lineitem").groupBy(F.concat(F.lit("p:"), F.col("l_partkey")).alias("file")).agg(F.count_distinct("l_orderkey").alias("users"))
    return n.orderBy(F.desc("users"), "file").limit(10)


@query("(SELECT 'both' AS part, l_partkey FROM (SELECT l_partkey FROM lineitem WHERE l_orderkey < 300 INTERSECT SELECT l_partkey FROM lineitem WHERE l_orderkey BETWEEN 300 AND 600)) UNION ALL (SELECT 'first', l_partkey FROM (SELECT l_partkey FROM lineitem WHERE l_orderkey < 300 EXCEPT SELECT l_partkey FROM lineitem WHERE l_orderkey BETWEEN 300 AND 600))")
def op_set_ops(spark, d):
    li = c.table(spark, d, "lineitem")
    a, b = li.filter("l_orderkey < 300").select("l_partkey"), li.filter("l_orderkey between 300 and 600").select("l_partkey")
    return a.intersect(b).select(F.lit("both").alias("part"), "l_partkey").unionByName(a.subtract(b).select(F.lit("first").alias("part"), "l_partkey"))


@query("WITH f AS (SELECT l_partkey FROM lineitem WHERE l_linestatus = 'F'), g AS (SELECT l_partkey FROM lineitem WHERE l_linestatus IS DISTINCT FROM 'F') SELECT 'both' AS part, l_partkey FROM (FROM f INTERSECT FROM g) UNION ALL SELECT 'first', l_partkey FROM (FROM f EXCEPT FROM g) UNION ALL SELECT 'second', l_partkey FROM (FROM g EXCEPT FROM f)")
def op_set_ops_all(spark, d):
    """Parts on finished and on other lines, over the whole table."""
    li = c.table(spark, d, "lineitem")
    done = F.col("l_linestatus").eqNullSafe("F")
    a, b = li.filter(done).select("l_partkey"), li.filter(~done).select("l_partkey")
    parts = (a.intersect(b), "both"), (a.subtract(b), "first"), (b.subtract(a), "second")
    x, y, z = (df.select(F.lit(name).alias("part"), "l_partkey") for df, name in parts)
    return x.unionByName(y).unionByName(z)


@query(rf"SELECT page_id, regexp_extract(url, '{_URL}', 2) AS host, array_to_string(string_split(url, '/')[-2:], '/') AS short FROM pages")
def op_string_path(spark, d):
    return c.table(spark, d, "pages").select("page_id", F.regexp_extract("url", _URL, 2).alias("host"), short_path(F.col("url")).alias("short"))


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS orders, max(epoch_us(o_orderdate)) - min(epoch_us(o_orderdate)) AS span_us FROM orders GROUP BY 1")
def op_time_intervals(spark, d):
    return c.table(spark, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.timestamp_diff("MICROSECOND", F.min("o_orderdate"), F.max("o_orderdate")).alias("span_us"))


@query(o.AUDIT + o.ONE_HOP + "SELECT process, round(100.0 * count(*) FILTER (feasible) / count(*), 3) AS feasible_pc FROM one_hop GROUP BY 1")
def op_math_ratios(spark, d):
    p = temporal.one_hop(trace.from_accesses(c.audit_accesses(spark, d)))
    return p.groupBy("process").agg(F.round(100 * F.try_divide(F.count_if("feasible"), F.count(F.lit(1))), 3).alias("feasible_pc"))


@query("SELECT l_orderkey, array_to_string(list_sort(list(DISTINCT l_suppkey)), ',') AS suppliers, len(list(DISTINCT l_suppkey)) AS k, list_contains(list(l_suppkey), 1) AS has_one FROM lineitem GROUP BY 1")
def op_array_annotations(spark, d):
    s = F.array_sort(F.collect_set("l_suppkey"))
    g = c.table(spark, d, "lineitem").groupBy("l_orderkey").agg(s.alias("s"))
    return g.select("l_orderkey", F.array_join(F.transform("s", lambda x: x.cast("string")), ",").alias("suppliers"), F.size("s").cast("long").alias("k"), F.exists("s", lambda x: x == 1).alias("has_one"))


@query("SELECT p_partkey, CASE WHEN starts_with(p_type, 'PROMO') THEN 'program' ELSE 'dependency' END AS class FROM part")
def op_map_attrs(spark, d):
    return c.star(spark, d, 2).nodes.filter("kind = 'part'").select(F.split("node_id", ":")[1].cast("long").alias("p_partkey"), F.element_at("attrs", "class").alias("class"))


@query("SELECT event_id, (props->>'$.k')::BIGINT AS k, true AS equal FROM events")
def op_json_props(spark, d):
    e = _events(spark, d).select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2"), F.variant_get(F.parse_json("props"), "$.k", "long").alias("k3"))
    return e.select("event_id", "k", ((F.col("k") == F.col("k2")) & (F.col("k") == F.col("k3"))).alias("equal"))


@query(o.STAR + o.spawn_sql("r:1") + "SELECT node_id FROM hit")
def op_sql_recursive(spark, d):
    """The spawn tree under a region by a recursive query; trees alone, as rows are not made distinct on the way.

    The edges are made once, not in every step; LIMIT ALL lifts the limit of a million rows that Spark sets for recursion.
    """
    materialize(c.star(spark, d).edges.filter("label = 'wasInformedBy'").select("src", "dst"), "spawned").createOrReplaceTempView("spawned")
    return spark.sql("WITH RECURSIVE hit(node_id) AS (SELECT 'r:1' UNION ALL SELECT s.src FROM spawned s JOIN hit ON s.dst = hit.node_id) SELECT node_id FROM hit LIMIT ALL")


@query()
def op_udf_rolling(spark, d):
    return c.table(spark, d, "documents").select("doc_id", sqlapi.rolling_cuts(F.coalesce("text", F.lit(""))).alias("chunks"))


@query("SELECT l_orderkey, true AS equal FROM lineitem GROUP BY 1")
def op_udaf_multiset(spark, d):
    """The grouped Python aggregate agrees with the built-in sums."""
    h = c.table(spark, d, "lineitem").select("l_orderkey", F.xxhash64("l_partkey").cast("decimal(20,0)").alias("h"))
    native = h.groupBy("l_orderkey").agg(F.sum("h").cast("string").alias("native"))
    return h.groupBy("l_orderkey").agg(sqlapi.multiset_udaf()("h").alias("udaf")).join(native, "l_orderkey").select("l_orderkey", (F.col("udaf") == F.col("native")).alias("equal"))


@query()
def op_udtf_chunks(spark, d):
    sqlapi.register(spark)
    c.table(spark, d, "documents").createOrReplaceTempView("chunk_texts")
    return spark.sql("SELECT doc_id, c.ord, c.start, c.stop FROM chunk_texts, LATERAL prov_chunks(text, 1024) c")


@query(o.CONV + "SELECT run_id, count(*) AS n FROM conv_e GROUP BY 1")
def op_sink_roundtrip(spark, d):
    path = f"{shared_dir(spark)}/runs-by-id-{spark.sparkContext.applicationId}"
    g = c.conversation_runs(spark, d)
    g.edges.withColumn("part", F.pmod(F.xxhash64("run_id"), F.lit(8))).write.mode("overwrite").partitionBy("part").parquet(path)
    return spark.read.parquet(path).groupBy("run_id").agg(F.count(F.lit(1)).alias("n"))
