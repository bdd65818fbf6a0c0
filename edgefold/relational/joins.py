"""Scans, readers and writers, filters, joins, set operations, subqueries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..algorithms import traversal
from ..graph import build, io
from ..graph.build import table
from ..graph.model import PropertyGraph
from ..oracles.graphs import ctes, relaxed
from ..runtime.scratch import new_path, save

TRADE = f"WITH {ctes('trade')} SELECT src, dst, w FROM e"


def scan_lineitem_pruned(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").where("l_quantity > 45 AND l_returnflag = 'R'").select("l_orderkey", "l_suppkey")


def filter_project_lineitem(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "lineitem").where("l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'N') AND l_linestatus LIKE 'O%' AND l_partkey IS NOT NULL")
    size = F.when(F.col("l_quantity") < 11, "small").otherwise("large")
    return rows.select("l_orderkey", "l_linenumber", size.alias("size"), (F.col("l_extendedprice").cast("decimal(12,2)") * (1 - F.col("l_discount").cast("decimal(4,2)"))).cast("double").alias("net"))


def _round_trip(fmt: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        path = new_path(spark, f"edges-{fmt}")
        io.write_edges(build.trade(spark, sf).edges.select("src", "dst", "w"), path, fmt)
        return io.read_edges(spark, path, fmt)

    return run


def graph_save_load(spark: SparkSession, sf: str) -> DataFrame:
    path = new_path(spark, "graph")
    io.save_graph(build.trade(spark, sf), path, parts=2)
    return io.load_graph(spark, path).edges.select("src", "dst", "w")


def rmat_source(spark: SparkSession, sf: str) -> DataFrame:
    """(edge_seq, src, dst): the edge that the source draws for each event's number, a block of numbers at a time."""
    numbers = table(spark, sf, "events").select(F.col("event_id").alias("edge_seq"))
    found = numbers.where("edge_seq IS NOT NULL").select(F.shiftright("edge_seq", io.RMAT_BLOCK.bit_length() - 1).alias("b")).distinct()
    blocks = sorted(r["b"] for r in found.collect())  # one for up to RMAT_BLOCK events
    edges = spark.read.format(io.rmat_format(spark)).option("scale", 8).option("blocks", ",".join(map(str, blocks))).load()
    return numbers.join(edges, "edge_seq", "left").select("edge_seq", "src", "dst")


def _edge_properties(hint: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        edges = build.purchase(spark, sf).edges
        customers = table(spark, sf, "customer").select((F.col("c_custkey") * 16).alias("src"), "c_mktsegment")
        return edges.join(customers.hint(hint), "src").groupBy("c_mktsegment").agg(F.sum("w").alias("lines"))

    return run


def join_settle_left(spark: SparkSession, sf: str) -> DataFrame:
    g = build.hyperlink(spark, sf)
    return g.vertices.join(g.in_degrees(), "id", "left").select("id", F.coalesce("in_degree", F.lit(0)).cast("long").alias("in_degree"))


def join_rank_compare_full(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff_strong(spark, sf)
    return g.out_degrees().join(g.in_degrees(), "id", "full").select("id", "out_degree", "in_degree")


def frontier_edges_traversal(spark: SparkSession, sf: str) -> DataFrame:
    """(level, src, dst): the edges out of each frontier of a traversal from vertex 0, whatever its depth."""
    g = build.handoff(spark, sf)
    g = PropertyGraph(save(g.vertices, "vertices"), save(g.edges, "edges"))
    reached = save(traversal.bfs(g, [0]).where("level IS NOT NULL"), "levels")
    return g.edges.join(reached.withColumnRenamed("id", "src"), "src").select("level", "src", "dst")


def dangling_anti(spark: SparkSession, sf: str) -> DataFrame:
    g = build.hyperlink(spark, sf)
    return g.vertices.join(g.edges.select(F.col("src").alias("id")), "id", "left_anti")


def cross_parts_nation(spark: SparkSession, sf: str) -> DataFrame:
    parts = spark.range(4).select(F.col("id").alias("pid"))
    nations = table(spark, sf, "nation").select(F.col("n_nationkey").cast("long").alias("n_nationkey"))
    return nations.crossJoin(F.broadcast(parts)).select("n_nationkey", "pid", ((F.col("n_nationkey") * 7 + F.col("pid") * 3) % 11).alias("score"))


def range_join_balance(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs of suppliers whose balances are less than 5 apart, by bands of 5 so that no pair of far bands meets."""
    s = table(spark, sf, "supplier").select("s_suppkey", "s_acctbal", F.floor(F.col("s_acctbal") / 5).alias("band"))
    near = s.select(F.col("s_suppkey").alias("b"), F.col("s_acctbal").alias("bal_b"), F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    pairs = s.select(F.col("s_suppkey").alias("a"), F.col("s_acctbal").alias("bal_a"), "band").join(near, "band")
    return pairs.where("a < b AND abs(bal_a - bal_b) < 5").select("a", "b")


def interval_join_events(spark: SparkSession, sf: str) -> DataFrame:
    from ..streaming.events import interval_pairs

    events = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return interval_pairs(events, events, 120)


def asof_events(spark: SparkSession, sf: str) -> DataFrame:
    """For each purchase the user's latest earlier click: union, order, carry the last one forward."""
    events = table(spark, sf, "events").select("event_id", "ts", "user_id", "event_type")
    click = F.when(F.col("event_type") == "click", F.col("event_id"))
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    carried = events.withColumn("click_id", F.last(click, ignorenulls=True).over(before))
    return carried.where("event_type = 'purchase'").select("event_id", "click_id")


def mutual_edges(spark: SparkSession, sf: str) -> DataFrame:
    e = build.handoff_strong(spark, sf).edges
    back = e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return e.select("src", "dst").join(back, ["src", "dst"], "left_semi").where("src < dst")


def triangle_count(spark: SparkSession, sf: str) -> DataFrame:
    """Undirected triangles, each from its smallest-degree end, so hubs don't pair their neighbours."""
    und = build.handoff_strong(spark, sf).symmetrize().edges
    degree = und.groupBy("src").agg(F.count("*").alias("d"))
    ranked = und.join(degree, "src").join(degree.select(F.col("src").alias("dst"), F.col("d").alias("e")), "dst").where("d < e OR (d = e AND src < dst)").select("src", "dst").persist()
    wedge = ranked.alias("a").join(ranked.alias("b"), F.col("a.src") == F.col("b.src")).where("a.dst < b.dst").select(F.col("a.dst").alias("x"), F.col("b.dst").alias("y"))
    closed = wedge.join(und.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"])
    return closed.agg(F.count("*").alias("triangles"))


def explode_adjacency(spark: SparkSession, sf: str) -> DataFrame:
    lists = build.trade(spark, sf).edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("targets"))
    return lists.select("src", F.posexplode("targets").alias("nth", "dst")).select("src", F.col("nth").cast("long").alias("nth"), "dst")


def symmetrize_union(spark: SparkSession, sf: str) -> DataFrame:
    return build.handoff_strong(spark, sf).symmetrize().edges


def common_edges_intersect(spark: SparkSession, sf: str) -> DataFrame:
    e = build.handoff(spark, sf).edges
    return e.where("w >= 2").select("src", "dst").intersect(e.where("src < dst").select("src", "dst"))


def new_edges_except(spark: SparkSession, sf: str) -> DataFrame:
    e = build.handoff(spark, sf).edges
    return e.select("src", "dst").exceptAll(e.where("w < 3").select("src", "dst"))


def above_mean_degree(spark: SparkSession, sf: str) -> DataFrame:
    d = build.purchase(spark, sf).in_degrees()
    d.createOrReplaceTempView("purchase_in_degrees")
    return spark.sql("SELECT id, in_degree FROM purchase_in_degrees WHERE in_degree > (SELECT avg(in_degree) FROM purchase_in_degrees)")


def customers_with_orders(spark: SparkSession, sf: str) -> DataFrame:
    table(spark, sf, "customer").createOrReplaceTempView("q_customer")
    table(spark, sf, "orders").createOrReplaceTempView("q_orders")
    return spark.sql("SELECT c_custkey FROM q_customer c WHERE EXISTS (SELECT 1 FROM q_orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000) AND c_nationkey NOT IN (SELECT 3)")


PROPERTY_SQL = f"WITH {ctes('purchase')} SELECT c_mktsegment, sum(w)::BIGINT AS lines FROM e JOIN customer ON c_custkey * 16 = src GROUP BY 1"
QUERIES = {
    "scan_lineitem_pruned": (scan_lineitem_pruned, "SELECT l_orderkey, l_suppkey FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'"),
    "filter_project_lineitem": (
        filter_project_lineitem,
        "SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity < 11 THEN 'small' ELSE 'large' END AS size, (l_extendedprice::DECIMAL(12,2) * (1 - l_discount::DECIMAL(4,2)))::DOUBLE AS net FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'N') AND l_linestatus LIKE 'O%'",
    ),
    "edges_roundtrip_csv": (_round_trip("csv"), TRADE),
    "edges_roundtrip_tsv": (_round_trip("tsv"), TRADE),
    "edges_roundtrip_text": (_round_trip("text"), TRADE),
    "edges_roundtrip_json": (_round_trip("json"), TRADE),
    "edges_roundtrip_orc": (_round_trip("orc"), TRADE),
    "graph_save_load": (graph_save_load, TRADE),
    "rmat_source": (rmat_source, f"WITH {ctes('rmat8_events')} SELECT edge_seq, src, dst FROM e"),
    "join_edge_properties_broadcast": (_edge_properties("broadcast"), PROPERTY_SQL),
    "join_edge_properties_merge": (_edge_properties("merge"), PROPERTY_SQL),
    "join_edge_properties_shuffle_hash": (_edge_properties("shuffle_hash"), PROPERTY_SQL),
    "join_settle_left": (join_settle_left, f"WITH {ctes('hyperlink')} SELECT v.id, count(e.dst) AS in_degree FROM v LEFT JOIN e ON e.dst = v.id GROUP BY v.id"),
    "join_rank_compare_full": (
        join_rank_compare_full,
        f"WITH {ctes('handoff_strong')} SELECT coalesce(a.id, b.id) AS id, out_degree, in_degree FROM (SELECT src AS id, count(*) AS out_degree FROM e GROUP BY src) a FULL JOIN (SELECT dst AS id, count(*) AS in_degree FROM e GROUP BY dst) b ON a.id = b.id",
    ),
    "frontier_edges_traversal": (frontier_edges_traversal, relaxed("handoff", "SELECT 0::BIGINT, 0::BIGINT", "d.x + 1", "SELECT d.x::BIGINT AS level, e.src, e.dst FROM e JOIN d ON d.id = e.src")),
    "dangling_anti": (dangling_anti, f"WITH {ctes('hyperlink')} SELECT id FROM v WHERE id NOT IN (SELECT src FROM e)"),
    "cross_parts_nation": (cross_parts_nation, "SELECT n_nationkey::BIGINT AS n_nationkey, pid, (n_nationkey * 7 + pid * 3) % 11 AS score FROM nation, range(4) t(pid)"),
    "range_join_balance": (range_join_balance, "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) < 5"),
    "interval_join_events": (interval_join_events, "SELECT a.user_id, a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 120 MINUTE"),
    "asof_events": (
        asof_events,
        "SELECT p.event_id, c.event_id AS click_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts > c.ts",
    ),
    "mutual_edges": (mutual_edges, f"WITH {ctes('handoff_strong')} SELECT a.src, a.dst FROM e a JOIN e b ON a.src = b.dst AND a.dst = b.src WHERE a.src < a.dst"),
    "triangle_count": (
        triangle_count,
        f"WITH {ctes('handoff_strong')}, u AS (SELECT DISTINCT least(src, dst) AS x, greatest(src, dst) AS y FROM e) SELECT count(*) AS triangles FROM u a JOIN u b ON a.y = b.x JOIN u c ON c.x = a.x AND c.y = b.y",
    ),
    "explode_adjacency": (explode_adjacency, f"WITH {ctes('trade')} SELECT src, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS nth, dst FROM e"),
    "symmetrize_union": (symmetrize_union, f"WITH {ctes('handoff_strong')} SELECT src, dst FROM e UNION SELECT dst, src FROM e"),
    "common_edges_intersect": (common_edges_intersect, f"WITH {ctes('handoff')} SELECT src, dst FROM e WHERE w >= 2 AND src < dst"),
    "new_edges_except": (new_edges_except, f"WITH {ctes('handoff')} SELECT src, dst FROM e WHERE w >= 3"),
    "above_mean_degree": (above_mean_degree, f"WITH {ctes('purchase')}, d AS (SELECT dst AS id, count(*) AS in_degree FROM e GROUP BY dst) SELECT id, in_degree FROM d WHERE in_degree > (SELECT avg(in_degree) FROM d)"),
    "customers_with_orders": (customers_with_orders, "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 400000) AND c_nationkey <> 3"),
}
