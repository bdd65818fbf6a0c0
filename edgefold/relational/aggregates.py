"""Aggregations, windows, sorting, sampling, scalar and nested functions, user functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..graph import build
from ..graph.build import table
from ..graph.ids import mix, mix_sql
from ..oracles.graphs import ctes


def degrees(spark: SparkSession, sf: str) -> DataFrame:
    g = build.purchase(spark, sf)
    return g.out_degrees().join(g.in_degrees(), "id", "full").select("id", F.coalesce("out_degree", F.lit(0)).alias("out_degree"), F.coalesce("in_degree", F.lit(0)).alias("in_degree"))


def weighted_degree(spark: SparkSession, sf: str) -> DataFrame:
    return build.purchase(spark, sf).edges.groupBy(F.col("dst").alias("id")).agg(F.sum("w").alias("weight"))


def adjacency_lists(spark: SparkSession, sf: str) -> DataFrame:
    lists = build.trade(spark, sf).edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("t"))
    return lists.select("src", F.array_join(F.transform("t", lambda x: x.cast("string")), ",").alias("targets"))


def distinct_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").groupBy(F.col("l_suppkey").alias("id")).agg(F.countDistinct("l_partkey").alias("parts"))


def approx_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    rows = table(spark, sf, "lineitem").groupBy(F.col("l_suppkey").alias("id"))
    return rows.agg(F.approx_count_distinct("l_partkey", 0.03).alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(12))).alias("sketch"), F.percentile_approx("l_quantity", 0.5).alias("median_quantity"))


def approx_neighbours_violations(spark: SparkSession, sf: str) -> DataFrame:
    """(n): suppliers whose approximate counts of parts are off by more than a quarter, or by more than 2 parts where these are few."""
    both = approx_neighbours(spark, sf).join(distinct_neighbours(spark, sf).withColumnRenamed("parts", "exact"), "id")
    off = lambda c: F.abs(F.col(c) - F.col("exact")) > F.greatest(F.lit(2.0), F.col("exact") / 4)
    return both.where(off("parts") | off("sketch")).agg(F.count("*").alias("n"))


def _flows(spark: SparkSession, sf: str) -> DataFrame:
    """Line counts by customer region, customer nation and segment."""
    edges = build.purchase(spark, sf).edges
    customers = table(spark, sf, "customer").join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return edges.join(customers.select((F.col("c_custkey") * 16).alias("src"), "r_name", "n_name", "c_mktsegment"), "src")


FLOW_SQL = f"WITH {ctes('purchase')}, f AS (SELECT * FROM e JOIN customer ON c_custkey * 16 = src JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"


def flow_cube(spark: SparkSession, sf: str) -> DataFrame:
    return _flows(spark, sf).cube("r_name", "c_mktsegment").agg(F.sum("w").alias("lines"), F.grouping_id().cast("long").alias("gid"))


def flow_rollup(spark: SparkSession, sf: str) -> DataFrame:
    return _flows(spark, sf).rollup("r_name", "n_name").agg(F.sum("w").alias("lines"), F.grouping_id().cast("long").alias("gid"))


def flow_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    return _flows(spark, sf).groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(F.sum("w").alias("lines"))


def flow_pivot_all(spark: SparkSession, sf: str) -> DataFrame:
    """Flows between nations: a row per sender, a column for every nation of the table."""
    keys = sorted(r[0] for r in table(spark, sf, "nation").select(F.col("n_nationkey").cast("long")).distinct().collect())
    return build.trade(spark, sf).edges.groupBy("src").pivot("dst", keys).agg(F.sum("w")).select("src", *(F.col(str(i)).alias(f"to_{i}") for i in keys))


def degree_having(spark: SparkSession, sf: str) -> DataFrame:
    return build.handoff(spark, sf).edges.groupBy("src").agg(F.count("*").alias("n"), F.count_if(F.col("w") > 1).alias("repeated")).where("repeated >= 10")


def degree_stats(spark: SparkSession, sf: str) -> DataFrame:
    g = build.handoff(spark, sf)
    d = g.out_degrees().join(g.in_degrees(), "id")
    return d.agg(F.round(F.corr("out_degree", "in_degree"), 6).alias("corr"), F.round(F.stddev("out_degree"), 6).alias("sd"), F.round(F.regr_slope("in_degree", "out_degree"), 6).alias("slope"))


def presence_bitmap(spark: SparkSession, sf: str) -> DataFrame:
    e = build.purchase(spark, sf).edges
    pid = ((mix("src") * 31 + mix("dst")) % 1000003 % 16).cast("int")
    bits = e.groupBy(F.col("dst").alias("id")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), pid)).alias("bits"))
    return bits.select("id", "bits", F.bit_count("bits").cast("long").alias("parts"))


def rank_hubs(spark: SparkSession, sf: str) -> DataFrame:
    suppliers = table(spark, sf, "supplier").select((F.col("s_suppkey") * 16 + 1).alias("id"), "s_nationkey")
    d = build.purchase(spark, sf).in_degrees().join(suppliers, "id")
    by, alone = Window.partitionBy("s_nationkey").orderBy(F.desc("in_degree")), Window.partitionBy("s_nationkey").orderBy(F.desc("in_degree"), "id")
    return d.select(
        "id", "s_nationkey", F.row_number().over(alone).cast("long").alias("rn"), F.rank().over(by).cast("long").alias("rk"), F.dense_rank().over(by).cast("long").alias("dr"),
        F.round(F.percent_rank().over(by), 6).alias("pr"), F.round(F.cume_dist().over(by), 6).alias("cd"),
    )


def ntile_degrees(spark: SparkSession, sf: str) -> DataFrame:
    suppliers = table(spark, sf, "supplier").select((F.col("s_suppkey") * 16 + 1).alias("id"), "s_nationkey")
    d = build.purchase(spark, sf).in_degrees().join(suppliers, "id")
    return d.select("id", F.ntile(3).over(Window.partitionBy("s_nationkey").orderBy("in_degree", "id")).cast("long").alias("third"))


def handoff_edges(spark: SparkSession, sf: str) -> DataFrame:
    return build.handoff(spark, sf).edges


def lag_gap(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    e = table(spark, sf, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", (F.col("us") - F.lag("us").over(w)).alias("gap"), F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(whole).alias("last_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


def csr_offsets(spark: SparkSession, sf: str) -> DataFrame:
    d = build.trade(spark, sf).out_degrees()
    before = Window.partitionBy(F.lit(0)).orderBy("id").rowsBetween(Window.unboundedPreceding, -1)
    return d.select("id", F.coalesce(F.sum("out_degree").over(before), F.lit(0)).alias("offset"), "out_degree")


def moving_value_rows(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return table(spark, sf, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("moving"))


def moving_value_range(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "events").withColumn("s", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-86_400_000_000, 0)
    return e.select("event_id", F.count("*").over(w).alias("day_count"))


def sessions_by_gap(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(spark, sf, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    flagged = e.withColumn("fresh", F.when(F.col("us") - F.lag("us").over(w) <= 7_200_000_000, 0).otherwise(1))
    numbered = flagged.withColumn("session", F.sum("fresh").over(w))
    return numbered.groupBy("user_id", "session").agg(F.count("*").alias("n"), F.min("event_id").alias("first_id"))


def top_ranks(spark: SparkSession, sf: str) -> DataFrame:
    return build.purchase(spark, sf).in_degrees().orderBy(F.desc("in_degree"), "id").limit(20)


def sorted_page(spark: SparkSession, sf: str) -> DataFrame:
    return build.purchase(spark, sf).in_degrees().orderBy(F.desc("in_degree"), "id").offset(10).limit(10)


def topk_per_group(spark: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("src").orderBy(F.desc("w"), "dst")
    return build.trade(spark, sf).edges.withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("src", "dst", "w")


def url_hosts(spark: SparkSession, sf: str) -> DataFrame:
    host = F.lower(F.regexp_extract("url", "://([^/?#]+)", 1))
    return table(spark, sf, "pages").groupBy(host.alias("host")).agg(F.count("*").alias("n"))


def hyperlink_edges(spark: SparkSession, sf: str) -> DataFrame:
    return build.hyperlink(spark, sf).edges


def sharedline_edges(spark: SparkSession, sf: str) -> DataFrame:
    return build.sharedline(spark, sf).edges


def string_measures(spark: SparkSession, sf: str) -> DataFrame:
    p = table(spark, sf, "part")
    return p.select("p_partkey", F.levenshtein("p_brand", F.lit("Brand#11")).cast("long").alias("lev"), F.upper(F.substring("p_name", 1, 4)).alias("head"), F.concat_ws("-", "p_brand", "p_type").alias("tag"), F.md5("p_name").alias("digest"))


def monthly_flow(spark: SparkSession, sf: str) -> DataFrame:
    o = table(spark, sf, "orders")
    month = F.date_format("o_orderdate", "yyyy-MM")
    return o.groupBy(month.alias("month"), F.year("o_orderdate").cast("long").alias("y")).agg(F.count("*").alias("n"))


def shipping_delay(spark: SparkSession, sf: str) -> DataFrame:
    lines, orders = table(spark, sf, "lineitem"), table(spark, sf, "orders")
    days = F.datediff("l_shipdate", "o_orderdate").cast("long")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(days.alias("days")).agg(F.count("*").alias("n"))


def hash_parts(spark: SparkSession, sf: str) -> DataFrame:
    c = table(spark, sf, "customer")
    return c.groupBy((mix("c_custkey") % 16).alias("part")).agg(F.count("*").alias("n"), F.round(F.sum(F.sqrt(F.abs("c_acctbal"))), 3).alias("roots"), F.max(F.greatest(F.col("c_acctbal"), F.lit(0.0))).alias("top"))


def neighbour_overlap(spark: SparkSession, sf: str) -> DataFrame:
    lists = build.handoff_strong(spark, sf).symmetrize().edges.groupBy("src").agg(F.collect_set("dst").alias("t"))
    e = build.handoff_strong(spark, sf).edges.where("src < dst").select("src", "dst")
    both = e.join(lists.withColumnRenamed("t", "a"), "src").join(lists.select(F.col("src").alias("dst"), F.col("t").alias("b")), "dst")
    return both.select("src", "dst", F.round(F.size(F.array_intersect("a", "b")) / F.size(F.array_union("a", "b")), 6).alias("jaccard"))


def map_label_counts(spark: SparkSession, sf: str) -> DataFrame:
    counts = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return maps.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, b: a + b).alias("total"), F.size("m").cast("long").alias("kinds"))


def events_json_k(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "events").select(F.from_json("props", "k long").alias("p"), "value")
    return e.groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n"))


def decimal_flow_all(spark: SparkSession, sf: str) -> DataFrame:
    lines = table(spark, sf, "lineitem")
    price = F.col("l_extendedprice").cast("decimal(12,2)")
    return lines.groupBy("l_returnflag").agg(F.sum(price).cast("double").alias("total"), F.count(F.nullif("l_linestatus", F.lit("O"))).alias("closed"), F.count(F.expr("try_cast(l_returnflag AS int)")).alias("numeric"))


def edge_sample(spark: SparkSession, sf: str) -> DataFrame:
    key = F.conv(F.substring(F.md5(F.concat_ws(":", "src", "dst")), 1, 8), 16, 10).cast("long")
    return build.handoff(spark, sf).edges.where(key % 10 == 0).select("src", "dst", "w")


def udf_fold_product(spark: SparkSession, sf: str) -> DataFrame:
    @F.pandas_udf("double")
    def product(x: pd.Series) -> float:
        return float(x.prod())

    return build.trade(spark, sf).edges.withColumn("x", 1 + F.col("w") / 1000).groupBy("src").agg(F.round(product("x"), 6).alias("p"))


def udtf_neighbours(spark: SparkSession, sf: str) -> DataFrame:
    @F.udtf(returnType="dst: bigint")
    class Neighbours:
        def eval(self, targets):
            for t in targets or []:
                yield (t,)

    spark.udtf.register("neighbours", Neighbours)
    build.trade(spark, sf).edges.groupBy("src").agg(F.collect_list("dst").alias("t")).createOrReplaceTempView("trade_lists")
    return spark.sql("SELECT src, n.dst FROM trade_lists, LATERAL neighbours(t) n")


W = "(PARTITION BY user_id ORDER BY ts, event_id"
SUPPLIERS = f"WITH {ctes('purchase')}, d AS (SELECT dst AS id, count(*) AS in_degree FROM e GROUP BY dst), s AS (SELECT d.*, s_nationkey FROM d JOIN supplier ON s_suppkey * 16 + 1 = id)"
QUERIES = {
    "degrees": (degrees, f"WITH {ctes('purchase')} SELECT v.id, (SELECT count(*) FROM e WHERE src = v.id) AS out_degree, (SELECT count(*) FROM e WHERE dst = v.id) AS in_degree FROM v"),
    "weighted_degree": (weighted_degree, f"WITH {ctes('purchase')} SELECT dst AS id, sum(w)::BIGINT AS weight FROM e GROUP BY dst"),
    "adjacency_lists": (adjacency_lists, f"WITH {ctes('trade')} SELECT src, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS targets FROM e GROUP BY src"),
    "distinct_neighbours": (distinct_neighbours, "SELECT l_suppkey AS id, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1"),
    "approx_neighbours": (approx_neighbours, None),
    "approx_neighbours_violations": (approx_neighbours_violations, "SELECT 0::BIGINT AS n"),
    "flow_cube": (flow_cube, FLOW_SQL + " SELECT r_name, c_mktsegment, sum(w)::BIGINT AS lines, grouping_id(r_name, c_mktsegment)::BIGINT AS gid FROM f GROUP BY CUBE (r_name, c_mktsegment)"),
    "flow_rollup": (flow_rollup, FLOW_SQL + " SELECT r_name, n_name, sum(w)::BIGINT AS lines, grouping_id(r_name, n_name)::BIGINT AS gid FROM f GROUP BY ROLLUP (r_name, n_name)"),
    "flow_grouping_sets": (flow_grouping_sets, FLOW_SQL + " SELECT r_name, c_mktsegment, sum(w)::BIGINT AS lines FROM f GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())"),
    "flow_pivot_all": (flow_pivot_all, f"WITH {ctes('trade')} SELECT src, " + ", ".join(f"(sum(w) FILTER (dst = {i}))::BIGINT AS to_{i}" for i in range(25)) + " FROM e GROUP BY src"),
    "degree_having": (degree_having, f"WITH {ctes('handoff')} SELECT src, count(*) AS n, count(*) FILTER (w > 1) AS repeated FROM e GROUP BY src HAVING count(*) FILTER (w > 1) >= 10"),
    "degree_stats": (
        degree_stats,
        f"WITH {ctes('handoff')}, d AS (SELECT a.id, o, i FROM (SELECT src AS id, count(*) AS o FROM e GROUP BY src) a JOIN (SELECT dst AS id, count(*) AS i FROM e GROUP BY dst) b ON a.id = b.id) SELECT round(corr(o, i), 6) AS corr, round(stddev(o), 6) AS sd, round(regr_slope(i, o), 6) AS slope FROM d",
    ),
    "presence_bitmap": (
        presence_bitmap,
        f"WITH {ctes('purchase')} SELECT dst AS id, bit_or(1::BIGINT << (({mix_sql('src')} * 31 + {mix_sql('dst')}) % 1000003 % 16)::INT)::BIGINT AS bits, bit_count(bit_or(1::BIGINT << (({mix_sql('src')} * 31 + {mix_sql('dst')}) % 1000003 % 16)::INT))::BIGINT AS parts FROM e GROUP BY dst",
    ),
    "rank_hubs": (
        rank_hubs,
        SUPPLIERS + " SELECT id, s_nationkey, row_number() OVER (PARTITION BY s_nationkey ORDER BY in_degree DESC, id) AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM s WINDOW w AS (PARTITION BY s_nationkey ORDER BY in_degree DESC)",
    ),
    "ntile_degrees": (ntile_degrees, SUPPLIERS + " SELECT id, ntile(3) OVER (PARTITION BY s_nationkey ORDER BY in_degree, id) AS third FROM s"),
    "handoff_edges": (handoff_edges, f"WITH {ctes('handoff')} SELECT src, dst, w FROM e"),
    "lag_gap": (
        lag_gap,
        f"SELECT event_id, epoch_us(ts) - lag(epoch_us(ts)) OVER {W}) AS gap, first(event_id) OVER {W}) AS first_id, last(event_id) OVER {W} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_id, nth_value(event_id, 2) OVER {W} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_id FROM events",
    ),
    "csr_offsets": (csr_offsets, f"WITH {ctes('trade')}, d AS (SELECT src AS id, count(*) AS out_degree FROM e GROUP BY src) SELECT id, coalesce(sum(out_degree) OVER (ORDER BY id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS \"offset\", out_degree FROM d"),
    "moving_value_rows": (moving_value_rows, f"SELECT event_id, round(sum(value) OVER {W} ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS moving FROM events"),
    "moving_value_range": (moving_value_range, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day_count FROM events"),
    "sessions_by_gap": (
        sessions_by_gap,
        f"WITH g AS (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER {W}) <= 7200000000 THEN 0 ELSE 1 END AS fresh FROM events), n AS (SELECT *, (sum(fresh) OVER {W}))::BIGINT AS session FROM g) SELECT user_id, session, count(*) AS n, min(event_id) AS first_id FROM n GROUP BY user_id, session",
    ),
    "top_ranks": (top_ranks, SUPPLIERS + " SELECT id, in_degree FROM d ORDER BY in_degree DESC, id LIMIT 20"),
    "sorted_page": (sorted_page, SUPPLIERS + " SELECT id, in_degree FROM d ORDER BY in_degree DESC, id LIMIT 10 OFFSET 10"),
    "topk_per_group": (topk_per_group, f"WITH {ctes('trade')} SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS rn FROM e) WHERE rn <= 3"),
    "url_hosts": (url_hosts, "SELECT lower(regexp_extract(url, '://([^/?#]+)', 1)) AS host, count(*) AS n FROM pages GROUP BY 1"),
    "hyperlink_edges": (hyperlink_edges, f"WITH {ctes('hyperlink')} SELECT src, dst FROM e"),
    "sharedline_edges": (sharedline_edges, f"WITH {ctes('sharedline')} SELECT src, dst FROM e"),
    "string_measures": (string_measures, "SELECT p_partkey, levenshtein(p_brand, 'Brand#11')::BIGINT AS lev, upper(substr(p_name, 1, 4)) AS head, concat_ws('-', p_brand, p_type) AS tag, md5(p_name) AS digest FROM part"),
    "monthly_flow": (monthly_flow, "SELECT strftime(o_orderdate, '%Y-%m') AS month, year(o_orderdate)::BIGINT AS y, count(*) AS n FROM orders GROUP BY 1, 2"),
    "shipping_delay": (shipping_delay, "SELECT date_diff('day', o_orderdate::DATE, l_shipdate::DATE) AS days, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"),
    "hash_parts": (hash_parts, f"SELECT {mix_sql('c_custkey')} % 16 AS part, count(*) AS n, round(sum(sqrt(abs(c_acctbal))), 3) AS roots, max(greatest(c_acctbal, 0.0)) AS top FROM customer GROUP BY 1"),
    "neighbour_overlap": (
        neighbour_overlap,
        f"WITH {ctes('handoff_strong')}, u AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e), n AS (SELECT src, count(*) AS d FROM u GROUP BY src), p AS (SELECT src, dst FROM e WHERE src < dst), i AS (SELECT p.src, p.dst, count(b.dst) AS k FROM p JOIN u a ON a.src = p.src LEFT JOIN u b ON b.src = p.dst AND b.dst = a.dst GROUP BY 1, 2) SELECT i.src, i.dst, round(k / (x.d + y.d - k), 6) AS jaccard FROM i JOIN n x ON x.src = i.src JOIN n y ON y.src = i.dst",
    ),
    "map_label_counts": (map_label_counts, "SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(*) AS total, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id"),
    "events_json_k": (events_json_k, "SELECT (props->>'k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1"),
    "decimal_flow_all": (decimal_flow_all, "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(12,2))::DOUBLE AS total, count(nullif(l_linestatus, 'O')) AS closed, count(try_cast(l_returnflag AS INT)) AS numeric FROM lineitem GROUP BY 1"),
    "edge_sample": (edge_sample, f"WITH {ctes('handoff')} SELECT src, dst, w FROM e WHERE ('0x' || substr(md5(src || ':' || dst), 1, 8))::BIGINT % 10 = 0"),
    "udf_fold_product": (udf_fold_product, f"WITH {ctes('trade')} SELECT src, round(product(1 + w / 1000), 6) AS p FROM e GROUP BY src"),
    "udtf_neighbours": (udtf_neighbours, f"WITH {ctes('trade')} SELECT src, dst FROM e"),
}
