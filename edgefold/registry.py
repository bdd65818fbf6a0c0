"""All queries of the graph library and their SQL twins, by name."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import methods, workloads
from .graph import build
from .oracles.graphs import ctes
from .oracles.methods import ORACLES
from .relational import aggregates, joins
from .streaming import queries as streams

Query = Callable[[SparkSession, str], DataFrame]
PAIRS = {**joins.QUERIES, **aggregates.QUERIES, **streams.QUERIES}
#: The reference's experiments; times and loader-dependent cuts have no SQL twin.
WORKLOADS: dict[str, Query] = {
    "workload_rank_engines": lambda spark, sf: workloads.rank_engines(spark, build.handoff(spark, sf), (4,)),
    "workload_weak_scaling": lambda spark, sf: workloads.weak_scaling(spark, (8, 10)),
    "workload_weak_scaling_slopes": lambda spark, sf: workloads.weak_scaling_slopes(spark, (12, 14, 16)),
    "workload_strong_scaling": lambda spark, sf: workloads.strong_scaling(spark, 14),
    "workload_engines_social": lambda spark, sf: workloads.program_engines(spark, build.handoff(spark, sf)),
    "workload_engines_web": lambda spark, sf: workloads.program_engines(spark, build.hyperlink(spark, sf)),
    "workload_rank_engines_web": lambda spark, sf: workloads.rank_engines(spark, build.hyperlink(spark, sf), (2, 4, 8, 16)),
    "workload_compute_share": lambda spark, sf: workloads.compute_shares(spark, build.handoff(spark, sf)),
    "workload_cut_factors_social_12": lambda spark, sf: workloads.cut_factors(spark, build.handoff(spark, sf), (12,)),
    "workload_cut_factors_purchase": lambda spark, sf: workloads.cut_factors(spark, build.purchase(spark, sf), (2, 4, 8, 12, 16)),
    "workload_cut_factors_social": lambda spark, sf: workloads.cut_factors(spark, build.handoff(spark, sf), (2, 4, 8, 16)),
    "workload_cut_factors_web": lambda spark, sf: workloads.cut_factors(spark, build.hyperlink(spark, sf), (2, 4, 8, 16)),
    "workload_cut_table": lambda spark, sf: workloads.cut_table(spark, sf, 16),
    "workload_capacity": lambda spark, sf: workloads.capacity_rows(spark, sf),
}
CAPACITY = " UNION ALL ".join(
    f"""SELECT * FROM (WITH {ctes(g)} SELECT '{g}' AS graph, v::DOUBLE AS vertices, e::DOUBLE AS edges, (80 * v + 4 * e) / 1e9 AS one_sided_gb, (2 * (80 * v + 4 * e) + 16 * e) / 1e9 AS split_gb
FROM (SELECT (SELECT count(*) FROM v) AS v, (SELECT count(*) FROM e) AS e))"""
    for g in workloads.CAPACITY_GRAPHS
)


def queries() -> dict[str, Query]:
    return {**methods.QUERIES, **{n: f for n, (f, _) in PAIRS.items()}, **WORKLOADS}


def oracle_sql() -> dict[str, str]:
    return {**ORACLES, **{n: s for n, (_, s) in PAIRS.items() if s}, "workload_capacity": CAPACITY}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, rank_e9, events): the 20 highest exact ranks of the hand-off graph with their users' event counts."""
    from pyspark.sql import functions as F

    ranks = methods.pagerank_scaled_10(spark, sf_dir)
    events = methods.build.table(spark, sf_dir, "events").groupBy(F.col("user_id").cast("long").alias("id")).agg(F.count("*").alias("events"))
    return ranks.join(events, "id").orderBy(F.desc("rank_e9"), "id").limit(20)
