"""All queries of the spatial engine and their SQL oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from cellfleet.plans import batch_queries, fleet_queries, index_queries, operator_queries, study_queries, variant_queries  # noqa: F401  (they register themselves)
from cellfleet.plans.registry import ORACLES, QUERIES


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The snapshot index on uniform points, answering 20 range queries."""
    from pyspark.sql import functions as F

    from cellfleet.operators import pivots, range_query
    from cellfleet.sources import views

    pts = views.uniform(spark, sf_dir)
    queries_ = views.uniform_queries(spark, sf_dir, 20).withColumn("r", F.lit(400_000.0))
    return range_query.run(pts, queries_, pivots.choose(pts, 8))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLES
