"""The engine's tables as temporary views, for queries written in SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession


def register_views(spark: SparkSession, sf_dir: str) -> list[str]:
    """feed_samples, feed_tuples, feed_runs, feed_shard_stats, feed_shard_index and feed_plan over the tables of sf_dir."""
    from .operators import shards as H
    from .plans import energy_queries as EQ, feed_queries as Q
    from .sources.tables import records, samples

    views = {
        "feed_samples": samples(spark, sf_dir), "feed_tuples": EQ.tuples(spark, sf_dir), "feed_runs": EQ.runs(spark, sf_dir),
        "feed_shard_stats": Q.stats(spark, sf_dir), "feed_shard_index": H.shard_index(records(spark, sf_dir, "documents")), "feed_plan": Q.plan(spark, sf_dir, scope="worker"),
    }
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    return list(views)
