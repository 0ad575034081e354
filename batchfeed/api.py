"""One object over a folder of tables, for use from programs and the command line."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from .config import FEED, HOUR_US, MODEL_A, Feed, Power
from .operators import energy as E, loaders as L, measures as M, planner as P, shards as H
from .plans.catalog import ORACLES, QUERIES
from .plans import feed_queries as Q
from .sources.tables import records, regimes, samples
from .sql import register_views


@dataclass
class Engine:
    """Energy accounting, planning and loader comparison over the tables in sf_dir."""

    spark: SparkSession
    sf_dir: str
    feed: Feed = FEED
    power: Power = MODEL_A

    def energy(self, delta_us: int = HOUR_US, **options) -> DataFrame:
        """Gap-free component energies by node and slot."""
        return E.tuples(samples(self.spark, self.sf_dir), delta_us, **options)

    def interval_energy(self, intervals: DataFrame, delta_us: int = HOUR_US, **options) -> DataFrame:
        """Energy of intervals(run_id, node_id, start_us, end_us)."""
        return E.interval_energy(self.energy(delta_us), intervals, delta_us, **options)

    def shard_index(self, name: str = "documents") -> DataFrame:
        return H.shard_index(records(self.spark, self.sf_dir, name), self.feed.header)

    def plan(self, name: str = "documents", scope: str = "shard", split: str = "striped", coverage: str = "partition", tail: str = "keep") -> DataFrame:
        """The batch plan of all epochs."""
        stats = H.shard_stats(records(self.spark, self.sf_dir, name), self.feed.header)
        nodes = P.assign_nodes(P.shuffle_shards(stats, self.feed.epochs, self.feed.seed), self.feed.nodes, coverage)
        return P.batch_plan(P.assign_workers(nodes, self.feed.workers, split), self.feed.batch, scope, tail, self.feed.workers)

    def compare(self, name: str = "documents", rtts: tuple[str, ...] = ("local", "lan", "lan_10", "wan"), loaders: tuple[str, ...] = Q.ALL, scope: str = "shard") -> DataFrame:
        """Modelled time and energy of each loader at each round trip."""
        batches = P.batches(P.with_bytes(self.plan(name, scope), self.shard_index(name), self.feed.header))
        return L.cells(batches, regimes(self.spark, *rtts), self.feed, self.power, loaders)

    def speedup(self, **options) -> DataFrame:
        return M.speedup(self.compare(**options))

    def sql(self, text: str) -> DataFrame:
        """A query over the views of `sql.register_views`."""
        register_views(self.spark, self.sf_dir)
        return self.spark.sql(text)

    def query(self, name: str) -> DataFrame:
        """A query of the catalogue."""
        return QUERIES[name](self.spark, self.sf_dir)

    @staticmethod
    def oracle(name: str) -> str | None:
        return ORACLES.get(name)
