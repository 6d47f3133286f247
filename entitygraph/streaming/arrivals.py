"""References that arrive in batches: each batch is blocked against all that is stored, its matches are added, and only touched components are closed again."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.operators import blocking, matching, parsing
from entitygraph.operators.closure import connected_components
from entitygraph.plans.pipeline import ResolveConfig
from entitygraph.shared import materialise, new_path

RECORDS = "record_id string, body string"


class IncrementalLinkIndex:
    """Tables under one folder, a part for each batch: ``tokens``, ``edges``, and the ``labels`` that stand after it. A batch that is tried again replaces its own parts.

    A token's frequency is that at arrival: pairs that were found stay, however common their tokens become. In one batch the result is that of the closure pipeline."""

    def __init__(self, spark: SparkSession, cfg: ResolveConfig = ResolveConfig(), folder: str | None = None):
        self.spark, self.cfg, self.folder = spark, cfg, folder or new_path(spark, "arrivals")
        self.batches: list[int] = []

    def _part(self, table: str, batch: int) -> str:
        return f"{self.folder}/{table}/batch={batch}"

    def _all(self, table: str, schema: str) -> DataFrame:
        if not self.batches:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*[self._part(table, b) for b in self.batches])

    def add(self, batch: DataFrame, number: int) -> None:
        cfg, spark = self.cfg, self.spark
        before = [b for b in self.batches if b < number]
        self.batches = before
        labels = spark.read.parquet(self._part("labels", before[-1])) if before else spark.createDataFrame([], "component_id string, record_id string")
        parsing.explode_tokens(batch).write.mode("overwrite").parquet(self._part("tokens", number))
        self.batches = [*before, number]
        tokens = self._all("tokens", "record_id string, pos int, token string")
        new = materialise(batch.select("record_id").distinct(), "new")
        kept = materialise(blocking.cut_stop_tokens(tokens, parsing.token_frequencies(tokens), cfg.sigma, cfg.bounds), "kept")
        blocked = blocking.blocking_tokens(kept, cfg.beta, cfg.bounds)
        fresh = blocked.join(new, "record_id", "left_semi").select("token").distinct()
        pairs = blocking.candidate_pairs(blocking.blocks(blocked.join(fresh, "token", "left_semi")))
        told = pairs.join(new.select(F.col("record_id").alias("a"), F.lit(1).alias("na")), "a", "left").join(new.select(F.col("record_id").alias("b"), F.lit(1).alias("nb")), "b", "left")
        scored = matching.match_pairs(told.where("na = 1 or nb = 1").select("a", "b"), blocking.filtered_records(kept), cfg.measure, cfg.max_tokens)
        matching.above(scored, cfg.mu).write.mode("overwrite").parquet(self._part("edges", number))
        edges = spark.read.parquet(self._part("edges", number)).select("a", "b")
        ends = edges.select(F.col("a").alias("record_id")).union(edges.select(F.col("b").alias("record_id"))).distinct()
        touched = materialise(labels.join(ends, "record_id", "left_semi").select("component_id").distinct(), "touched")
        rays = labels.join(touched, "component_id", "left_semi").where("component_id != record_id").select(F.col("component_id").alias("a"), F.col("record_id").alias("b"))
        closed = connected_components(rays.union(edges), cfg.closure_method)
        same = labels.join(touched, "component_id", "left_anti").select("component_id", "record_id")
        same.unionByName(closed).write.mode("overwrite").parquet(self._part("labels", number))

    def link_index(self) -> DataFrame:
        """cluster_id, record_id of every record that has arrived with a token."""
        records = self._all("tokens", "record_id string, pos int, token string").select("record_id").distinct()
        labels = self.spark.read.parquet(self._part("labels", self.batches[-1]))
        return records.join(labels, "record_id", "left").select(F.coalesce("component_id", "record_id").alias("cluster_id"), "record_id")


def link_index_of_stream(spark: SparkSession, folder: str, cfg: ResolveConfig = ResolveConfig(), files_a_batch: int = 1) -> DataFrame:
    """The link index of references that arrive as Parquet files in a folder, so many files a batch."""
    index = IncrementalLinkIndex(spark, cfg)
    stream = spark.readStream.schema(RECORDS).option("maxFilesPerTrigger", files_a_batch).parquet(folder)
    query = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", new_path(spark, "stream-state")).foreachBatch(index.add).start()
    query.awaitTermination()
    return index.link_index()
