"""Entropy quality of clusters: 1 where all records say the same, 0 where they share no token."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def entropy_quality(clusters: DataFrame, tokens: DataFrame) -> DataFrame:
    """cluster_id, n, entropy, quality. The token entropy of a cluster lies between that of one record's worth of distinct
    tokens and that of all its tokens being distinct; quality is how near it is to the former."""
    placed = clusters.join(tokens, "record_id", "left")
    counts = placed.where("token is not null").groupBy("cluster_id", "token").agg(F.count("*").alias("c"))
    sums = counts.groupBy("cluster_id").agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2("c")).alias("clogc"))
    sizes = clusters.groupBy("cluster_id").agg(F.count("*").alias("n"))
    h = F.log2("t") - F.col("clogc") / F.col("t")
    low, high = F.log2(F.col("t") / F.col("n")), F.log2("t")
    share = F.greatest(F.lit(0.0), F.least(F.lit(1.0), 1 - (h - low) / (high - low)))
    return sizes.join(sums, "cluster_id", "left").select(
        "cluster_id", "n", F.round(F.coalesce(h, F.lit(0.0)), 6).alias("entropy"), F.round(F.when((F.col("n") == 1) | F.col("t").isNull(), 1.0).otherwise(share), 6).alias("quality")
    )
