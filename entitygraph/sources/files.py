"""Files of unlike layouts merged into one record set, and the link index as a sink."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.errors import DuplicateIdError


@dataclass(frozen=True)
class SourceSpec:
    """data: a DataFrame or a path; key: the column that is unique within the source, or several."""

    data: DataFrame | str
    name: str
    key: str | tuple[str, ...]
    fmt: str = "parquet"


def merge_files(spark: SparkSession, specs: list[SourceSpec]) -> DataFrame:
    """record_id ('source:key'), source and attrs, a map of all other columns as text; nulls are left out. Narrow: no shuffle."""
    out = None
    for s in specs:
        df = spark.read.format(s.fmt).load(s.data) if isinstance(s.data, str) else s.data
        keys = (s.key,) if isinstance(s.key, str) else s.key
        pairs = [F.struct(F.lit(c).alias("key"), F.col(c).cast("string").alias("value")) for c in df.columns if c not in keys]
        attrs = F.map_from_entries(F.filter(F.array(*pairs), lambda p: p["value"].isNotNull()))
        one = df.select(F.concat_ws(":", F.lit(s.name), *[F.col(k).cast("string") for k in keys]).alias("record_id"), F.lit(s.name).alias("source"), attrs.alias("attrs"))
        out = one if out is None else out.unionByName(one)
    return out


def assert_unique_ids(df: DataFrame, column: str = "record_id") -> DataFrame:
    twice = df.groupBy(column).count().where("count > 1").limit(1).collect()
    if twice:
        raise DuplicateIdError(f"{column} {twice[0][0]!r} occurs {twice[0][1]} times")
    return df


def assign_ids(df: DataFrame) -> DataFrame:
    """An id from the content of all columns, the same on every retry."""
    return df.withColumn("record_id", F.sha2(F.to_json(F.struct(*df.columns)), 256))


def write_link_index(clusters: DataFrame, path: str, fmt: str = "parquet", overwrite: bool = False) -> None:
    """(cluster_id, record_id) pairs, sorted within ranges of the cluster id."""
    out = clusters.select("cluster_id", "record_id").repartitionByRange("cluster_id", "record_id").sortWithinPartitions("cluster_id", "record_id")
    out.write.mode("overwrite" if overwrite else "errorifexists").format(fmt).option("header", True).save(path)


def read_link_index(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    return spark.read.format(fmt).option("header", True).schema("cluster_id string, record_id string").load(path)
