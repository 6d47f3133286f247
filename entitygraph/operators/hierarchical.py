"""The two-step clusterer: closure into soft clusters, then modularity refinement of each."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entitygraph.operators.closure import closure, connected_components
from entitygraph.operators.louvain import RefineConfig, refine_large, refine_local
from entitygraph.operators.modularity import component_edges
from entitygraph.shared import materialise


def refine(edges: DataFrame, cfg: RefineConfig = RefineConfig()) -> DataFrame:
    """component_id, record_id, community, m; large components over arrays or by the distributed form. Components of one edge have nothing to split and never reach Python."""
    sizes = materialise(edges.groupBy("component_id").agg(F.count("*").alias("n_edges")), "sizes")
    sized = edges.join(sizes, "component_id")
    local = (F.col("n_edges") > 1) & (F.col("n_edges") <= cfg.local_edge_cap)
    n_edges = sizes.where(local).agg(F.sum("n_edges")).first()[0] or 0
    small = refine_local(sized.where(local).drop("n_edges"), cfg, n_edges=n_edges).select("component_id", "record_id", "community", "m")
    large = sizes.where(F.col("n_edges") > cfg.local_edge_cap)
    if large.limit(1).count():
        big = refine_large(edges, large, cfg)
        small = small.unionByName(big.select("component_id", "record_id", "community", "m"))
    return small


def accept_or_collapse(refined: DataFrame) -> DataFrame:
    """Refined communities where modularity is positive, else the whole component."""
    return refined.select("component_id", "record_id", F.when(F.col("m") > 0, F.col("community")).otherwise(F.col("component_id")).alias("community"))


def rename_to_least(assign: DataFrame) -> DataFrame:
    least = assign.groupBy("component_id", "community").agg(F.min("record_id").alias("cluster_id"))
    return assign.join(least, ["component_id", "community"]).select("cluster_id", "record_id")


def with_singletons(clusters: DataFrame, records: DataFrame) -> DataFrame:
    """Records that no pair mentions are clusters of their own."""
    alone = records.select("record_id").join(clusters.select("record_id"), "record_id", "left_anti")
    return clusters.union(alone.select(F.col("record_id").alias("cluster_id"), "record_id"))


def isolated_nodes(components: DataFrame, edges: DataFrame) -> DataFrame:
    """Members of a component that its edge set leaves without an edge."""
    ends = edges.select(F.col("u").alias("record_id")).union(edges.select(F.col("v").alias("record_id")))
    return components.join(ends.distinct(), "record_id", "left_anti")


def cluster_hierarchical(scored: DataFrame, records: DataFrame, mu: float, cfg: RefineConfig = RefineConfig(), refine_edges: str = "scored", method: str = "alternating_star") -> DataFrame:
    """cluster_id, record_id: every record once; cluster_id is the cluster's least record."""
    components = materialise(closure(scored, mu, method), "soft")
    edges = materialise(component_edges(scored, components, refine_edges, mu), "inside")
    refined = materialise(accept_or_collapse(refine(edges, cfg)), "refined")
    left = components.join(refined.select("record_id"), "record_id", "left_anti")
    rest = left.select("component_id", "record_id", F.col("component_id").alias("community"))
    return with_singletons(rename_to_least(refined.unionByName(rest)), records)


def cluster_closure(scored: DataFrame, records: DataFrame, mu: float, method: str = "alternating_star") -> DataFrame:
    """Closure alone."""
    return with_singletons(closure(scored, mu, method).select(F.col("component_id").alias("cluster_id"), "record_id"), records)


def cluster_modularity(scored: DataFrame, records: DataFrame, cfg: RefineConfig = RefineConfig()) -> DataFrame:
    """Refinement alone, over the whole graph; collapse does not apply. A node only ever moves to a neighbour's community, and all that a move needs of the rest of the graph is its
    weight: so the parts that no edge joins are searched by themselves, with the weight of the whole, and nothing is gathered in one task."""
    components = materialise(connected_components(scored.select("a", "b")), "parts")
    edges = materialise(component_edges(scored, components), "graph")
    whole = edges.agg(F.sum("w") if cfg.weighted else F.count("*").cast("double")).first()[0] or 0.0
    sizes = materialise(edges.groupBy("component_id").agg(F.count("*").alias("n_edges")), "sizes")
    big = sizes.where(F.col("n_edges") > cfg.local_edge_cap)
    found = refine_local(edges.join(big.select("component_id"), "component_id", "left_anti"), cfg, whole=whole).select("component_id", "record_id", "community")
    if big.limit(1).count():
        found = found.unionByName(refine_large(edges, big, cfg, whole).select("component_id", "record_id", "community"))
    return with_singletons(rename_to_least(found.select("component_id", "record_id", "community")), records)
