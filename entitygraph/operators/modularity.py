"""Modularity of partitions, gains of moves, and contraction, as DataFrame aggregates.

Edges are (component_id, u, v, w), undirected, once each; a loop (u = v) counts once in the inside weight and twice in the degree.
Assignments are (component_id, record_id, community)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entitygraph.errors import LocalCapExceeded


def component_edges(scored: DataFrame, components: DataFrame, refine_edges: str = "scored", mu: float | None = None) -> DataFrame:
    """The scored pairs inside one component: the complete graph without the pairs that were never scored, which never exists as such."""
    if refine_edges == "above_mu":
        scored = scored.where(F.col("score") >= mu)
    left = components.select(F.col("record_id").alias("a"), "component_id")
    right = components.select(F.col("record_id").alias("b"), F.col("component_id").alias("cb"))
    inside = scored.join(left, "a").join(right, "b").where("component_id = cb")
    return inside.select("component_id", F.col("a").alias("u"), F.col("b").alias("v"), F.col("score").alias("w"))


def degrees(edges: DataFrame) -> DataFrame:
    ends = edges.select("component_id", F.col("u").alias("record_id"), "w").union(edges.select("component_id", F.col("v").alias("record_id"), "w"))
    return ends.groupBy("component_id", "record_id").agg(F.sum("w").alias("k"))


def modularity(edges: DataFrame, assign: DataFrame, weighted: bool = True, resolution: float = 1.0, total: float | None = None) -> DataFrame:
    """component_id, m: sum over communities of inside share less the squared degree share; components without weight are left out.
    ``total`` is the weight of a whole graph that the components are parts of; else each is a graph of its own."""
    if not weighted:
        edges = edges.withColumn("w", F.lit(1.0))
    left = assign.select("component_id", F.col("record_id").alias("u"), F.col("community").alias("cu"))
    right = assign.select("component_id", F.col("record_id").alias("v"), F.col("community").alias("cv"))
    placed = edges.join(left, ["component_id", "u"]).join(right, ["component_id", "v"])
    halves = placed.select("component_id", F.explode(F.array(
        F.struct(F.col("cu").alias("c"), F.when(F.col("cu") == F.col("cv"), F.col("w")).otherwise(0.0).alias("inside"), F.col("w").alias("d")),
        F.struct(F.col("cv").alias("c"), F.lit(0.0).alias("inside"), F.col("w").alias("d")),
    )).alias("x"))
    per = halves.groupBy("component_id", "x.c").agg(F.sum("x.inside").alias("inside"), F.sum("x.d").alias("d"))
    whole = edges.groupBy("component_id").agg((F.sum("w") if total is None else F.lit(float(total))).alias("total"))
    share = F.col("inside") / F.col("total") - F.lit(resolution) * F.pow(F.col("d") / (2 * F.col("total")), 2)
    return per.join(whole.where("total > 0"), "component_id").groupBy("component_id").agg(F.sum(share).alias("m"))


def modularity_dense(edges: DataFrame, assign: DataFrame, max_nodes: int = 2000) -> DataFrame:
    """The double sum over ordered pairs of nodes, for reference on graphs without loops; refuses components of more than ``max_nodes`` nodes."""
    largest = assign.groupBy("component_id").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
    if largest > max_nodes:
        raise LocalCapExceeded(f"{largest} nodes, at most {max_nodes} for the double sum")
    k = degrees(edges)
    whole = edges.groupBy("component_id").agg(F.sum("w").alias("total"))
    nodes = assign.join(k, ["component_id", "record_id"])
    left = nodes.select("component_id", F.col("record_id").alias("i"), F.col("community").alias("ci"), F.col("k").alias("ki"))
    right = nodes.select("component_id", F.col("record_id").alias("j"), F.col("community").alias("cj"), F.col("k").alias("kj"))
    both = edges.select("component_id", F.col("u").alias("i"), F.col("v").alias("j"), "w").union(edges.select("component_id", F.col("v").alias("i"), F.col("u").alias("j"), "w"))
    same = left.join(right, "component_id").where("ci = cj").join(both, ["component_id", "i", "j"], "left").join(whole, "component_id")
    term = F.coalesce("w", F.lit(0.0)) - F.col("ki") * F.col("kj") / (2 * F.col("total"))
    return same.groupBy("component_id").agg((F.sum(term) / (2 * F.max("total"))).alias("m"))


def move_gain(k_i, k_to, d_to, k_own, d_own, total, resolution: float = 1.0):
    """Gain of moving a node from its community to another; d_own leaves the node out, and k_to, k_own are its links to either. For columns and for numbers alike."""
    return (k_to - k_own) / total - resolution * k_i * (d_to - d_own) / (2 * total * total)


def contract(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Communities become nodes, weights add up, inner weight becomes a loop."""
    left = assign.select("component_id", F.col("record_id").alias("u"), F.col("community").alias("cu"))
    right = assign.select("component_id", F.col("record_id").alias("v"), F.col("community").alias("cv"))
    placed = edges.join(left, ["component_id", "u"]).join(right, ["component_id", "v"])
    return placed.groupBy("component_id", F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).agg(F.sum("w").alias("w"))


def graph_profile(edges: DataFrame) -> DataFrame:
    """Per component: nodes, edges, density, largest degree, triangles (each counted once, from its node of the least degree on, so that a hub is nobody's first node)."""
    e = edges.select("component_id", F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).where("u != v").distinct()
    ends = e.select("component_id", F.col("u").alias("x")).union(e.select("component_id", F.col("v").alias("x")))
    deg = ends.groupBy("component_id", "x").agg(F.count("*").alias("d"))
    nodes = deg.groupBy("component_id").agg(F.count("*").alias("nodes"), F.max("d").alias("max_degree"))
    count = e.groupBy("component_id").agg(F.count("*").alias("edges"))
    ends_of = lambda x: deg.select("component_id", F.col("x").alias(x), F.col("d").alias(f"d{x}"))
    ranked = e.join(ends_of("u"), ["component_id", "u"]).join(ends_of("v"), ["component_id", "v"])
    up = (F.col("du") < F.col("dv")) | ((F.col("du") == F.col("dv")) & (F.col("u") < F.col("v")))
    e = ranked.select("component_id", F.when(up, F.col("u")).otherwise(F.col("v")).alias("u"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("v"))
    paths = e.join(e.select("component_id", F.col("u").alias("v"), F.col("v").alias("x")), ["component_id", "v"])
    closed = paths.join(e.select("component_id", "u", F.col("v").alias("x")), ["component_id", "u", "x"])
    triangles = closed.groupBy("component_id").agg(F.count("*").alias("triangles"))
    return (
        nodes.join(count, "component_id").join(triangles, "component_id", "left")
        .select("component_id", "nodes", "edges", F.round(2 * F.col("edges") / (F.col("nodes") * (F.col("nodes") - 1)), 6).alias("density"), "max_degree", F.coalesce("triangles", F.lit(0)).alias("triangles"))
    )
