"""Transitive closure: connected components of an undirected edge table, by four methods that agree."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entitygraph.errors import ClosureDidNotConverge, LocalCapExceeded
from entitygraph.shared import discard, materialise

METHODS = ("alternating_star", "star_merge", "min_label", "local")


def canonical_edges(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(a, b) with a < b, once each; loops and null ends are left out."""
    return (
        edges.where(F.col(a) != F.col(b))
        .select(F.least(a, b).alias("a"), F.greatest(a, b).alias("b"))
        .distinct()
    )


def stars(edges: DataFrame) -> DataFrame:
    """Every edge as a ray from its smaller end: (center, member), with the center as a member of its own star."""
    rays = edges.select(F.least("a", "b").alias("center"), F.greatest("a", "b").alias("member")).distinct()
    return rays.union(rays.select("center", F.col("center").alias("member")).distinct())


def _both_ways(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("a").alias("v"), F.col("b").alias("n")).union(
        edges.select(F.col("b").alias("v"), F.col("a").alias("n"))
    )


def _fingerprint(edges: DataFrame) -> tuple:
    row = edges.agg(
        F.count("*").alias("n"),
        F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("s"),
    ).first()
    return row["n"], row["s"]


def _large_star(edges: DataFrame) -> DataFrame:
    """Each vertex links its larger neighbours to the least vertex it knows."""
    both = _both_ways(edges)
    least = both.groupBy("v").agg(F.min("n").alias("m")).select("v", F.least("v", "m").alias("m"))
    linked = both.where(F.col("n") > F.col("v")).join(least, "v")
    return linked.select(F.col("m").alias("a"), F.col("n").alias("b")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Each vertex links itself and its smaller neighbours to the least of them."""
    down = edges.select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("n"))
    least = down.groupBy("v").agg(F.min("n").alias("m"))
    others = down.join(least, "v").where(F.col("n") != F.col("m")).select(F.col("m").alias("a"), F.col("n").alias("b"))
    own = least.select(F.col("m").alias("a"), F.col("v").alias("b"))
    return others.union(own).distinct()


def _iterate(edges: DataFrame, step, max_rounds: int) -> tuple[DataFrame, int]:
    current, seen = edges, _fingerprint(edges)
    for done in range(1, max_rounds + 1):
        if seen[0] == 0:
            return current, done - 1
        before, current = current, materialise(step(current), "closure")
        now = _fingerprint(current)
        discard(before)
        if now == seen:
            return current, done
        seen = now
    raise ClosureDidNotConverge(f"no fixed point within {max_rounds} rounds")


def _star_merge(edges: DataFrame) -> DataFrame:
    """One round of the star merge: all that a vertex sees moves to the least vertex in its neighbourhood."""
    both = _both_ways(edges)
    least = both.groupBy("v").agg(F.min("n").alias("m")).select("v", F.least("v", "m").alias("m"))
    moved = both.join(least, "v")
    return canonical_edges(
        moved.select(F.col("m").alias("a"), F.col("n").alias("b")).union(least.select(F.col("m").alias("a"), F.col("v").alias("b")))
    )


def _members(star_edges: DataFrame) -> DataFrame:
    rays = star_edges.select(F.col("a").alias("component_id"), F.col("b").alias("record_id"))
    return rays.union(rays.select("component_id", F.col("component_id").alias("record_id")).distinct())


def _min_label(edges: DataFrame, max_rounds: int) -> DataFrame:
    both = materialise(_both_ways(edges), "labels")
    labels = materialise(both.groupBy("v").agg(F.least(F.min("n"), F.col("v")).alias("l")), "labels")
    for _ in range(max_rounds):
        heard = both.join(labels.select(F.col("v").alias("n"), "l"), "n").groupBy("v").agg(F.min("l").alias("h"))
        new = materialise(
            labels.select("v", "l").join(heard, "v").select("v", F.least("l", "h").alias("l"), (F.col("h") < F.col("l")).alias("changed")), "labels"
        )
        discard(labels)
        if new.where("changed").limit(1).count() == 0:
            return new.select(F.col("l").alias("component_id"), F.col("v").alias("record_id"))
        labels = new
    raise ClosureDidNotConverge(f"no fixed point within {max_rounds} rounds")


def _local(edges: DataFrame, cap: int) -> DataFrame:
    n = edges.count()
    if n > cap:
        raise LocalCapExceeded(f"{n} edges, at most {cap} for the in-memory form")
    kind = edges.schema["a"].dataType.simpleString()

    def union_find(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        parent: dict = {}

        def root(x):
            parent.setdefault(x, x)
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for rows in batches:
            for x, y in zip(rows["a"], rows["b"], strict=True):
                rx, ry = root(x), root(y)
                if rx != ry:
                    parent[max(rx, ry)] = min(rx, ry)
        members = list(parent)
        yield pd.DataFrame({"component_id": [root(x) for x in members], "record_id": members})

    return edges.coalesce(1).mapInPandas(union_find, f"component_id {kind}, record_id {kind}")


def connected_components(edges: DataFrame, method: str = "alternating_star", max_rounds: int = 50, local_cap: int = 2_000_000) -> DataFrame:
    """(component_id, record_id) for every vertex that has an edge; component_id is the least vertex of the component.

    ``alternating_star`` keeps hubs small and needs O(log^2 n) rounds; ``star_merge`` is the adapted closure; ``min_label``
    needs as many rounds as the diameter; ``local`` runs union-find in one task and refuses more than ``local_cap`` edges.
    An empty table gives an empty result; repeated edges and loops change nothing."""
    if method not in METHODS:
        raise ValueError(f"method must be one of {METHODS}")
    edges = canonical_edges(edges)
    if method == "local":
        return _local(edges, local_cap)
    edges = materialise(edges, "closure")
    if method == "min_label":
        return _min_label(edges, max_rounds)
    step = (lambda e: _small_star(_large_star(e))) if method == "alternating_star" else _star_merge
    final, _ = _iterate(edges, step, max_rounds)
    return _members(final)


def closure(scored: DataFrame, mu: float, method: str = "alternating_star") -> DataFrame:
    """Soft clusters: components of the pairs that score at least ``mu`` (scores are rounded to 6 places first)."""
    return connected_components(scored.where(F.round("score", 6) >= mu).select("a", "b"), method)
