"""The single-shot pipeline, the entropy-iterated baseline, and the experiment harness."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.operators import blocking, matching, parsing
from entitygraph.operators.closure import closure
from entitygraph.operators.entropy import entropy_quality
from entitygraph.operators.evaluation import LOG, pair_confusion, pair_metrics
from entitygraph.operators.hierarchical import cluster_closure, cluster_hierarchical, cluster_modularity, with_singletons
from entitygraph.operators.louvain import RefineConfig
from entitygraph.shared import materialise


@dataclass(frozen=True)
class ResolveConfig:
    mu: float = 0.6
    beta: int = 6
    sigma: int = 7
    bounds: str = "inclusive"
    measure: str = "both"
    max_tokens: int | None = None
    clusterer: str = "hierarchical"  # or closure, modularity
    blocking: str = "frequency"  # or none
    refine_edges: str = "scored"  # or above_mu
    two_phase: bool = False
    closure_method: str = "alternating_star"
    refine: RefineConfig = field(default_factory=RefineConfig)


def score_records(records: DataFrame, cfg: ResolveConfig = ResolveConfig()) -> DataFrame:
    """Scored candidate pairs of normalised bodies, written once."""
    tokens = materialise(parsing.explode_tokens(records), "tokens")
    pairs, filtered = blocking.block_records(tokens, parsing.token_frequencies(tokens), cfg.beta, cfg.sigma, cfg.bounds)
    if cfg.blocking == "none":
        pairs = blocking.all_pairs(records)
    if cfg.two_phase:
        return score_in_two_phases(materialise(pairs, "pairs"), materialise(filtered, "filtered"), cfg)
    return materialise(matching.match_pairs(pairs, filtered, cfg.measure, cfg.max_tokens), "scored")


def score_in_two_phases(pairs: DataFrame, filtered: DataFrame, cfg: ResolveConfig) -> DataFrame:
    """Exact scores only where they matter: pairs whose length bound reaches mu first, then the others inside a component.
    Scores across components are never read, so clusters are as with all scores."""
    listed = matching.with_tokens(pairs, filtered, cfg.max_tokens)
    bound = matching.upper_bound(F.col("ta"), F.col("tb"))
    score = matching.similarity(cfg.measure, F.col("ta"), F.col("tb")).alias("score")
    first = materialise(listed.where(bound >= cfg.mu - 1e-9).select("a", "b", score), "scored")
    soft = materialise(closure(first, cfg.mu, cfg.closure_method), "soft")
    left, right = (soft.select(F.col("record_id").alias(c), F.col("component_id").alias(f"c{c}")) for c in ("a", "b"))
    inside = pairs.join(first.select("a", "b"), ["a", "b"], "left_anti").join(left, "a").join(right, "b").where("ca = cb").select("a", "b")
    return materialise(first.unionByName(matching.with_tokens(inside, filtered, cfg.max_tokens).select("a", "b", score)), "scored")


def cluster(scored: DataFrame, records: DataFrame, cfg: ResolveConfig) -> DataFrame:
    if cfg.clusterer == "closure":
        return cluster_closure(scored, records, cfg.mu, cfg.closure_method)
    if cfg.clusterer == "modularity":
        return cluster_modularity(matching.above(scored, cfg.mu), records, cfg.refine)
    return cluster_hierarchical(scored, records, cfg.mu, cfg.refine, cfg.refine_edges, cfg.closure_method)


def resolve(records: DataFrame, cfg: ResolveConfig = ResolveConfig()) -> DataFrame:
    """The link index of records (record_id, body), in one run: cluster_id, record_id."""
    return cluster(score_records(records, cfg), records, cfg)


def iterate_round(records: DataFrame, mu: float, epsilon: float, cfg: ResolveConfig) -> tuple[DataFrame, DataFrame]:
    """One round of the baseline: all clusters with their quality, and the records whose cluster falls short."""
    one = ResolveConfig(**{**cfg.__dict__, "mu": mu, "clusterer": "closure"})
    clusters = materialise(resolve(records, one), "round")
    quality = entropy_quality(clusters, parsing.explode_tokens(records))
    judged = materialise(clusters.join(quality.select("cluster_id", "quality"), "cluster_id"), "judged")
    return judged, records.join(judged.where(F.col("quality") < epsilon).select("record_id"), "record_id", "left_semi")


def resolve_iterative(records: DataFrame, mu: float, epsilon: float, cfg: ResolveConfig = ResolveConfig(), mu_step: float = 0.1) -> tuple[DataFrame, int]:
    """The baseline: clusters of enough quality are emitted, the records of others start again at a higher mu, until mu is one or none is left. (link index, rounds)."""
    left, done, rounds = materialise(records.select("record_id", "body"), "left"), None, 0
    while True:
        rounds += 1
        judged, rest = iterate_round(left, mu, epsilon, cfg)
        mu = round(mu + mu_step, 6)
        last = mu >= 1
        good = judged.select("cluster_id", "record_id") if last else judged.where(F.col("quality") >= epsilon).select("cluster_id", "record_id")
        done = good if done is None else done.unionByName(good)
        if last:
            return done, rounds
        left = materialise(rest, "left")
        if left.limit(1).count() == 0:
            return done, rounds


def sweep(spark: SparkSession, samples: list[tuple], mus=tuple(k / 10 for k in range(1, 10)), epsilons=(), cfg: ResolveConfig = ResolveConfig(), clusterers=("hierarchical",)) -> DataFrame:
    """A run log: samples are (Sample, references with truth). Scores are computed once a sample and shared by all mu; epsilons give baseline runs."""
    names, rows = {"hierarchical": "two_step", "closure": "closure", "modularity": "modularity"}, []

    def measured(sample, n, algo, mu, epsilon, run):
        began = time.perf_counter()
        found = materialise(run(), "link-index")
        seconds = time.perf_counter() - began
        m = pair_metrics(pair_confusion(found, truth)).first()
        rows.append((sample.name, sample.quality, sample.layout, n, algo, float(mu), epsilon, m["precision"], m["recall"], m["f1"], m["bal_acc"], seconds))

    for sample, refs in samples:
        truth = materialise(refs, "references")
        n = truth.count()
        scored = score_records(truth, cfg)
        for mu in mus:
            for c in clusterers:
                one = ResolveConfig(**{**cfg.__dict__, "mu": mu, "clusterer": c})
                measured(sample, n, names[c], mu, None, lambda one=one: cluster(scored, truth, one))
            for e in epsilons:
                measured(sample, n, "entropy_iterated", mu, float(e), lambda mu=mu, e=e: resolve_iterative(truth, mu, e, cfg)[0])
    return spark.createDataFrame(rows, LOG)


__all__ = ["ResolveConfig", "cluster", "iterate_round", "resolve", "resolve_iterative", "score_records", "sweep", "with_singletons"]
