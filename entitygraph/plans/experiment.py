"""The experiment grid as one plan: all runs of all samples go through each step together, told apart by the name of their run.

Ids and tokens carry the run's name (``run|id``), so that the operators of a single run serve any number of them: frequencies are counted, blocks are made and
components are closed within a run, and no step needs to know how many there are. Candidate pairs of the first round are scored once a sample and shared by all thresholds.
The baseline's runs of one sample and mu go through their rounds in one task (``operators.iterated``); by other measures than the scoring matrix's all runs take each round as joins together."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from entitygraph.operators import blocking, iterated, matching, parsing
from entitygraph.operators.entropy import entropy_quality
from entitygraph.operators.evaluation import metrics_of
from entitygraph.operators.hierarchical import accept_or_collapse, refine, rename_to_least
from entitygraph.operators.modularity import component_edges
from entitygraph.plans.pipeline import ResolveConfig
from entitygraph.shared import materialise
from entitygraph.sources.fixtures import SAMPLES, Sample, references

TENTHS = tuple(k / 10 for k in range(1, 10))


def _run(*parts: Column) -> Column:
    return F.concat_ws(";", *parts)


def _named(run: Column, name: Column) -> Column:
    return F.concat(run, F.lit("|"), name)


def run_of(name: str) -> Column:
    return F.substring_index(name, "|", 1)


def plain_of(name: str) -> Column:
    return F.substring_index(name, "|", -1)


def sample_records(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """run (the sample's name), record_id (named by it), truth_id, body of the samples; each has the rows that the tables give.

    Samples that differ in their number of rows alone are the first rows of the largest of them, which is made once."""
    alike: dict[Sample, list[Sample]] = {}
    for s in (SAMPLES[n] for n in names or SAMPLES):
        alike.setdefault(replace(s, name="", rows=None), []).append(s)
    parts, cuts = [], []
    for k, group in enumerate(alike.values()):
        largest = max(group, key=lambda s: s.rows)
        parts.append(references(spark, sf_dir, largest).select(F.lit(k).alias("kind"), "record_id", "truth_id", "body"))
        cuts += [(k, s.name, s.rows) for s in group]
    made = materialise(reduce(DataFrame.unionByName, parts), "made")
    ranked = made.withColumn("r", F.row_number().over(Window.partitionBy("kind").orderBy("record_id")))
    each = ranked.join(F.broadcast(spark.createDataFrame(cuts, "kind int, run string, rows int")), "kind").where("r <= rows")
    return materialise(each.select("run", _named(F.col("run"), F.col("record_id")).alias("record_id"), "truth_id", "body"), "samples")


def score_runs(records: DataFrame, cfg: ResolveConfig) -> DataFrame:
    """a, b, score, cells of the candidate pairs of each run. records: record_id and body."""
    named = parsing.explode_tokens(records).withColumn("token", _named(run_of("record_id"), F.col("token")))
    tokens = materialise(named, "tokens")
    pairs, filtered = blocking.block_records(tokens, parsing.token_frequencies(tokens), cfg.beta, cfg.sigma, cfg.bounds)
    filtered = filtered.withColumn("tokens", F.transform("tokens", lambda t: F.substring_index(t, "|", -1)))
    listed = materialise(matching.with_tokens(pairs, filtered, cfg.max_tokens).select("a", "b", "ta", "tb"), "listed")
    score = matching.similarity(cfg.measure, F.col("ta"), F.col("tb")).alias("score")
    once = materialise(listed.select("ta", "tb").distinct().select("ta", "tb", score), "scores")
    return materialise(listed.join(once, ["ta", "tb"]).select("a", "b", "score", (F.size("ta") * F.size("tb")).cast("long").alias("cells")), "scored")


def close_runs(edges: DataFrame) -> DataFrame:
    """component_id, record_id: union-find for each run by itself; a run has the edges of one sample, which fit a task."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        parent: dict[str, str] = {}

        def root(x: str) -> str:
            parent.setdefault(x, x)
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for x, y in zip(rows.a, rows.b, strict=True):
            a, b = root(x), root(y)
            if a != b:
                parent[max(a, b)] = min(a, b)
        return pd.DataFrame({"component_id": [root(x) for x in list(parent)], "record_id": list(parent)})

    return edges.select(run_of("a").alias("run"), "a", "b").groupBy("run").applyInPandas(run, "component_id string, record_id string")


def _in_runs(df: DataFrame, runs: DataFrame, *names: str) -> DataFrame:
    """Rows of samples, once for each run of the grid over them (a few numbers a run, broadcast)."""
    out = df.crossJoin(F.broadcast(runs)).withColumn("run", _run(run_of(names[0]), *[F.col(c) for c in runs.columns]))
    for n in names:
        out = out.withColumn(n, _named(F.col("run"), plain_of(n)))
    return out


def _grid(spark: SparkSession, **axes: tuple) -> DataFrame:
    frames = [spark.createDataFrame([(float(x),) for x in xs], f"{name} double") for name, xs in axes.items()]
    return reduce(DataFrame.crossJoin, frames)


def _singletons(clusters: DataFrame, records: DataFrame) -> DataFrame:
    alone = records.select("record_id").join(clusters.select("record_id"), "record_id", "left_anti")
    return clusters.select("cluster_id", "record_id").union(alone.select(F.col("record_id").alias("cluster_id"), "record_id"))


def closure_runs(scored: DataFrame, records: DataFrame, mus: tuple = TENTHS) -> DataFrame:
    """cluster_id, record_id of closure alone, a run for each sample and mu."""
    spark = records.sparkSession
    edges = _in_runs(scored.select("a", "b", "score"), _grid(spark, mu=mus), "a", "b").where("score >= mu")
    found = materialise(close_runs(edges), "closed")
    return _singletons(found.withColumnRenamed("component_id", "cluster_id"), _in_runs(records.select("record_id"), _grid(spark, mu=mus), "record_id"))


def two_step_runs(scored: DataFrame, records: DataFrame, mus: tuple = TENTHS, cfg: ResolveConfig = ResolveConfig()) -> DataFrame:
    """cluster_id, record_id of the two-step clusterer, a run for each sample and mu."""
    spark = records.sparkSession
    every = materialise(_in_runs(scored.select("a", "b", "score"), _grid(spark, mu=mus), "a", "b"), "edges")
    soft = materialise(close_runs(every.where("score >= mu")), "soft")
    kept = every.where("score >= mu") if cfg.refine_edges == "above_mu" else every
    edges = materialise(component_edges(kept.select("a", "b", "score"), soft), "inside")
    refined = materialise(accept_or_collapse(refine(edges, cfg.refine)), "refined")
    rest = soft.join(refined.select("record_id"), "record_id", "left_anti").select("component_id", "record_id", F.col("component_id").alias("community"))
    return _singletons(rename_to_least(refined.unionByName(rest)), _in_runs(records.select("record_id"), _grid(spark, mu=mus), "record_id"))


def graph_only_runs(scored: DataFrame, records: DataFrame, mus: tuple = TENTHS, cfg: ResolveConfig = ResolveConfig()) -> DataFrame:
    """cluster_id, record_id of refinement alone over each run's whole graph above mu; nothing is closed or collapsed."""
    spark = records.sparkSession
    kept = _in_runs(scored.select("a", "b", "score"), _grid(spark, mu=mus), "a", "b").where("score >= mu")
    edges = materialise(kept.select(run_of("a").alias("component_id"), F.col("a").alias("u"), F.col("b").alias("v"), F.col("score").alias("w")), "graph")
    found = materialise(refine(edges, cfg.refine).select("component_id", "record_id", "community"), "refined")
    single = edges.join(found.select("component_id").distinct(), "component_id", "left_anti")  # a run with one edge
    pairs = single.select("component_id", F.explode(F.array("u", "v")).alias("record_id"), F.col("u").alias("community"))
    return _singletons(rename_to_least(found.unionByName(pairs)), _in_runs(records.select("record_id"), _grid(spark, mu=mus), "record_id"))


def baseline_rounds(scored: DataFrame, records: DataFrame, mus: tuple = TENTHS, epsilons: tuple = TENTHS, cfg: ResolveConfig = ResolveConfig(), step: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """(cluster_id, record_id; run, rounds, comparisons, cells) of the entropy-iterated baseline, a run for each sample, mu and epsilon, by any measure.

    All runs take their n-th round together: clusters of enough quality are emitted, the records of the others start again at a higher mu, until mu is one or none is left."""
    spark = records.sparkSession
    bodies = records.select("record_id", "body")
    clusters = materialise(closure_runs(scored, records, mus), "round")
    tokens = _in_runs(parsing.explode_tokens(bodies), _grid(spark, mu=mus), "record_id").select("record_id", "token")
    judged = clusters.join(entropy_quality(clusters, tokens).select("cluster_id", "quality"), "cluster_id")
    judged = _in_runs(judged.withColumn("mu", F.split(run_of("record_id"), ";")[1].cast("double")).withColumn("sample", F.split(run_of("record_id"), ";")[0]), _grid(spark, epsilon=epsilons), "record_id", "cluster_id")
    judged = materialise(judged.select("run", "mu", "epsilon", "cluster_id", "record_id", "quality"), "judged")
    per = scored.groupBy(run_of("a").alias("sample")).agg(F.count("*").alias("comparisons"), F.sum("cells").alias("cells"))
    runs = judged.select("run").distinct().withColumn("sample", F.split("run", ";")[0])
    costs = [runs.join(per, "sample", "left").select("run", F.lit(1).alias("rounds"), "comparisons", "cells")]
    done: list[DataFrame] = []
    while True:
        judged = judged.withColumn("mu", F.round(F.col("mu") + step, 6))
        out = (F.col("quality") >= F.col("epsilon")) | (F.col("mu") >= 1)
        done.append(materialise(judged.where(out).select("cluster_id", "record_id"), "emitted"))
        left = judged.where(~out).select("run", "mu", "epsilon", "record_id")
        left = left.withColumn("own", F.concat(F.split("run", ";")[0], F.lit("|"), plain_of("record_id"))).join(bodies.withColumnRenamed("record_id", "own"), "own").drop("own")
        left = materialise(left, "left")
        if left.limit(1).count() == 0:
            break
        again = score_runs(left.select("record_id", "body"), cfg)
        limit = left.select("run", "mu").distinct()
        costs.append(
            limit.select("run").join(again.groupBy(run_of("a").alias("run")).agg(F.count("*").alias("comparisons"), F.sum("cells").alias("cells")), "run", "left")
            .select("run", F.lit(1).alias("rounds"), "comparisons", "cells")
        )
        edges = again.withColumn("run", run_of("a")).join(F.broadcast(limit), "run").where("score >= mu").select("a", "b")
        found = _singletons(materialise(close_runs(edges), "closed").withColumnRenamed("component_id", "cluster_id"), left)
        found = materialise(found, "round")
        tokens = parsing.explode_tokens(left.select("record_id", "body")).select("record_id", "token")
        quality = entropy_quality(found, tokens).select("cluster_id", "quality")
        judged = materialise(found.join(quality, "cluster_id").join(left.select("record_id", "run", "mu", "epsilon"), "record_id").select("run", "mu", "epsilon", "cluster_id", "record_id", "quality"), "judged")
    total = reduce(DataFrame.unionByName, costs).groupBy("run").agg(F.sum("rounds").alias("rounds"), F.coalesce(F.sum("comparisons"), F.lit(0)).alias("comparisons"), F.coalesce(F.sum("cells"), F.lit(0)).alias("cells"))
    return reduce(DataFrame.unionByName, done), materialise(total, "costs")


def _searched(records: DataFrame, mus: tuple, epsilons: tuple, cfg: ResolveConfig, step: float, row, schema: str) -> DataFrame:
    """What ``row(run, ids, truth, clusters, rounds, comparisons, cells)`` makes of each run of the baseline; the runs of a sample and a mu are a task's."""

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        sample, mu = key
        rows = rows.sort_values("record_id", ignore_index=True)
        found = iterated.Sample(list(rows.body), cfg.beta, cfg.sigma, cfg.bounds, cfg.measure, cfg.max_tokens)
        truth = pd.factorize(rows.truth_id, use_na_sentinel=False)[0]
        ids = rows.record_id.str.rpartition("|")[2].to_numpy(object)
        runs = [row(f"{sample};{mu};{epsilon}", ids, truth, *rest) for epsilon, *rest in found.runs(mu, [float(e) for e in epsilons], step)]
        return pd.concat(runs, ignore_index=True)

    each = records.select(run_of("record_id").alias("run"), "record_id", "truth_id", "body").crossJoin(F.broadcast(_grid(records.sparkSession, mu=mus)))
    return each.repartition(len(mus) * len(SAMPLES), "run", "mu").groupBy("run", "mu").applyInPandas(run, schema)


def baseline_runs(scored: DataFrame, records: DataFrame, mus: tuple = TENTHS, epsilons: tuple = TENTHS, cfg: ResolveConfig = ResolveConfig(), step: float = 0.1) -> tuple[DataFrame, DataFrame]:
    """(cluster_id, record_id; run, rounds, comparisons, cells) of the entropy-iterated baseline, a run for each sample, mu and epsilon. scored is read by measures only that the search doesn't know."""
    if cfg.measure not in iterated.MEASURES:
        return baseline_rounds(scored, records, mus, epsilons, cfg, step)

    def row(run, ids, truth, clusters, rounds, comparisons, cells) -> pd.DataFrame:
        names = run + "|" + ids
        return pd.DataFrame({"cluster_id": names[clusters], "record_id": names, "run": run, "rounds": rounds, "comparisons": comparisons, "cells": cells})

    every = materialise(_searched(records, mus, epsilons, cfg, step, row, "cluster_id string, record_id string, run string, rounds long, comparisons long, cells long"), "baseline")
    return every.select("cluster_id", "record_id"), every.select("run", "rounds", "comparisons", "cells").distinct()


def baseline_measures(records: DataFrame, mus: tuple = TENTHS, epsilons: tuple = TENTHS, cfg: ResolveConfig = ResolveConfig(), step: float = 0.1) -> DataFrame:
    """The columns of ``measures_by_run`` and rounds, comparisons, cells of each run of the baseline; pairs are counted where its clusters are found."""

    def row(run, ids, truth, clusters, rounds, comparisons, cells) -> pd.DataFrame:
        both, found, true = iterated.pair_counts(clusters, truth)
        return pd.DataFrame({"run": [run], "tp": both, "p": found, "t": true, "n_rows": len(ids), "rounds": rounds, "comparisons": comparisons, "cells": cells})

    counts = materialise(_searched(records, mus, epsilons, cfg, step, row, "run string, tp long, p long, t long, n_rows long, rounds long, comparisons long, cells long"), "baseline")
    num = lambda c: F.expr(c).cast("decimal(38,0)")
    return metrics_of(
        counts.select("run", num("tp").alias("tp"), num("p - tp").alias("fp"), num("t - tp").alias("fn"), num("n_rows * (n_rows - 1) div 2 - p - t + tp").alias("tn"), "n_rows", "rounds", "comparisons", "cells")
    )


def measures_by_run(clusters: DataFrame, records: DataFrame) -> DataFrame:
    """run, tp, fp, fn, tn, precision, recall, f1, bal_acc of each run's clusters against its sample's truth, by group sizes."""
    truth = records.select(F.col("record_id").alias("own"), "truth_id")
    placed = clusters.withColumn("run", run_of("record_id")).withColumn("own", F.concat(F.split("run", ";")[0], F.lit("|"), plain_of("record_id"))).join(truth, "own")
    cells = placed.groupBy("run", "cluster_id", "truth_id").agg(F.count("*").alias("n"))
    pairs = F.expr("cast(n * (n - 1) / 2 as decimal(38,0))")
    both = cells.groupBy("run").agg(F.sum(pairs).alias("tp"), F.sum("n").alias("total"))
    found = cells.groupBy("run", "cluster_id").agg(F.sum("n").alias("n")).groupBy("run").agg(F.sum(pairs).alias("p"))
    true = cells.groupBy("run", "truth_id").agg(F.sum("n").alias("n")).groupBy("run").agg(F.sum(pairs).alias("t"))
    num = lambda c: F.expr(c).cast("decimal(38,0)")
    one = both.join(found, "run").join(true, "run").select(
        "run", num("tp").alias("tp"), num("p - tp").alias("fp"), num("t - tp").alias("fn"), num("total * (total - 1) / 2 - p - t + tp").alias("tn"), F.col("total").alias("n_rows")
    )
    return metrics_of(one)


def run_log(spark: SparkSession, sf_dir: str, names: list[str] | None = None, mus: tuple = TENTHS, epsilons: tuple = TENTHS, cfg: ResolveConfig = ResolveConfig(), algos: tuple = ("two_step", "entropy_iterated"), records: DataFrame | None = None) -> DataFrame:
    """sample, quality, layout, n_rows, algo, mu, epsilon, the counts and measures, rounds, comparisons and matrix cells of every run. Times are not here: a run has none of its own
    where all go together (see ``pipeline.sweep`` and the bench)."""
    records = sample_records(spark, sf_dir, names) if records is None else records
    searched = cfg.measure in iterated.MEASURES
    if not searched or any(a != "entropy_iterated" for a in algos):
        scored = score_runs(records.select("record_id", "body"), cfg)
        per = materialise(scored.groupBy(run_of("a").alias("sample")).agg(F.count("*").alias("comparisons"), F.sum("cells").alias("cells")), "costs")
    about = spark.createDataFrame([(s.name, s.quality, s.layout) for s in SAMPLES.values()], "sample string, quality string, layout string")
    single = {"two_step": two_step_runs, "graph_only": graph_only_runs, "closure": lambda s, r, m, c: closure_runs(s, r, m)}
    logs = []
    for algo in algos:
        if algo == "entropy_iterated" and searched:
            found = baseline_measures(records, mus, epsilons, cfg)
        elif algo == "entropy_iterated":
            clusters, costs = baseline_rounds(scored, records, mus, epsilons, cfg)
            found = measures_by_run(clusters, records).join(costs, "run")
        else:
            found = measures_by_run(single[algo](scored, records, mus, cfg), records)
        found = found.withColumn("sample", F.split("run", ";")[0]).withColumn("mu", F.split("run", ";")[1].cast("double"))
        if algo != "entropy_iterated":
            found = found.withColumn("epsilon", F.lit(None).cast("double")).withColumn("rounds", F.lit(1).cast("long")).join(per, "sample", "left")
        else:
            found = found.withColumn("epsilon", F.split("run", ";")[2].cast("double"))
        logs.append(found.withColumn("algo", F.lit(algo)))
    log = reduce(lambda a, b: a.unionByName(b), logs).join(F.broadcast(about), "sample")
    return materialise(
        log.select("sample", "quality", "layout", "n_rows", "algo", "mu", "epsilon", "tp", "fp", "fn", "tn", "precision", "recall", "f1", "bal_acc", "rounds",
                   F.coalesce("comparisons", F.lit(0)).alias("comparisons"), F.coalesce("cells", F.lit(0)).alias("cells")),
        "run-log",
    )


def best_runs(log: DataFrame) -> DataFrame:
    """Of each sample and algorithm the run with the highest F1, then the lowest mu, then the fewest comparisons, then the lowest epsilon."""
    order = Window.partitionBy("sample", "algo").orderBy(F.desc("f1"), "mu", "comparisons", "epsilon")
    return log.withColumn("r", F.row_number().over(order)).where("r = 1").drop("r")


def table_of_best_runs(log: DataFrame) -> DataFrame:
    """algo, samples, and the means over the best runs of the samples: the measures, rounds, comparisons, matrix cells; and the algorithm's runs in all."""
    runs = log.groupBy("algo").agg(F.count("*").alias("runs"), F.sum("comparisons").alias("all_comparisons"))
    means = best_runs(log).groupBy("algo").agg(
        F.count("*").alias("samples"), *[F.round(F.avg(c), 6).alias(c) for c in ("precision", "recall", "f1", "bal_acc")], *[F.round(F.avg(c), 3).alias(c) for c in ("rounds", "comparisons", "cells")]
    )
    return means.join(runs, "algo")
