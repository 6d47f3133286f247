"""Pair-counting measures from contingency counts, run logs and their summaries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from entitygraph.errors import LocalCapExceeded
from entitygraph.shared import materialise

LOG = "sample string, quality string, layout string, n_rows long, algo string, mu double, epsilon double, precision double, recall double, f1 double, bal_acc double, seconds double"


def contingency(pred: DataFrame, truth: DataFrame) -> DataFrame:
    return pred.join(truth.select("record_id", "truth_id"), "record_id").groupBy("cluster_id", "truth_id").agg(F.count("*").alias("n"))


def _pairs(n: Column) -> Column:
    n = n.cast("decimal(38,0)")
    return (n * (n - 1) / 2).cast("decimal(38,0)")


def pair_confusion(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """tp, fp, fn, tn over unordered record pairs, from group sizes in linear time."""
    cells = contingency(pred, truth)
    both = cells.agg(F.coalesce(F.sum(_pairs(F.col("n"))), F.lit(0)).alias("tp"), F.sum("n").alias("total"))
    rows = cells.groupBy("cluster_id").agg(F.sum("n").alias("n")).agg(F.coalesce(F.sum(_pairs(F.col("n"))), F.lit(0)).alias("p"))
    cols = cells.groupBy("truth_id").agg(F.sum("n").alias("n")).agg(F.coalesce(F.sum(_pairs(F.col("n"))), F.lit(0)).alias("t"))
    one = both.crossJoin(rows).crossJoin(cols)  # one row each
    num = lambda c: F.expr(c).cast("decimal(38,0)")
    return one.select(num("tp").alias("tp"), num("p - tp").alias("fp"), num("t - tp").alias("fn"), (_pairs(F.coalesce("total", F.lit(0))) - num("p") - num("t") + num("tp")).cast("decimal(38,0)").alias("tn"))


def pair_confusion_enumerated(pred: DataFrame, truth: DataFrame, max_records: int | None = None) -> DataFrame:
    """The same by looping over pairs, for reference: each pair inside a cluster and each inside a true group is made and looked at by itself; all other pairs are in neither, so they
    are counted as what is left of n (n - 1) / 2. Work grows with the squares of groups, not of the table. Refuses more than ``max_records`` records, where that is given."""
    one = materialise(pred.join(truth.select("record_id", "truth_id"), "record_id").select("record_id", "cluster_id", "truth_id"), "judged")
    n = one.count()
    if max_records is not None and n > max_records:
        raise LocalCapExceeded(f"{n} records, at most {max_records} for all pairs")
    left = one.select(F.col("record_id").alias("a"), F.col("cluster_id").alias("ca"), F.col("truth_id").alias("ta"))
    right = one.select(F.col("record_id").alias("b"), F.col("cluster_id").alias("cb"), F.col("truth_id").alias("tb"))
    together, true = F.col("ca").eqNullSafe(F.col("cb")), F.col("ta").eqNullSafe(F.col("tb"))
    number = lambda c: F.count_if(c).cast("decimal(38,0)")
    found = left.join(right, together & (F.col("a") < F.col("b"))).agg(number(true).alias("tp"), number(~true).alias("fp"))
    missed = left.join(right, true & (F.col("a") < F.col("b"))).agg(number(~together).alias("fn"))
    tn = F.lit(n * (n - 1) // 2).cast("decimal(38,0)") - F.col("tp") - F.col("fp") - F.col("fn")
    return found.crossJoin(missed).select("tp", "fp", "fn", tn.cast("decimal(38,0)").alias("tn"))  # one row each


def metrics_of(confusion: DataFrame, literal: bool = False) -> DataFrame:
    """Adds precision, recall, f1 and balanced accuracy (``literal``: without halving), rounded to six places, to rows with tp, fp, fn, tn."""
    d = {c: F.col(c).cast("double") for c in ("tp", "fp", "fn", "tn")}
    nothing = (F.col("tp") + F.col("fp") + F.col("fn")) == 0
    ratio = lambda a, b: F.when(nothing, 1.0).when(b == 0, 0.0).otherwise(a / F.when(b == 0, None).otherwise(b))
    out = confusion.withColumn("precision", ratio(d["tp"], d["tp"] + d["fp"])).withColumn("recall", ratio(d["tp"], d["tp"] + d["fn"]))
    total = F.col("precision") + F.col("recall")
    out = out.withColumn("f1", F.when(total == 0, 0.0).otherwise(2 * F.col("precision") * F.col("recall") / F.when(total == 0, None).otherwise(total)))
    tnr = F.when(d["tn"] + d["fp"] == 0, 1.0).otherwise(d["tn"] / F.when(d["tn"] + d["fp"] == 0, None).otherwise(d["tn"] + d["fp"]))
    out = out.withColumn("bal_acc", F.col("recall") + tnr if literal else (F.col("recall") + tnr) / 2)
    return out.select(*confusion.columns, *[F.round(c, 6).alias(c) for c in ("precision", "recall", "f1", "bal_acc")])


def pair_metrics(confusion: DataFrame, literal: bool = False) -> DataFrame:
    """tp, fp, fn, tn with the measures."""
    return metrics_of(confusion.select("tp", "fp", "fn", "tn"), literal)


def best_run(log: DataFrame) -> DataFrame:
    """Of each sample and algorithm the run with the highest F1, then the lowest mu, then the least time."""
    order = Window.partitionBy("sample", "algo").orderBy(F.desc("f1"), "mu", "seconds", "epsilon")
    return log.withColumn("r", F.row_number().over(order)).where("r = 1").drop("r")


def summarise(best: DataFrame) -> DataFrame:
    return best.groupBy("algo").agg(*[F.round(F.avg(c), 6).alias(c) for c in ("precision", "recall", "f1", "bal_acc", "seconds")])


def compare(summary: DataFrame, ours: str = "two_step", other: str = "entropy_iterated") -> DataFrame:
    """Gains of one algorithm over the other, and the ratio of their times."""
    pick = lambda a, s: summary.where(F.col("algo") == a).select(*[F.col(c).alias(f"{c}_{s}") for c in ("precision", "recall", "f1", "bal_acc", "seconds")])
    one = pick(ours, "x").crossJoin(pick(other, "y"))  # one row each
    gains = [F.round(F.col(f"{c}_x") - F.col(f"{c}_y"), 6).alias(f"{c}_gain") for c in ("precision", "recall", "f1", "bal_acc")]
    return one.select(*gains, F.round(F.col("seconds_y") / F.col("seconds_x"), 6).alias("speed_up"))


def sensitivity(log: DataFrame, samples: list[str], measures: tuple[str, ...] = ("f1",)) -> DataFrame:
    """Means by mu, one column for each sample and measure (named by the sample alone where there is one measure)."""
    means = [F.round(F.avg(m), 6).alias(m) for m in measures]
    return log.where(F.col("sample").isin(samples)).groupBy("algo", "mu").pivot("sample", samples).agg(*means)


def dominance(log: DataFrame, ours: str = "two_step", other: str = "entropy_iterated") -> DataFrame:
    """Difference of best F1 by quality and mu, with subtotals."""
    best = log.groupBy("sample", "quality", "mu", "algo").agg(F.max("f1").alias("f1"))
    a = best.where(F.col("algo") == ours).select("sample", "quality", "mu", F.col("f1").alias("x"))
    b = best.where(F.col("algo") == other).select("sample", "quality", "mu", F.col("f1").alias("y"))
    return a.join(b, ["sample", "quality", "mu"]).rollup("quality", "mu").agg(F.round(F.avg(F.col("x") - F.col("y")), 6).alias("gain"), F.count("*").alias("n"))


def cluster_report(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """Clusters by size, and how many equal a true one exactly."""
    cells = contingency(pred, truth)
    size = cells.groupBy("cluster_id").agg(F.sum("n").alias("size"), F.count("*").alias("parts"), F.max("truth_id").alias("truth_id"))
    true_size = cells.groupBy("truth_id").agg(F.sum("n").alias("true_size"))
    exact = (F.col("parts") == 1) & (F.col("size") == F.col("true_size"))
    return size.join(true_size, "truth_id").groupBy("size").agg(F.count("*").alias("clusters"), F.sum(exact.cast("int")).cast("long").alias("exact"))
