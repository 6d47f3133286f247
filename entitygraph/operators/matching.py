"""Pairwise similarity: the token scoring matrix and other measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

REDUCTIONS = ("both", "rows", "cols", "shorter")
#: Other names of a reduction.
ALIASES = {"monge_elkan": "rows"}


def token_similarity(a: Column, b: Column) -> Column:
    return F.lit(1.0) - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b))


def _best(rows: Column, cols: Column) -> Column:
    """The sum over row tokens of their best cell."""
    return F.aggregate(rows, F.lit(0.0), lambda acc, x: acc + F.array_max(F.transform(cols, lambda y: token_similarity(x, y))))


def scoring_matrix(a: Column, b: Column, reduce: str = "both") -> Column:
    """The mean of the largest cell of each row or column of the token-by-token similarity matrix; 0 where a list is empty."""
    na, nb = F.size(a), F.size(b)
    reduce = ALIASES.get(reduce, reduce)
    if reduce == "rows":
        score = _best(a, b) / na
    elif reduce == "cols":
        score = _best(b, a) / nb
    elif reduce == "shorter":
        score = F.when(na <= nb, _best(a, b) / na).otherwise(_best(b, a) / nb)
    elif reduce == "greedy":
        score = 2 * _one_to_one(a, b) / (na + nb)
    elif reduce == "both":
        score = (_best(a, b) + _best(b, a)) / (na + nb)
    else:
        raise ValueError(f"reduce must be one of {REDUCTIONS}")
    # twice, so that the order of a sum cannot tip a score that lies half way between two of six places
    return F.when((na > 0) & (nb > 0), F.round(F.round(score, 9), 6)).otherwise(0.0)


def _one_to_one(a: Column, b: Column) -> Column:
    """The sum of cells that are taken from the largest on, each row and column once; ties go to the first row, then the first column."""
    rows = F.transform(a, lambda x, i: F.transform(b, lambda y, j: F.struct((-token_similarity(x, y)).alias("s"), i.alias("i"), j.alias("j"))))
    none = F.expr("cast(array() as array<int>)")
    taken = F.aggregate(
        F.array_sort(F.flatten(rows)),
        F.struct(F.lit(0.0).alias("total"), none.alias("rows"), none.alias("cols")),
        lambda acc, c: F.when(F.array_contains(acc["rows"], c["i"]) | F.array_contains(acc["cols"], c["j"]), acc).otherwise(
            F.struct((acc["total"] - c["s"]).alias("total"), F.array_append(acc["rows"], c["i"]).alias("rows"), F.array_append(acc["cols"], c["j"]).alias("cols"))
        ),
    )
    return taken["total"]


def upper_bound(a: Column, b: Column) -> Column:
    """What the scoring matrix can reach at most from token lengths alone: a cell is at most shorter over longer."""
    bound = lambda rows, cols: F.aggregate(
        rows, F.lit(0.0), lambda acc, x: acc + F.array_max(F.transform(cols, lambda y: F.least(F.length(x), F.length(y)) / F.greatest(F.length(x), F.length(y))))
    )
    return F.when((F.size(a) > 0) & (F.size(b) > 0), (bound(a, b) + bound(b, a)) / (F.size(a) + F.size(b))).otherwise(0.0)


def similarity(name: str, a: Column, b: Column) -> Column:
    """By any measure, a record without kept tokens is like no other: 0."""
    if name in (*REDUCTIONS, *ALIASES, "greedy"):
        return scoring_matrix(a, b, name)
    common = F.size(F.array_intersect(a, b))
    if name == "exact":
        score = (F.array_join(a, " ") == F.array_join(b, " ")).cast("double")
    elif name == "jaccard":
        score = F.round(common / F.size(F.array_union(a, b)), 6)
    elif name == "overlap":
        score = F.round(common / F.least(F.size(F.array_distinct(a)), F.size(F.array_distinct(b))), 6)
    elif name == "levenshtein_body":
        score = F.round(token_similarity(F.array_join(a, " "), F.array_join(b, " ")), 6)
    else:
        raise ValueError(f"unknown similarity {name!r}")
    return F.when((F.size(a) > 0) & (F.size(b) > 0), score).otherwise(0.0)


def with_tokens(pairs: DataFrame, filtered: DataFrame, max_tokens: int | None = None) -> DataFrame:
    """The pairs with both token lists, ta and tb; a record without kept tokens has an empty list."""
    lists = filtered.select("record_id", (F.slice("tokens", 1, max_tokens) if max_tokens else F.col("tokens")).alias("tokens"))
    left = lists.select(F.col("record_id").alias("a"), F.col("tokens").alias("ta"))
    right = lists.select(F.col("record_id").alias("b"), F.col("tokens").alias("tb"))
    empty = F.expr("cast(array() as array<string>)")
    return pairs.join(left, "a", "left").join(right, "b", "left").withColumn("ta", F.coalesce("ta", empty)).withColumn("tb", F.coalesce("tb", empty))


def match_pairs(pairs: DataFrame, filtered: DataFrame, measure: str = "both", max_tokens: int | None = None) -> DataFrame:
    """a, b, score, rounded to six places."""
    return with_tokens(pairs, filtered, max_tokens).select("a", "b", similarity(measure, F.col("ta"), F.col("tb")).alias("score"))


def idf_cosine(pairs: DataFrame, tokens: DataFrame, freqs: DataFrame, n_records: int) -> DataFrame:
    """Cosine of inverse-document-frequency vectors over the pairs' shared tokens, not rounded."""
    weights = tokens.select("record_id", "token").distinct().join(freqs.select("token", F.log(F.lit(float(n_records)) / F.col("df")).alias("w")), "token")
    norms = weights.groupBy("record_id").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    left = weights.select(F.col("record_id").alias("a"), "token", F.col("w").alias("wa"))
    right = weights.select(F.col("record_id").alias("b"), "token", F.col("w").alias("wb"))
    dots = pairs.select("a", "b").join(left, "a").join(right, ["b", "token"]).groupBy("a", "b").agg(F.sum(F.col("wa") * F.col("wb")).alias("dot"))
    named = lambda c: norms.select(F.col("record_id").alias(c), F.col("norm").alias(f"n{c}"))
    full = pairs.select("a", "b").join(dots, ["a", "b"], "left").join(named("a"), "a", "left").join(named("b"), "b", "left")
    return full.select("a", "b", F.coalesce(F.expr("try_divide(dot, na * nb)"), F.lit(0.0)).alias("score"))


def above(scored: DataFrame, mu: float) -> DataFrame:
    return scored.where(F.round("score", 6) >= mu)


def rule_pairs(pairs: DataFrame, filtered: DataFrame, least_common: int = 3) -> DataFrame:
    """A rule as a supervised contrast: so many kept tokens in common."""
    return with_tokens(pairs, filtered).where(F.size(F.array_intersect("ta", "tb")) >= least_common).select("a", "b")
