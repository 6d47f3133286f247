"""Functions for SQL: registered in a session, each either an expression of built-in functions or, where the method is a search, Python over Arrow."""

from __future__ import annotations

import math
from collections.abc import Iterator
from decimal import ROUND_HALF_UP, Decimal

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from entitygraph.operators.louvain import RefineConfig, louvain


def register_expressions(spark: SparkSession) -> None:
    """``normalise_reference(body)`` and ``token_similarity(a, b)`` as temporary SQL functions; Catalyst puts their bodies in place."""
    spark.sql(
        r"""CREATE OR REPLACE TEMPORARY FUNCTION normalise_reference(body STRING) RETURNS STRING
        RETURN trim(regexp_replace(upper(regexp_replace(body, '[^A-Za-z0-9 \\t\\r\\n\\f]+', '')), '[ \\t\\r\\n\\f]+', ' '))"""
    )
    spark.sql(
        """CREATE OR REPLACE TEMPORARY FUNCTION token_similarity(a STRING, b STRING) RETURNS DOUBLE
        RETURN CASE WHEN greatest(length(a), length(b)) = 0 THEN 1.0D ELSE 1.0D - levenshtein(a, b) / greatest(length(a), length(b)) END"""
    )


def edit_distance(a: str, b: str) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def rounded(x: float, places: int) -> float:
    """Half up on the shortest decimal form, as Spark's ``round`` does; Python's own goes by the binary value."""
    return float(Decimal(repr(x)).quantize(Decimal(1).scaleb(-places), ROUND_HALF_UP))


@F.pandas_udf(DoubleType())
def scoring_matrix_py(a: pd.Series, b: pd.Series) -> pd.Series:
    """The scoring matrix over Arrow batches: the contrast to the built-in form, which needs no Python."""

    def best(rows, cols, known) -> float:
        total = 0.0
        for x in rows:
            top = 0.0
            for y in cols:
                if (x, y) not in known:
                    known[x, y] = known[y, x] = 1 - edit_distance(x, y) / max(len(x), len(y))
                top = max(top, known[x, y])
            total += top
        return total

    known: dict[tuple[str, str], float] = {}
    # twice, as the built-in form does
    return pd.Series([rounded(rounded((best(x, y, known) + best(y, x, known)) / (len(x) + len(y)), 9), 6) if len(x) and len(y) else 0.0 for x, y in zip(a, b, strict=True)], dtype="float64")


@F.pandas_udf(DoubleType())
def entropy_agg(token: pd.Series) -> float:
    """The token entropy of a group: the contrast to counts and sums of built-in functions."""
    share = token.value_counts(normalize=True)
    return round(float(-(share * share.map(math.log2)).sum()) + 0.0, 6)


@F.udtf(returnType="pos int, token string")
class TokensOf:
    """tokens_of(body): the tokens of a normalised body with their places."""

    def eval(self, body: str) -> Iterator[tuple[int, str]]:
        yield from enumerate(t for t in (body or "").split(" ") if t)


@F.udtf(returnType="component_id string, record_id string, community string, m double")
class RefineEdges:
    """refine(TABLE(edges) PARTITION BY component_id): the modularity refinement of each component, from SQL."""

    def __init__(self):
        self.component, self.edges = None, []

    def eval(self, row) -> None:
        self.component = row["component_id"]
        self.edges.append((row["u"], row["v"], row["w"]))

    def terminate(self) -> Iterator[tuple[str, str, str, float]]:
        if self.edges:
            member, m = louvain(self.edges, RefineConfig())[-1]
            for x, c in sorted(member.items()):
                yield self.component, x, c, float(m)


def register_tables(spark: SparkSession) -> None:
    spark.udtf.register("tokens_of", TokensOf)
    spark.udtf.register("refine", RefineEdges)
