"""Reference bodies, tokens and their frequencies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def build_body(df: DataFrame, attrs: str = "attrs", order: list[str] | None = None) -> DataFrame:
    """record_id and body: all attribute values in one string, nulls skipped; attributes in key order or as listed."""
    if order:
        return df.select("record_id", F.concat_ws(" ", *[F.col(attrs)[k] for k in order]).alias("body"))
    entries = F.array_sort(F.map_entries(attrs))
    return df.select("record_id", F.array_join(F.transform(entries, lambda e: e["value"]), " ").alias("body"))


def normalise(body: Column, charset: str = "unicode", special: str = "delete") -> Column:
    """Upper case without special characters; white space becomes single spaces."""
    keep = r"[^A-Za-z0-9 \t\r\n\f]+" if charset == "ascii" else r"[^\p{L}\p{N} \t\r\n\f]+"
    cleaned = F.regexp_replace(body, keep, "" if special == "delete" else " ")
    return F.trim(F.regexp_replace(F.upper(cleaned), r"[ \t\r\n\f]+", " "))


def tokenise(body: Column) -> Column:
    return F.filter(F.split(body, " "), lambda t: t != "")


def explode_tokens(records: DataFrame) -> DataFrame:
    """record_id, pos, token of normalised bodies."""
    return records.select("record_id", F.posexplode(tokenise(F.col("body"))).alias("pos", "token"))


def token_frequencies(tokens: DataFrame) -> DataFrame:
    """token, c (occurrences) and df (records). Counted per record first, so that a common token's rows combine before they move."""
    per = tokens.groupBy("token", "record_id").agg(F.count("*").alias("n"))
    return per.groupBy("token").agg(F.sum("n").alias("c"), F.count("*").alias("df"))


def frequency_profile(freqs: DataFrame) -> DataFrame:
    """How many tokens have each count, to choose the two cuts by."""
    return freqs.groupBy("c").agg(F.count("*").alias("tokens"))
