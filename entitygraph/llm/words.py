"""Words of whole texts as numbers, a block of texts at a time, and the labelled sample that classifiers are fitted on."""

from __future__ import annotations

import zlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Signs that are cut from both ends of a word.
SIGNS = ".,;:!?\"'()[]{}<>*#$%&+-_=/\\|~^`@…«»„“”‚‘’¿¡–—"


def word_codes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, list[str]]:
    """(offsets, codes, words): the words of text i are words[c] for c in codes[offsets[i]:offsets[i + 1]]."""
    lists = pc.ascii_split_whitespace(texts.fill_null("").cast(pa.large_string()))
    borders = lists.offsets.to_numpy()
    coded = lists.flatten().dictionary_encode()
    codes = coded.indices.to_numpy().astype(np.int64)
    words = coded.dictionary.to_pylist()
    if "" not in words:
        return borders - borders[0], codes, words
    keep = codes != words.index("")  # white space at an end of a text leaves an empty word
    before = np.append(0, np.cumsum(keep))
    return before[borders - borders[0]], codes[keep], words


def mapped(words: list[str], codes: np.ndarray, value: Callable[[str], float], kind=np.int64) -> np.ndarray:
    table = np.fromiter(map(value, words), kind, len(words)) if words else np.empty(0, kind)
    return table[codes] if len(codes) else np.empty(0, kind)


def hashed(bits: int) -> Callable[[str], int]:
    mask = (1 << bits) - 1
    return lambda w: zlib.crc32(w.lower().strip(SIGNS).encode()) & mask


def fold(divisor: int):
    """crc32 of the id as text, modulo the divisor."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % divisor


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, divisor: int, left_out: int, most: int) -> DataFrame:
    """(text, y) of at most ``most`` labelled rows outside the held-out fold, those with the least hash of their id. The
    sample's ids are at most ``most`` numbers and are broadcast; texts are read once and never shuffled."""
    known = (
        labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & (fold(divisor) != left_out))
        .groupBy("doc_id")
        .agg(F.max(label).alias("y"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(most)
    )
    return docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").select(F.coalesce("text", F.lit("")).alias("text"), F.col("y").cast("int").alias("y"))
