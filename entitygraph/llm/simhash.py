"""SimHash near-dedup: majority fingerprints of word shingles, and exact links within a Hamming radius.

Candidates come from blocks of the fingerprint: for radius r the 64 bits are cut into r + 2 blocks, and two fingerprints that
differ in at most r bits agree on at least two blocks; every pair of blocks is a key. The free bits of a bucket with more than ``BUCKET`` distinct fingerprints are cut in the same way, which
loses no pair, until a bucket is small or so few bits are free that it cannot be large. All buckets are compared
with vertical bit planes: plane k holds bit k of every fingerprint, each bucket in words of its own; a query's differing planes are
added with carry-save counters, and a word of columns is left as soon as every column in it is beyond the radius. Only a
spanning forest of a bucket's links leaves it."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.operators.closure import connected_components
from entitygraph.shared import materialise

BITS = 64
BUCKET = 2048
SEED = 42


def shingle_hashes(text: bytes, size: int) -> np.ndarray:
    """XXH64 of each shingle of ``size`` words; fewer words make one shingle; no words none."""
    words = text.lower().split()
    if not words:
        return np.empty(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    if len(words) <= size:
        return np.array([digest(b" ".join(words), SEED)], np.uint64)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.append(0, ends[: len(words) - size]).tolist()
    return np.array([digest(joined[a:b], SEED) for a, b in zip(starts, (ends[size - 1 :] - 1).tolist(), strict=True)], np.uint64)


def majority(hashes: np.ndarray) -> int:
    """The bits set in over half of the hashes, as a signed 64-bit number."""
    if not len(hashes):
        return 0
    total, n = np.zeros(BITS, np.int64), len(hashes)
    for k in range(0, n, 65536):
        bits = np.unpackbits(hashes[k : k + 65536].view(np.uint8), bitorder="little").reshape(-1, BITS)
        total += bits.sum(axis=0, dtype=np.int32)
    return int(np.packbits(2 * total > n, bitorder="little").view(np.int64)[0])


def _fingerprints(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marks = [majority(shingle_hashes(x.as_py() or b"", size)) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(marks, pa.int64())], ["doc_id", "mark"])

    return run


def fingerprints(docs: DataFrame, size: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, mark): the fingerprint as a signed 64-bit number."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))
    return texts.mapInArrow(_fingerprints(size), "doc_id long, mark long")


def bit_planes(marks: np.ndarray) -> np.ndarray:
    """Plane k: bit k of every mark, packed into 64-bit words, column by column."""
    columns = -(-len(marks) // 64) * 64
    bits = np.zeros((columns, BITS), np.uint8)
    bits[: len(marks)] = np.unpackbits(marks.view(np.uint8), bitorder="little").reshape(-1, BITS)
    return np.ascontiguousarray(np.packbits(bits.T, axis=1, bitorder="little")).view(np.uint64)


def within_words(planes: np.ndarray, queries: np.ndarray, row: np.ndarray, block: np.ndarray, radius: int) -> np.ndarray:
    """For each pair of a query and a word of columns, the columns within the radius, as bits. Counters saturate above the radius; a pair is abandoned when all its columns have."""
    ones = np.uint64(0xFFFFFFFFFFFFFFFF)
    found, left = np.zeros(len(row), np.uint64), np.arange(len(row))
    width = (radius + 1).bit_length()
    counters = [np.zeros(len(row), np.uint64) for _ in range(width)]
    beyond = np.zeros(len(row), np.uint64)
    flip = np.where(np.unpackbits(queries.view(np.uint8), bitorder="little").reshape(-1, BITS) == 1, ones, np.uint64(0))
    for k in range(BITS):
        carry = planes[k, block] ^ flip[row, k]
        for c in counters:
            carry, c[:] = c & carry, c ^ carry
        over = carry
        greater, equal = np.zeros_like(over), np.full_like(over, ones)  # the counters against the radius
        for j in reversed(range(width)):
            bit = ones if radius >> j & 1 else np.uint64(0)
            greater |= equal & counters[j] & ~bit
            equal &= ~(counters[j] ^ bit)
        beyond |= over | greater
        if k % 8 == 7:
            alive = beyond != ones
            if not alive.all():
                row, block, beyond, left = row[alive], block[alive], beyond[alive], left[alive]
                counters = [c[alive] for c in counters]
                if not len(row):
                    return found
    found[left] = ~beyond
    return found


def within(planes: np.ndarray, queries: np.ndarray, radius: int) -> np.ndarray:
    """For each query, the columns within the radius, as packed words."""
    words = planes.shape[1]
    row, block = (x.ravel() for x in np.meshgrid(np.arange(len(queries)), np.arange(words), indexing="ij"))
    return within_words(planes, queries, row, block, radius).reshape(len(queries), words)


def bucket_links(marks: np.ndarray, borders: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (x, y), x < y, of the marks of one bucket within the radius. Bucket i is marks[borders[i]:borders[i + 1]]; each has plane words of its own."""
    size = np.diff(borders)
    words = -(-size // 64)
    first = np.cumsum(words) - words
    which = np.repeat(np.arange(len(size)), size)
    inside = np.arange(len(marks)) - borders[which]
    columns = np.zeros((int(words.sum()) * 64, BITS), np.uint8)
    columns[first[which] * 64 + inside] = np.unpackbits(marks.view(np.uint8), bitorder="little").reshape(-1, BITS)
    planes = np.ascontiguousarray(np.packbits(columns.T, axis=1, bitorder="little")).view(np.uint64)
    per = words[which] - inside // 64  # a query meets its own word and those after it
    todo = np.append(0, np.cumsum(per))
    for at in range(0, int(todo[-1]), 1 << 18):
        pair = np.arange(at, min(at + (1 << 18), int(todo[-1])))
        row = np.searchsorted(todo, pair, "right") - 1
        block = first[which[row]] + inside[row] // 64 + pair - todo[row]
        base = int(row[0])
        near = within_words(planes, marks[base : int(row[-1]) + 1], row - base, block, radius)
        hit = np.flatnonzero(near)
        bits = np.unpackbits(near[hit].view(np.uint8), bitorder="little").reshape(-1, 64)
        i, column = np.nonzero(bits)
        x = row[hit[i]]
        y = borders[which[x]] + (block[hit[i]] - first[which[x]]) * 64 + column
        real = (y > x) & (y < borders[which[x] + 1])  # padding columns are zeros
        yield x[real], y[real]


def forests(marks: np.ndarray, borders: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Of buckets of distinct marks: (member, a mark of its component) for edges that make the components of each bucket."""
    parent = np.arange(len(marks))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    left, right = [], []
    for xs, ys in bucket_links(marks, borders, radius):
        for x, y in zip(xs.tolist(), ys.tolist(), strict=True):
            a, b = root(x), root(y)
            if a != b:
                parent[b] = a
                left.append(x)
                right.append(y)
    return marks[np.array(left, int)], marks[np.array(right, int)]


def _forests(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(0)
            borders = lists.offsets.to_numpy().astype(np.int64)
            marks = np.ascontiguousarray(lists.values.to_numpy()[borders[0] : borders[-1]])
            a, b = forests(marks, borders - borders[0], radius)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def block_masks(radius: int, fixed: tuple[int, ...] = ()) -> list[tuple[int, ...]]:
    """The choices of two of radius + 2 blocks of the bits that are still free, each as all bits that are fixed then. Marks that agree on the fixed bits and differ in at most
    ``radius`` others agree on one of the choices."""
    free = [k for k in range(BITS) if k not in set(fixed)]
    cuts = np.linspace(0, len(free), radius + 3).astype(int)
    blocks = [tuple(free[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    return [(*fixed, *a, *b) for a, b in combinations(blocks, 2)]


def _signed(bits: tuple[int, ...]) -> int:
    mask = sum(1 << k for k in bits)
    return mask - (1 << 64) if mask >> 63 else mask


def linked_marks(marks: DataFrame, radius: int = 2, bucket: int = BUCKET, levels: int = 3) -> DataFrame:
    """Edges (a, b) between distinct fingerprints whose components are those of all pairs within the radius.

    A bucket of more than ``bucket`` is dealt by the choices of its own free bits, level by level; at the last one a bucket holds at most 2 to the number of free bits,
    256 for radius 2. Buckets are dealt by a hash of all their fixed bits."""
    choices = block_masks(radius)
    table = F.array(*[F.lit(_signed(c)) for c in choices])
    number = len(choices)
    keyed = marks.select("mark", F.explode(F.sequence(F.lit(0), F.lit(number - 1))).alias("choice"))
    edges = None
    for level in range(levels):
        keyed = keyed.select("choice", F.col("mark").bitwiseAND(F.get(table, "choice")).alias("key"), "mark")
        sizes = keyed.groupBy("choice", "key").agg(F.count("*").alias("n")).where("n > 1")
        grouped = materialise(keyed.join(sizes, ["choice", "key"]), "buckets")
        last = level == levels - 1
        small = grouped if last else grouped.where(F.col("n") <= bucket)
        near = small.groupBy("choice", "key").agg(F.collect_list("mark").alias("marks")).select("marks").mapInArrow(_forests(radius), "a long, b long")
        edges = near if edges is None else edges.union(near)
        large = grouped.where(F.col("n") > bucket)
        if last or large.limit(1).count() == 0:
            return edges
        choices = [d for c in choices for d in block_masks(radius, c)]
        table = F.array(*[F.lit(_signed(c)) for c in choices])
        keyed = large.select("mark", F.explode(F.sequence(F.col("choice") * number, F.col("choice") * number + number - 1)).alias("choice"))
    return edges


def simhash_components(docs: DataFrame, size: int = 3, radius: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits), component_id: the least doc_id reachable over links of at most ``radius`` differing bits.

    Null and wordless texts have fingerprint zero and link like any other; equal fingerprints always link; texts of any length are read whole; rows that repeat an id keep a row each; a row
    without an id has its fingerprint's component, which a null never names unless no member has an id; other columns are
    ignored, whatever their names; an empty table gives no rows. Documents with equal fingerprints are one class and never paired."""
    marked = materialise(fingerprints(docs, size, id_col, text_col), "fingerprints")
    classes = materialise(marked.groupBy("mark").agg(F.min("doc_id").alias("least")), "classes")
    groups = connected_components(linked_marks(classes.select("mark"), radius))
    led = classes.join(groups.select(F.col("record_id").alias("mark"), "component_id"), "mark", "left").withColumn(
        "component_id", F.coalesce("component_id", "mark")
    )
    lead = led.groupBy("component_id").agg(F.min("least").alias("lead"))
    named = led.join(lead, "component_id").select("mark", F.col("lead").alias("component_id"))
    return marked.join(named, "mark").select("doc_id", F.lpad(F.lower(F.hex("mark")), 16, "0").alias("fingerprint"), "component_id")


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
