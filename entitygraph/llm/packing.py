"""Packing along a space-filling curve: neighbours in content become neighbours in a sequence, with no padding at all.

A document's ids are hashed to a vector of ``HASHED`` log counts, projected to ``DIMS`` dimensions by a fixed random matrix, and placed
on a Hilbert curve of ``LEVELS`` bits a dimension. The curve is cut into stretches of about equally many ids; tasks take stretches, sort each by its key and lay
its documents end to end, cut every ``size`` ids. What is left at the end of a task is cut into powers of two, which need no padding."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.llm.tokens import WORD_BLOCK, blocks, encoder, forget_encoders, vocabulary
from entitygraph.shared import materialise

HASHED, DIMS, LEVELS = 256, 4, 10
#: Ids in a stretch of the curve, stretches that a task packs on average, and tasks at most.
RANGE_IDS, STRETCHES, MOST_TASKS = 500_000, 8, 100_000


def hilbert_keys(points: np.ndarray, levels: int = LEVELS) -> np.ndarray:
    """Places along the Hilbert curve of integer points, one row each, by the transposed form of Skilling (2004)."""
    x = points.T.astype(np.int64).copy()
    dims = len(x)
    bit = 1 << levels - 1
    while bit > 1:
        mask = bit - 1
        for i in range(dims):
            on = (x[i] & bit) != 0
            swap = np.where(on, 0, (x[0] ^ x[i]) & mask)
            x[0] ^= np.where(on, mask, swap)
            x[i] ^= swap
        bit >>= 1
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    turn = np.zeros_like(x[0])
    bit = 1 << levels - 1
    while bit > 1:
        turn ^= np.where(x[-1] & bit, bit - 1, 0)
        bit >>= 1
    x ^= turn
    key = np.zeros_like(x[0])
    for level in reversed(range(levels)):
        for i in range(dims):
            key = key << 1 | x[i] >> level & 1
    return key


def content_keys(offsets: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """The curve keys of documents from their ids."""
    rng = np.random.default_rng(7)
    axes = rng.standard_normal((HASHED, DIMS))
    axes -= axes.mean(axis=0)
    n = len(offsets) - 1
    doc = np.repeat(np.arange(n), np.diff(offsets))
    slot = (ids.astype(np.uint32) * np.uint32(2654435761)) >> np.uint32(24)
    counts = np.bincount(doc * HASHED + slot, minlength=n * HASHED).reshape(n, HASHED)
    vectors = np.log1p(counts)
    vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-9)
    grid = np.clip((vectors @ axes / 3 + 0.5) * (1 << LEVELS), 0, (1 << LEVELS) - 1).astype(np.int64)
    return hilbert_keys(grid)


def _tokenised(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = encoder(path)
        width = 2 if max(tokens.size - 1, end_id) < 1 << 16 else 4
        for batch in batches:
            for block in blocks(batch, 1, WORD_BLOCK):
                offsets, ids = tokens.encode(block.column(1), end_id)
                raw = pa.py_buffer(np.ascontiguousarray(ids, f"<u{width}"))
                data = pa.Array.from_buffers(pa.large_binary(), len(offsets) - 1, [None, pa.py_buffer((offsets * width).astype(np.int64).tobytes()), raw])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(content_keys(offsets, ids)), block.column(0), pa.array(np.full(len(offsets) - 1, width, np.int32)), pa.array(np.diff(offsets)), data.cast(pa.binary())],
                    ["key", "doc_id", "width", "n", "ids"],
                )

    return run


def _pack(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_encoders()
        base, number, filled = TaskContext.get().partitionId() << 32, 0, 0
        open_pieces: list[tuple] = []  # of the sequence that is not full: doc_id, start, ids, doc_tokens

        def rows(pieces: list[tuple]) -> pa.RecordBatch:
            doc, start, ids, total, seq, at = zip(*pieces, strict=True)
            return pa.RecordBatch.from_arrays(
                [pa.array(doc, pa.int64()), pa.array(start, pa.int64()), pa.array(list(map(len, ids)), pa.int64()),
                 pa.array([zlib.crc32(x.astype("<u4")) for x in ids], pa.int64()), pa.array(total, pa.int64()), pa.array(seq, pa.int64()),
                 pa.array(at, pa.int64()), pa.array([x.astype("<u4").tobytes() for x in ids], pa.binary())],
                ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "ids"],
            )

        def laid(pieces: list[tuple], seq: int) -> list[tuple]:
            out, at = [], 0
            for doc, start, ids, total in pieces:
                out.append((doc, start, ids, total, seq, at))
                at += len(ids)
            return out

        def cut(pieces: list[tuple], first: int) -> tuple[list[tuple], list[tuple]]:
            """The first so many ids, and the rest."""
            head, tail, left = [], [], first
            for doc, start, ids, total in pieces:
                if left >= len(ids):
                    head.append((doc, start, ids, total))
                elif left > 0:
                    head.append((doc, start, ids[:left], total))
                    tail.append((doc, start + left, ids[left:], total))
                else:
                    tail.append((doc, start, ids, total))
                left = max(0, left - len(ids))
            return head, tail

        for batch in batches:
            done: list[tuple] = []
            pending = 0
            for doc, width, raw in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3), strict=True):
                ids = np.frombuffer(raw.as_buffer(), f"<u{width}")
                at, total = 0, len(ids)
                while at < total:
                    take = min(size - filled, total - at)
                    open_pieces.append((doc, at, ids[at : at + take], total))
                    at, filled = at + take, filled + take
                    if filled == size:
                        done += laid(open_pieces, base + number)
                        number, filled, open_pieces = number + 1, 0, []
                pending += total
                if pending > 1_000_000 and done:
                    yield rows(done)
                    done, pending = [], 0
            open_pieces = [(d, s, i.copy(), t) for d, s, i, t in open_pieces]
            if done:
                yield rows(done)
        while filled:
            power = 1 << filled.bit_length() - 1
            head, open_pieces = cut(open_pieces, power)
            yield rows(laid(head, base + number))
            number, filled = number + 1, filled - power

    return run


def _ranges(kept: DataFrame, range_ids: int) -> tuple[DataFrame, int]:
    """``kept`` with the number of the stretch of the curve that each document lies in, and how many stretches there are.

    Stretches hold about ``range_ids`` ids each, by the sums over 2**16 cells of the curve, which are all that reaches the driver. A cell with more (copies share a
    key) is cut by a hash of the document, so that no stretch grows with the input."""
    cell = F.shiftright("key", DIMS * LEVELS - 16)
    cells = np.array([(r["c"], r["n"]) for r in kept.groupBy(cell.alias("c")).agg(F.sum("n").alias("n")).orderBy("c").collect()], np.int64).reshape(-1, 2)
    if not len(cells):
        return kept.withColumn("stretch", F.lit(0).cast("long")), 1
    parts = np.maximum(1, cells[:, 1] // range_ids)
    before = np.cumsum(cells[:, 1]) - cells[:, 1]
    # a cut cell's parts are stretches of their own; the cells between share those that their sums fall in
    own = np.where(parts > 1, parts, 0)
    first = before // range_ids + np.cumsum(own) - own
    table = kept.sparkSession.createDataFrame([(int(c), int(f), int(p)) for (c, _), f, p in zip(cells, first, parts, strict=True)], "cell int, first long, parts long")
    placed = kept.withColumn("cell", cell.cast("int")).join(F.broadcast(table), "cell")
    stretch = F.col("first") + F.when(F.col("parts") > 1, 1 + F.pmod(F.xxhash64("doc_id"), F.col("parts"))).otherwise(0)
    return placed.withColumn("stretch", stretch).drop("cell", "first", "parts"), int(first[-1] + own[-1] + 1)


def pack(docs: DataFrame, end_id: int = 2, size: int = 4096, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text", range_ids: int = RANGE_IDS) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, and ids (little-endian u32).

    Null and empty texts are their end id alone; a text longer than a sequence spreads over several; ties in the key go by doc_id, and rows that repeat an id
    are packed each, next to each other; an empty table gives no rows; other columns are ignored, whatever their names. ``size`` must be a power of two."""
    if size & size - 1:
        raise ValueError("size must be a power of two")
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    kept = materialise(texts.mapInArrow(_tokenised(tokenizer or vocabulary(), end_id), "key long, doc_id long, width int, n long, ids binary"), "tokenised", "zstd")
    placed, stretches = _ranges(kept, range_ids)
    dealt = placed.repartition(max(1, min(MOST_TASKS, stretches // STRETCHES)), "stretch").sortWithinPartitions("stretch", "key", "doc_id", "ids")
    return dealt.select("key", "doc_id", "width", "ids").mapInArrow(
        _pack(size), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, ids binary"
    )


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet")).drop("ids")
