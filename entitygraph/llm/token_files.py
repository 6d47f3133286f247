"""Binary token files: one concatenated id array with Elias-Fano document boundaries.

A file image is: magic ``EGTK``, version, bytes per id, number of documents (u64), number of ids (u64), first document id (i64);
the Elias-Fano sequence of document boundaries, that of the document ids less the first, then the ids, little-endian. An
Elias-Fano sequence is: number of values (u64), low width (u8), number of 64-bit high words (u64), number of select samples
(u64); low bits packed; high words; select samples (u64), the position of every SAMPLE-th one.

Images of about ``shard_ids`` ids are rows of a Parquet dataset in ascending document order, which any file system
that Spark writes to can hold."""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from entitygraph.llm.tokens import WORD_BLOCK, blocks, encoder, vocabulary
from entitygraph.shared import materialise, new_path

MAGIC = b"EGTK\x01"
SAMPLE = 256
SHARD_IDS = 1_000_000
#: Rows of file starts that are broadcast; more are joined by shuffling.
BROADCAST_ROWS = 500_000


class EliasFano:
    """A non-decreasing sequence of integers from 0 on, in about 2 + log2(universe / n) bits each."""

    def __init__(self, n: int, width: int, low: np.ndarray, high: np.ndarray, samples: np.ndarray):
        self.n, self.width, self.low, self.high, self.samples = n, width, low, high, samples

    @classmethod
    def encode(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, np.uint64)
        n = len(values)
        top = int(values[-1]) + 1 if n else 1
        width = max(0, (top // max(n, 1)).bit_length() - 1)
        low = np.packbits((values[:, None] >> np.arange(width, dtype=np.uint64) & np.uint64(1)).astype(np.uint8).ravel(), bitorder="little")
        ones = (values >> np.uint64(width)).astype(np.int64) + np.arange(n)
        words = (int(ones[-1]) if n else 0) // 64 + 1
        bits = np.zeros(words * 64, np.uint8)
        bits[ones] = 1
        return cls(n, width, low, np.packbits(bits, bitorder="little").view("<u8"), ones[::SAMPLE].astype("<u8"))

    def _low(self, i: np.ndarray) -> np.ndarray:
        if not self.width:
            return np.zeros(len(i), np.uint64)
        at = i.astype(np.int64)[:, None] * self.width + np.arange(self.width)
        bits = (self.low[at >> 3] >> (at & 7).astype(np.uint8)) & 1
        return (bits.astype(np.uint64) << np.arange(self.width, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)

    def select(self, i: int) -> int:
        """Value i."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        return int(self.select_many(np.array([i]))[0])

    def select_many(self, i: np.ndarray) -> np.ndarray:
        """Values i (from 0 to n - 1): from the nearest sample on, word by word for all that are not yet there, then bit by bit inside the word."""
        if not len(i):
            return np.empty(0, np.int64)
        i = np.asarray(i, np.int64)
        at = self.samples[i // SAMPLE].astype(np.int64)
        word, left = at >> 6, i % SAMPLE
        skip = (at & 63).astype(np.uint64)
        bits = self.high[word] >> skip << skip  # from the sample's own one on
        open_ = np.arange(len(i))
        while len(open_):
            ones = np.bitwise_count(bits[open_]).astype(np.int64)
            open_, ones = (x[ones <= left[open_]] for x in (open_, ones))
            left[open_] -= ones
            word[open_] += 1
            bits[open_] = self.high[word[open_]]
        open_ = np.flatnonzero(left)
        while len(open_):
            bits[open_] &= bits[open_] - np.uint64(1)
            left[open_] -= 1
            open_ = open_[left[open_] > 0]
        low_one = bits & (~bits + np.uint64(1))
        place = (word << 6) + np.bitwise_count(low_one - np.uint64(1)).astype(np.int64)
        return (place - i << self.width) | self._low(i).astype(np.int64)

    def values(self) -> np.ndarray:
        """All values, selected in blocks."""
        return np.concatenate([np.empty(0, np.int64), *(self.select_many(np.arange(k, min(k + 65536, self.n))) for k in range(0, self.n, 65536))])

    def to_bytes(self) -> bytes:
        head = struct.pack("<QBQQ", self.n, self.width, len(self.high), len(self.samples))
        return head + self.low.tobytes() + self.high.tobytes() + self.samples.tobytes()

    @classmethod
    def read(cls, data: bytes, at: int) -> tuple[EliasFano, int]:
        n, width, words, samples = struct.unpack_from("<QBQQ", data, at)
        at += struct.calcsize("<QBQQ")
        lows = -(-n * width // 8)
        low = np.frombuffer(data, np.uint8, lows, at)
        high = np.frombuffer(data, "<u8", words, at + lows)
        at += lows + 8 * words
        return cls(n, width, low, high, np.frombuffer(data, "<u8", samples, at)), at + 8 * samples


def file_image(doc_ids: np.ndarray, offsets: np.ndarray, ids: np.ndarray, width: int) -> bytes:
    """offsets: n + 1 boundaries from 0; doc_ids ascending."""
    first = int(doc_ids[0]) if len(doc_ids) else 0
    head = MAGIC + struct.pack("<BQQq", width, len(doc_ids), len(ids), first)
    gaps = np.asarray(doc_ids, np.int64).view(np.uint64) - np.uint64(first & (1 << 64) - 1)
    return head + EliasFano.encode(offsets).to_bytes() + EliasFano.encode(gaps).to_bytes() + ids.astype(f"<u{width}").tobytes()


class TokenFile:
    """A file image: document ids, boundaries and ids, read in place."""

    def __init__(self, data: bytes):
        if data[: len(MAGIC)] != MAGIC:
            raise ValueError("not a token file")
        width, self.n_docs, self.n_ids, self.first = struct.unpack_from("<BQQq", data, len(MAGIC))
        at = len(MAGIC) + struct.calcsize("<BQQq")
        self.bounds, at = EliasFano.read(data, at)
        self.gaps, at = EliasFano.read(data, at)
        self.ids = np.frombuffer(data, f"<u{width}", self.n_ids, at)

    def document(self, i: int) -> np.ndarray:
        return self.ids[self.bounds.select(i) : self.bounds.select(i + 1)]

    def doc_ids(self) -> np.ndarray:
        return self.gaps.values() + self.first


def _write(path: str, end_id: int, shard_ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = encoder(path)
        width = 2 if max(tokens.size - 1, end_id) < 1 << 16 else 4
        part, number = TaskContext.get().partitionId(), 0
        docs, sizes, held, total = [], [], [], 0

        def image():
            offsets = np.append(0, np.cumsum(np.concatenate(sizes), dtype=np.int64))
            data = file_image(np.concatenate(docs), offsets, np.concatenate(held), width)
            return pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int32()), pa.array([number], pa.int32()), pa.array([len(offsets) - 1]), pa.array([total]), pa.array([data], pa.binary())],
                ["part", "number", "n_docs", "n_ids", "image"],
            )

        for batch in batches:
            for block in blocks(batch, 1, WORD_BLOCK):
                offsets, ids = tokens.encode(block.column(1), end_id)
                docs.append(block.column(0).to_numpy())
                sizes.append(np.diff(offsets))
                held.append(ids.astype(f"<u{width}"))
                total += len(ids)
                if total >= shard_ids:
                    yield image()
                    number, docs, sizes, held, total = number + 1, [], [], [], 0
        if docs:
            yield image()

    return run


def write_token_files(docs: DataFrame, path: str, end_id: int, tokenizer: str | None = None, shard_ids: int = SHARD_IDS, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Writes the ids of all texts, each with the end id after it, in ascending order of the document id.

    Null and empty texts are their end id alone; a text of any length lies in one file; rows that repeat an id lie next to each other, in the order of their texts;
    rows without an id come first, as id null is not a number: they are left out. An empty table gives no files; other columns are ignored, whatever their names."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    ordered = texts.where("doc_id is not null").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    images = ordered.mapInArrow(_write(tokenizer or vocabulary(), end_id, shard_ids), "part int, number int, n_docs long, n_ids long, image binary")
    images.write.option("compression", "zstd").parquet(path)


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for base, image in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            file = TokenFile(image.as_buffer().to_pybytes())
            for at in range(0, file.n_docs, 65536):
                bounds = file.bounds.select_many(np.arange(at, min(at + 65536, file.n_docs) + 1))
                wide = file.ids[bounds[0] : bounds[-1]].astype("<u4")
                local = (bounds - bounds[0]).tolist()
                sums = [zlib.crc32(wide[a:b]) for a, b in zip(local[:-1], local[1:], strict=True)]
                docs = file.gaps.select_many(np.arange(at, at + len(sums))) + file.first
                yield pa.RecordBatch.from_arrays([pa.array(docs), pa.array(bounds[:-1] + base), pa.array(np.diff(bounds)), pa.array(sums, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the files. The ids before a part are summed over parts, and
    those before a file over the files of its part, so no task sees more rows than a part has files or than there are parts."""
    files = spark.read.parquet(path)
    parts = files.groupBy("part").agg(F.sum("n_ids").alias("n"))
    bases = parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    own = (F.sum("n_ids").over(Window.partitionBy("part").orderBy("number")) - F.col("n_ids")).alias("own")
    starts = files.select("part", "number", "n_ids").select("part", "number", own).join(bases, "part").select("part", "number", (F.col("own") + F.col("base")).alias("start"))
    starts = materialise(starts, "starts")
    if starts.count() <= BROADCAST_ROWS:  # three numbers a row
        starts = F.broadcast(starts)
    placed = files.select("part", "number", "image").join(starts, ["part", "number"]).select("start", "image")
    return placed.mapInArrow(_read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "token-files")
    write_token_files(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, 1)
    return read_token_files(spark, path)
