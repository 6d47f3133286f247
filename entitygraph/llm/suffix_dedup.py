"""Suffix-array dedup: every byte covered by a long string that also starts earlier in the corpus.

The construction is blockwise, with a locally consistent difference cover. A text position belongs to the cover if its
``GRAM``-byte string has the least hash among those of a ``length``-byte window (the leftmost of equals), so that two windows
with equal bytes hold a cover position at the same shift: the property that a difference cover gives to long ties. (A cover of fixed residues has it too, but at the
sparsest that a window allows it keeps one position in eight, this one about one in forty.)

The suffixes at cover positions are sorted: by their first eight bytes, which range partitioning cuts into blocks of the suffix array, one a task; then by the name of their
whole gram, and then, where they tie beyond it, by a rank of the cover sample that is computed beforehand: the name of all that the windows around the cover position (a run) hold together.
In that order equals are neighbours. Runs of equal rank tie over their whole length, so comparing neighbours settles all their windows and only the first of each rank stays. Neighbours that share a gram
but not a rank are the long ties that the ranks leave open: their runs are refined and sorted again, in blocks of windows and then window by window.

A block of the array is read in one pass with two rows in memory, and what it cannot know, whether its first and last groups go on in the blocks beside it, is settled from two rows a block. So a
group of equal suffixes may hold any share of the corpus, and is cut like any other range.

Names are 64-bit hashes of random byte values; a false tie needs a collision within a bucket whose own key is a second 64-bit hash."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.shared import discard, materialise, release

GRAM = 24
SLICE = 1 << 19
#: Windows that are settled together where a run is open.
BLOCK = 8
_BASE = 0x9E3779B97F4A7C15
_MASK = (1 << 64) - 1


class _Powers:
    """Powers of an odd base and of its inverse, modulo 2**64, and a random value for each byte."""

    def __init__(self, size: int):
        rng = np.random.default_rng(20240607)
        self.value = rng.integers(1, 1 << 63, 256, dtype=np.uint64)
        up = np.full(size + 1, _BASE, np.uint64)
        up[0] = 1
        self.up = np.cumprod(up)
        down = np.full(size + 1, pow(_BASE, -1, 1 << 64), np.uint64)
        down[0] = 1
        self.down = np.cumprod(down)


_powers: _Powers | None = None


def powers(size: int) -> _Powers:
    global _powers
    if _powers is None or len(_powers.up) <= size:
        _powers = _Powers(max(size, SLICE + 65536))
    return _powers


def mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def prefix_sums(data: np.ndarray) -> tuple[np.ndarray, _Powers]:
    p = powers(len(data) + 1)
    sums = np.empty(len(data) + 1, np.uint64)
    sums[0] = 0
    np.cumsum(p.value[data] * p.up[: len(data)], out=sums[1:])
    return sums, p


def pieces(offsets: np.ndarray, length: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """Slices of whole texts of about SLICE bytes; a longer text is cut into slices that overlap by ``length`` - 1 bytes.
    Gives the slice's bounds, and for each text in it the row, its start in the slice and the offset of that start in the text."""
    n, row = len(offsets) - 1, 0
    while row < n:
        start = offsets[row]
        last = max(row + 1, int(np.searchsorted(offsets, start + SLICE, "right")) - 1)
        if last == row + 1 and offsets[last] - start > SLICE:
            step = SLICE - (length - 1)
            for at in range(0, max(1, int(offsets[last] - start) - (length - 1)), step):
                end = min(int(offsets[last]), int(start) + at + SLICE)
                yield int(start) + at, end, np.array([row]), np.array([0]), np.array([at])
        else:
            rows = np.arange(row, last)
            yield int(start), int(offsets[last]), rows, (offsets[row:last] - start).astype(np.int64), np.zeros(last - row, np.int64)
        row = last


def cover_runs(data: np.ndarray, starts: np.ndarray, length: int):
    """(head, bucket, rank, text index, first window, number of windows, shift to the cover position) of every run of windows with one cover position; head is the first eight bytes of the
    suffix there, as a number in their order. starts: where the texts of the slice begin, ascending."""
    none = (np.empty(0, np.int64),) * 7
    width = length - GRAM + 1
    if len(data) < length:
        return none
    sums, p = prefix_sums(data)
    m = len(data) - GRAM + 1
    h = mixed((sums[GRAM:] - sums[:m]) * p.down[:m])
    bits = np.uint64(20)
    key = ((h >> bits) << bits) | np.arange(m, dtype=np.uint64)
    span = 1
    while 2 * span <= width:
        key = np.minimum(key[: len(key) - span], key[span:])
        span *= 2
    if span < width:
        rest = width - span
        key = np.minimum(key[: len(key) - rest], key[rest:])
    cover = (key & np.uint64((1 << 20) - 1)).astype(np.int64)
    ends = np.append(starts[1:], len(data))
    whole = ends - starts >= length
    if not whole.any():
        return none
    valid = np.zeros(len(cover) + 1, np.int8)
    valid[starts[whole]] = 1
    valid[np.minimum(ends[whole] - length + 1, len(cover))] -= 1
    valid = np.cumsum(valid[:-1], dtype=np.int8) > 0
    begins = np.empty(len(cover), bool)
    begins[0] = True
    np.not_equal(cover[1:], cover[:-1], out=begins[1:])
    begins[starts[whole]] = True
    first = np.flatnonzero(begins & valid)
    text = np.searchsorted(starts, first, "right") - 1
    stop = np.minimum(np.append(first[1:], len(cover)), ends[text] - length + 1)
    size = stop - first + length - 1
    at = cover[first]
    rank = mixed((sums[first + size] - sums[first]) * p.down[first] + (at - first).astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D) + size.astype(np.uint64))
    head = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(data, 8)[at]).view(">u8").ravel().astype(np.uint64) ^ np.uint64(1 << 63)
    return head.view(np.int64), h[at].view(np.int64), rank.view(np.int64), text, first, stop - first, at - first


def _binary(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets and bytes of a binary column; nulls are empty."""
    column = column.fill_null(b"") if column.null_count else column
    _, offsets, data = column.buffers()
    kind = np.int64 if pa.types.is_large_binary(column.type) else np.int32
    offsets = np.frombuffer(offsets, kind, len(column) + 1, column.offset * np.dtype(kind).itemsize).astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.empty(0, np.uint8)
    return offsets, data


def _runs(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            offsets, data = _binary(batch.column(1))
            for lo, hi, rows, starts, shift in pieces(offsets, length):
                head, bucket, rank, text, first, n, at = cover_runs(data[lo:hi], starts, length)
                if len(first):
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(head), pa.array(bucket), pa.array(rank), pa.array(ids[rows[text]]), pa.array(first - starts[text] + shift[text]), pa.array(n.astype(np.int32)), pa.array(at.astype(np.int32))],
                        ["head", "bucket", "rank", "doc_id", "lo", "n", "at"],
                    )

    return run


def _blocks(length: int):
    """The asked runs of each text in blocks of up to BLOCK windows at the same shifts from the cover position. A block's bucket is the part that all
    its possible windows share, its rank the part that its own windows cover together."""
    core = length - BLOCK + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            offsets, data = _binary(batch.column(1))
            asked = batch.column(2)
            held, size = [], 0
            for i in range(len(ids)):
                if not asked[i].is_valid:
                    continue
                runs = asked.slice(i, 1).flatten()
                lo, n, at, bucket, head = (runs.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(5))
                order = np.argsort(lo)
                lo, n, at, bucket, head = lo[order], n[order], at[order], bucket[order], head[order]
                text = data[offsets[i] : offsets[i + 1]]
                k = 0
                while k < len(lo):  # runs within SLICE bytes at a time
                    last = max(k + 1, int(np.searchsorted(lo, lo[k] + SLICE, "right")))
                    base = int(lo[k])
                    sums, p = prefix_sums(text[base : int((lo[k:last] + n[k:last]).max()) + length - 1])
                    count = n[k:last]
                    which = np.repeat(np.arange(k, last), count)
                    start = lo[which] - base + np.arange(len(which)) - np.repeat(np.cumsum(count) - count, count)
                    group = (lo[which] + at[which] - base - start) // BLOCK  # by shift: how far the window starts before the cover position
                    fresh = np.append(True, (which[1:] != which[:-1]) | (group[1:] != group[:-1]))
                    first = np.flatnonzero(fresh)
                    own, g, begin = which[first], group[first], start[first]
                    number = np.diff(np.append(first, len(start)))
                    middle = lo[own] + at[own] - base - BLOCK * g  # where the last possible window of the block starts
                    inner = mixed((sums[middle + core] - sums[middle]) * p.down[middle] + g.astype(np.uint64) * np.uint64(0x9FB21C651E98DF25))
                    outer = mixed((sums[begin + number + length - 1] - sums[begin]) * p.down[begin] + (middle - begin).astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D) + number.astype(np.uint64))
                    held.append((head[own], inner ^ bucket[own].view(np.uint64), outer, np.full(len(own), ids[i]), begin + base, number))
                    size += len(start)
                    k = last
                    if size > 200_000:
                        yield _block_batch(held)
                        held, size = [], 0
            if held:
                yield _block_batch(held)

    return run


def _block_batch(held: list[tuple]) -> pa.RecordBatch:
    head, bucket, rank, doc, lo, n = (np.concatenate(x) for x in zip(*held, strict=True))
    return pa.RecordBatch.from_arrays(
        [pa.array(head), pa.array(bucket.view(np.int64)), pa.array(rank.view(np.int64)), pa.array(doc), pa.array(lo), pa.array(n.astype(np.int32)), pa.array(np.zeros(len(n), np.int32))],
        ["head", "bucket", "rank", "doc_id", "lo", "n", "at"],
    )


def _windows(length: int):
    """The windows of the asked blocks of each text, each with its hash as rank."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            offsets, data = _binary(batch.column(1))
            asked = batch.column(2)
            for i in range(len(ids)):
                if not asked[i].is_valid:
                    continue
                blocks = asked.slice(i, 1).flatten()
                lo, n, bucket, head = (blocks.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (0, 1, 3, 4))
                order = np.argsort(lo)
                lo, n, bucket, head = lo[order], n[order], bucket[order], head[order]
                text = data[offsets[i] : offsets[i + 1]]
                k = 0
                while k < len(lo):
                    last = max(k + 1, int(np.searchsorted(lo, lo[k] + SLICE, "right")))
                    base, count = int(lo[k]), n[k:last]
                    sums, p = prefix_sums(text[base : int((lo[k:last] + count).max()) + length - 1])
                    start = np.repeat(lo[k:last] - base - np.cumsum(count) + count, count) + np.arange(count.sum())
                    h = mixed((sums[start + length] - sums[start]) * p.down[start])
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.repeat(head[k:last], count)), pa.array(np.repeat(bucket[k:last], count)), pa.array(h.view(np.int64)), pa.array(np.full(len(h), ids[i])), pa.array(start + base),
                         pa.array(np.ones(len(h), np.int32)), pa.array(np.zeros(len(h), np.int32))],
                        ["head", "bucket", "rank", "doc_id", "lo", "n", "at"],
                    )
                    k = last

    return run


UNIT = "head long, bucket long, rank long, doc_id long, lo long, n int, at int"
NAMES = ("head", "bucket", "rank", "doc_id", "lo", "n", "at")
SETTLED, OPEN, FIRST, SECOND, LAST, LAST_SHARING = range(6)


def _neighbours(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One block of the sorted units. Those that are not the first of their rank are settled; firsts that share a bucket with the first before or after them are open.
    The block's own first, second and last firsts are told as well: whether its first and last go on in the blocks beside it is decided from them."""
    part = TaskContext.get().partitionId()
    key: np.ndarray | None = None  # of the last row
    before, shares, seen = None, False, 0  # the last first, whether it shares the bucket of the one before it, firsts so far

    def told(kind: int, columns: np.ndarray) -> pa.RecordBatch:
        size = columns.shape[1]
        arrays = [pa.array(np.full(size, k, np.int32)) for k in (part, kind)]
        arrays += [pa.array(c.astype(np.int32 if name in ("n", "at") else np.int64)) for name, c in zip(NAMES, columns, strict=True)]
        return pa.RecordBatch.from_arrays(arrays, ["part", "kind", *NAMES])

    for batch in batches:
        if not batch.num_rows:
            continue
        columns = np.stack([c.to_numpy().astype(np.int64) for c in batch.columns])
        again = np.append(key is not None and bool((columns[:3, 0] == key).all()), (columns[:3, 1:] == columns[:3, :-1]).all(axis=0))
        key = columns[:3, -1].copy()
        if again.any():
            yield told(SETTLED, columns[:, again])
        firsts = columns[:, ~again]
        if not firsts.shape[1]:
            continue
        for kind, i in ((FIRST, -seen), (SECOND, 1 - seen)):
            if 0 <= i < firsts.shape[1]:
                yield told(kind, firsts[:, i : i + 1])
        chain = firsts if before is None else np.column_stack([before, firsts])
        joined = (chain[:2, 1:] == chain[:2, :-1]).all(axis=0)
        sharing = np.append(shares, joined)
        open_ = sharing[:-1] | joined  # of all but the last
        if seen <= 1 and len(open_) and (before is None or seen == 1):
            open_[0] = False  # the block's own first
        if open_.any():
            yield told(OPEN, chain[:, :-1][:, open_])
        before, shares = chain[:, -1].copy(), bool(sharing[-1])
        seen += firsts.shape[1]
    if seen > 1:
        yield told(LAST_SHARING if shares else LAST, before[:, None])


def _across(rows: list) -> list[tuple[int, tuple]]:
    """(kind, unit) of the first and last firsts of all blocks, whose order is that of their numbers. rows: three a block at most."""
    blocks: dict[int, dict[int, tuple]] = {}
    for r in rows:
        blocks.setdefault(r["part"], {})[r["kind"]] = tuple(r[n] for n in NAMES)
    out: list[tuple[int, tuple]] = []
    pending: tuple | None = None  # a first whose next one is not yet known
    shares = False

    def meet(following: tuple) -> None:
        if pending is not None and (shares or pending[:2] == following[:2]):
            out.append((OPEN, pending))

    for part in sorted(blocks):
        told = blocks[part]
        first, second = told[FIRST], told.get(SECOND)
        if pending is not None and first[:3] == pending[:3]:
            out.append((SETTLED, first))
        else:
            meet(first)
            pending, shares = first, pending is not None and pending[:2] == first[:2]
        if second is not None:
            meet(second)
            pending, shares = (told[LAST_SHARING], True) if LAST_SHARING in told else (told[LAST], False)
    if pending is not None and shares:
        out.append((OPEN, pending))
    return out


def _settle(units: DataFrame, name: str) -> tuple[DataFrame, DataFrame]:
    """Of sorted units: the windows of those that are not the first of their rank, and the first of each rank in buckets of several."""
    key = ["head", "bucket", "rank", "doc_id", "lo"]
    array = units.repartitionByRange(*key).sortWithinPartitions(*key)
    told = materialise(array.select(*NAMES).mapInArrow(_neighbours, f"part int, kind int, {UNIT}"), f"{name}-array")
    release(units.sparkSession)
    edges = _across(told.where(F.col("kind") >= FIRST).collect())  # three rows a block of the array at most
    small = units.sparkSession.createDataFrame([(k, *r) for k, r in edges], f"kind int, {UNIT}")
    every = told.where(F.col("kind") < FIRST).select("kind", *NAMES).unionByName(small)
    return every.where(F.col("kind") == SETTLED).select("doc_id", "lo", "n"), every.where(F.col("kind") == OPEN).select(*NAMES)


def repeated_windows(texts: DataFrame, length: int = 100) -> DataFrame:
    """(doc_id, lo, n): runs of n windows of ``length`` bytes, from byte lo on, that occur with an earlier start as well.
    texts: doc_id, binary text. Ties are settled for whole runs, then for blocks of the open ones, then for the windows of the open blocks."""
    settled, left = _settle(texts.mapInArrow(_runs(length), UNIT), "runs")
    for refined, name in ((_blocks, "blocks"), (_windows, "windows")):
        asked = left.groupBy("doc_id").agg(F.collect_list(F.struct("lo", "n", "at", "bucket", "head")).alias("asked"))
        units = materialise(texts.join(asked, "doc_id").select("doc_id", "text", "asked").mapInArrow(refined(length), UNIT), name)
        release(texts.sparkSession)
        more, left = _settle(units, name)
        discard(units)
        settled = settled.union(more)
    return settled


def covered(lo: np.ndarray, n: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Maximal covered spans [start, end) of runs of windows."""
    order = np.argsort(lo, kind="stable")
    start, end = lo[order], (lo + n + length - 1)[order]
    reach = np.maximum.accumulate(end)
    fresh = np.append(True, start[1:] > reach[:-1])
    return start[fresh], np.append(reach[:-1][fresh[1:]], reach[-1])


def _keep(length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            offsets, data = _binary(batch.column(1))
            removed, spans, kept = [], [], []
            los, ns = batch.column(2), batch.column(3)
            for i in range(batch.num_rows):
                text = data[offsets[i] : offsets[i + 1]]
                if los[i].is_valid:
                    start, end = covered(los.slice(i, 1).flatten().to_numpy(), ns.slice(i, 1).flatten().to_numpy().astype(np.int64), length)
                    removed.append(int((end - start).sum()))
                    spans.append(len(start))
                    edges = np.concatenate([[0], np.ravel(np.column_stack([start, end])), [len(text)]])
                    kept.append(b"".join(text[a:b].tobytes() for a, b in zip(edges[::2], edges[1::2], strict=True)))
                else:
                    removed.append(0)
                    spans.append(0)
                    kept.append(text.tobytes())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(np.diff(offsets)), pa.array(removed, pa.int64()), pa.array(spans, pa.int64()),
                 pa.array([hashlib.sha256(x).hexdigest() for x in kept]), pa.array(kept, pa.binary())],
                ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"],
            )

    return run


def suffix_dedup(docs: DataFrame, length: int = 100, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 and kept (the bytes that remain; cutting bytes may break a character).

    Null texts are empty; texts under ``length`` bytes keep all; of equal strings the first by (doc_id, offset) stays; other
    columns are ignored, whatever their names; an empty table gives no rows. Rows need distinct ids."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))
    found = repeated_windows(texts, length).groupBy("doc_id").agg(F.collect_list("lo").alias("los"), F.collect_list("n").alias("ns"))
    both = texts.join(found, "doc_id", "left").select("doc_id", "text", "los", "ns")
    return both.mapInArrow(_keep(length), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup(spark.read.parquet(f"{sf_dir}/documents.parquet"), 100).drop("kept")
