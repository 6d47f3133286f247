"""Benchmark decontamination by the q-gram lemma.

Benchmark texts are cut into segments of ``SEGMENT`` normalised bytes at half that stride (shorter items are one segment). A segment of m bytes
that occurs in a text with at most e = floor(m * RATE) edits shares at least m + 1 - q - q * e of its q-grams with it on diagonals
within a band of e + 1; so shared q-grams are counted in overlapping bands of 2(e + 1) diagonals, regions that meet the bound are
kept, and each is verified by an alignment restricted to its band. A text with a verified segment is contaminated. Items under ``SHORT`` normalised bytes, for which the lemma
gives no bound, are searched for as they are, between word borders and without edits."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.llm.suffix_dedup import _binary

Q, SEGMENT, RATE, SHORT = 8, 64, 0.08, 16
#: Benchmark bytes that go to every worker at once; more are searched for in turns.
TURN_BYTES = 8_000_000
SLICE = 1 << 20

_plain = np.full(256, 32, np.uint8)
for _c in range(128):
    if chr(_c).isalnum():
        _plain[_c] = ord(chr(_c).lower())
_plain[128:] = np.arange(128, 256)


def normalised(data: np.ndarray) -> np.ndarray:
    """Lower-case ASCII letters and digits and all other bytes from 128 on; runs of anything else are one space; none at the ends."""
    out = _plain[data]
    space = out == 32
    keep = ~space
    keep[1:] |= space[1:] & ~space[:-1]
    out = out[keep]
    if len(out) and out[0] == 32:
        out = out[1:]
    return out[:-1] if len(out) and out[-1] == 32 else out


def grams(data: np.ndarray) -> np.ndarray:
    """Every 8 bytes in a row as one number."""
    n = len(data) - Q + 1
    return np.ndarray((max(n, 0),), "<u8", np.ascontiguousarray(data).tobytes(), 0, (1,)) if n > 0 else np.empty(0, np.uint64)


class Segments:
    """The segments of a benchmark with an index of their q-grams."""

    def __init__(self, items: list[tuple[int, str]]):
        self.texts: list[np.ndarray] = []
        owner = []
        self.short: list[tuple[int, bytes]] = []
        for item, text in items:
            data = normalised(np.frombuffer((text or "").encode(), np.uint8))
            if len(data) < SHORT:
                if len(data):
                    self.short.append((item, b" " + data.tobytes() + b" "))
                continue
            starts = range(0, max(1, len(data) - SEGMENT // 2), SEGMENT // 2) if len(data) > SEGMENT else [0]
            for at in {min(s, max(0, len(data) - SEGMENT)) for s in starts}:
                piece = data[at : at + SEGMENT]
                self.texts.append(piece)
                owner.append(item)
        self.owner = np.array(owner, np.int64)
        self.sizes = np.array([len(t) for t in self.texts], np.int64)
        self.edits = (self.sizes * RATE).astype(np.int64)
        self.bound = np.maximum(1, self.sizes + 1 - Q - Q * self.edits)
        gram = [grams(t) for t in self.texts]
        keys = np.concatenate(gram) if gram else np.empty(0, np.uint64)
        segment = np.repeat(np.arange(len(gram)), [len(g) for g in gram])
        place = np.concatenate([np.arange(len(g)) for g in gram]) if gram else np.empty(0, np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.first, self.count = np.unique(keys[order], return_index=True, return_counts=True)
        self.segment, self.place = segment[order], place[order]
        self.bitmap = np.zeros(1 << 22, bool)
        self.bitmap[self.slot(self.keys)] = True
        self.least = int(self.bound.min()) if len(self.bound) else 1
        self.reach = SEGMENT + int(SEGMENT * RATE)

    @staticmethod
    def slot(keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(42)).astype(np.int64)

    def regions(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(text, segment, first diagonal of the band) of the regions that meet the bound. data: normalised texts in a row."""
        none = (np.empty(0, np.int64),) * 3
        found = grams(data)
        at = np.flatnonzero(self.bitmap[self.slot(found)])
        if not len(at):
            return none
        where = np.searchsorted(self.keys, found[at])
        where = np.minimum(where, len(self.keys) - 1)
        real = self.keys[where] == found[at]
        at, where = at[real], where[real]
        text = np.searchsorted(starts, at, "right") - 1
        if self.least > 1 and len(at):  # a region holds at least so many hits within its reach
            dense = np.zeros(len(at), bool)
            k = self.least - 1
            together = np.flatnonzero(at[k:] - at[: len(at) - k] <= self.reach) if len(at) > k else np.empty(0, int)
            mark = np.zeros(len(at) + 1, np.int64)
            np.add.at(mark, together, 1)
            np.add.at(mark, together + k + 1, -1)
            dense = np.cumsum(mark[:-1]) > 0
            at, where, text = at[dense], where[dense], text[dense]
        if not len(at):
            return none
        n = self.count[where]
        which = np.repeat(self.first[where], n) + np.arange(n.sum()) - np.repeat(np.append(0, np.cumsum(n)[:-1]), n)
        at, text, segment = np.repeat(at, n), np.repeat(text, n), self.segment[which]
        diagonal = at - starts[text] - self.place[which] + SEGMENT  # never negative
        wide = self.edits[segment] + 1
        band = diagonal // wide
        bands = int(band.max()) + 2
        key = (text * len(self.texts) + segment) * bands + band + 1
        key, hits = np.unique(np.concatenate([key, key - 1]), return_counts=True)
        pair, band = np.divmod(key, bands)
        t, s = np.divmod(pair, len(self.texts))
        enough = hits >= self.bound[s]
        t, s, band = t[enough], s[enough], band[enough]
        return t, s, (band - 1) * (self.edits[s] + 1) - SEGMENT

    def aligned(self, data: np.ndarray, low: np.ndarray, high: np.ndarray, segment: np.ndarray, diagonal: np.ndarray) -> np.ndarray:
        """Of each region, the least edits between its segment and any substring of data[low:high] whose alignment stays near
        the band. All regions advance together, one segment byte at a time."""
        out = np.empty(len(segment), np.int64)
        for at in range(0, len(segment), 4096):
            out[at : at + 4096] = self._aligned(data, *(x[at : at + 4096] for x in (low, high, segment, diagonal)))
        return out

    def _aligned(self, data, low, high, segment, diagonal):
        width = 4 * (int(self.edits.max()) + 1) + 1
        size = self.sizes[segment]
        pieces = np.zeros((len(segment), int(size.max())), np.uint8)
        for k, s in enumerate(segment):
            pieces[k, : size[k]] = self.texts[s]
        big, steps = SEGMENT + 1, np.arange(width)
        first = (low + diagonal - self.edits[segment] - 1)[:, None] + steps
        row = np.zeros((len(segment), width), np.int64)  # after i bytes, column k: text position first + i + k
        for i in range(pieces.shape[1]):
            at = first + i
            inside = (at >= low[:, None]) & (at < high[:, None])
            same = inside & (data[np.minimum(np.maximum(at, 0), len(data) - 1)] == pieces[:, i, None])
            shifted = np.full_like(row, big)
            shifted[:, :-1] = row[:, 1:]
            best = np.minimum(row + np.where(inside, ~same, big), shifted + 1)
            best = np.minimum.accumulate(best - steps, axis=1) + steps
            row = np.where((size > i)[:, None], best, row)
        return row.min(axis=1)


def _search(items: list[tuple[int, str]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        segments = Segments(items)
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            offsets, data = _binary(batch.column(1))
            row, out = 0, []
            while row < len(ids) and (len(segments.texts) or segments.short):
                last = max(row + 1, int(np.searchsorted(offsets, offsets[row] + SLICE, "right")) - 1)
                texts = [normalised(data[a:b]) for a, b in zip(offsets[row:last], offsets[row + 1 : last + 1], strict=True)]
                padded = [np.append(t, np.zeros(Q, np.uint8)) for t in texts]
                joined = np.concatenate(padded)
                starts = np.append(0, np.cumsum([len(t) for t in padded]))
                for item, words in segments.short:
                    hits = [row + k for k, x in enumerate(texts) if words in b" " + x.tobytes() + b" "]
                    out.append(np.array([(ids[k], item) for k in hits], np.int64).reshape(-1, 2))
                t, s, d = segments.regions(joined, starts[:-1]) if segments.texts else (np.empty(0, np.int64),) * 3
                if len(t):
                    good = segments.aligned(joined, starts[t], starts[t + 1] - Q, s, d) <= segments.edits[s]
                    hits = np.unique(np.column_stack([ids[row + t[good]], segments.owner[s[good]]]), axis=0)
                    out.append(hits)
                row = last
            if out:
                doc, item = np.concatenate(out).astype(np.int64).T
                yield pa.RecordBatch.from_arrays([pa.array(doc), pa.array(item)], ["doc_id", "item_id"])

    return run


def _turns(benchmark: DataFrame) -> Iterator[list[tuple[int, str]]]:
    """The items in turns of about TURN_BYTES."""
    held, size = [], 0
    for r in benchmark.select("item_id", "text").where("item_id is not null and text is not null").orderBy("item_id").toLocalIterator():
        held.append((int(r["item_id"]), r["text"]))
        size += len(r["text"])
        if size >= TURN_BYTES:
            yield held
            held, size = [], 0
    yield held


def contaminated_pairs(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id), once each: the text holds a segment of the item within the edit budget.

    Null and empty texts or items match nothing, nor do items of signs alone; items under 16 normalised bytes match as whole words; whole texts are searched,
    with no cap; rows without an id match nothing; rows that repeat an id are one document, items that repeat one are one item; equal texts match equally; an empty table gives no rows;
    other columns are ignored; a benchmark of any size is searched for in turns that fit a worker."""
    texts = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).cast("binary").alias("text"))
    found = None
    for items in _turns(benchmark):
        part = texts.mapInArrow(_search(items), "doc_id long, item_id long")
        found = part if found is None else found.union(part)
    return found.distinct()


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that hold no benchmark segment, with all their columns. Rows without an id stay, as null, empty and clean texts do; of rows that repeat an id all go where one holds
    a segment; an empty table gives no rows."""
    bad = contaminated_pairs(docs, benchmark).select(F.col("doc_id").alias("_bad")).distinct()
    return docs.join(bad, docs["doc_id"] == bad["_bad"], "left_anti")


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: doc_id, contaminated, n_items, item_ids (ascending, comma-joined)."""
    docs, benchmark = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "benchmark"))
    per = contaminated_pairs(docs, benchmark).groupBy("doc_id").agg(F.count("*").alias("n_items"), F.array_join(F.array_sort(F.collect_list("item_id")), ",").alias("item_ids"))
    return (
        docs.select("doc_id")
        .join(per, "doc_id", "left")
        .select("doc_id", F.col("n_items").isNotNull().alias("contaminated"), F.coalesce("n_items", F.lit(0)).alias("n_items"), F.coalesce("item_ids", F.lit("")).alias("item_ids"))
    )
