"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

Every pair of active features interacts through vectors of ``RANK`` numbers; with the sum-of-squares identity a text's score takes time linear in its
features: the interactions are half of (sum of x v) squared less the sum of (x v) squared. Words count by presence, with length-normalised weights; the
statistics (shares of character classes, lengths, repetition) are features of their own and interact with words and with each other."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.llm.suffix_dedup import _binary
from entitygraph.llm.tokens import blocks
from entitygraph.llm.words import fold, hashed, labelled_sample, word_codes

WORD_BITS, RANK = 15, 6
#: Labelled rows that the model is fitted on, at most.
TRAIN_ROWS = 12_000
_kinds = np.zeros(256, np.uint8)
for _c in range(256):
    _ch = chr(_c)
    _kinds[_c] = 5 if _c > 127 else 0 if _ch.isupper() else 1 if _ch.islower() else 2 if _ch.isdigit() else 3 if _ch.isspace() else 4
KINDS = 6


def statistics(texts: pa.Array, offsets: np.ndarray, codes: np.ndarray, words: list[str]) -> np.ndarray:
    """One row of structure statistics and metadata for each text."""
    borders, data = _binary(texts.cast(pa.binary()))
    data = data[borders[0] : borders[-1]]
    borders = borders - borders[0]
    kind = _kinds[data]
    total = np.maximum(np.diff(borders), 1)
    shares = []
    for k in range(KINDS):
        before = np.append(0, np.cumsum(kind == k, dtype=np.int64))
        shares.append((before[borders[1:]] - before[borders[:-1]]) / total)
    n = np.diff(offsets)
    doc = np.repeat(np.arange(len(n)), n)
    some = np.maximum(n, 1)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) if words else np.empty(0, np.int64)
    last = np.fromiter((not w[-1:].isalnum() for w in words), bool, len(words)) if words else np.empty(0, bool)
    capital = np.fromiter((w.isupper() and len(w) > 1 for w in words), bool, len(words)) if words else np.empty(0, bool)
    mean = lambda x: np.bincount(doc, x, len(n)) / some
    length = sizes[codes] if len(codes) else codes
    pair = codes[:-1] * len(words) + codes[1:]
    inner = doc[:-1] == doc[1:]
    distinct = lambda d, c: np.bincount(np.unique(d * (int(c.max(initial=0)) + 1) + c) // (int(c.max(initial=0)) + 1), minlength=len(n))
    _, pairs = np.unique(pair[inner], return_inverse=True)
    words_share = distinct(doc, codes) / some if len(codes) else np.zeros(len(n))
    pairs_share = distinct(doc[:-1][inner], pairs) / np.maximum(n - 1, 1) if inner.any() else np.zeros(len(n))
    lines = pc.split_pattern(texts.cast(pa.large_string()), "\n")
    line_borders = lines.offsets.to_numpy()
    per = np.diff(line_borders)
    line_codes = lines.flatten().dictionary_encode().indices.to_numpy().astype(np.int64)
    line_share = distinct(np.repeat(np.arange(len(n)), per), line_codes) / np.maximum(per, 1)
    return np.column_stack(
        [*shares, np.log1p(total) / 8, np.log1p(n) / 6, mean(length) / 8, mean(last[codes] if len(codes) else codes), mean(capital[codes] if len(codes) else codes),
         words_share, pairs_share, line_share, np.log1p(n / np.maximum(per, 1)) / 4, (n == 0).astype(float)]
    )


STATISTICS = KINDS + 10


def features(texts: pa.Array, scale: tuple[np.ndarray, np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(offsets, word features, statistics): word features are each text's distinct hashed words."""
    texts = texts.fill_null("")
    offsets, codes, words = word_codes(texts)
    stats = statistics(texts, offsets, codes, words)
    table = np.fromiter(map(hashed(WORD_BITS), words), np.int64, len(words)) if words else np.empty(0, np.int64)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    keys = np.unique(doc << WORD_BITS | (table[codes] if len(codes) else codes))
    borders = np.searchsorted(keys >> WORD_BITS, np.arange(len(offsets)))
    return borders, keys & ((1 << WORD_BITS) - 1), stats


class FactorisationMachine:
    """Weights of word slots and statistics; statistics are standardised."""

    def __init__(self, rank: int = RANK, seed: int = 1):
        rng = np.random.default_rng(seed)
        self.n = (1 << WORD_BITS) + STATISTICS
        self.bias, self.w = 0.0, np.zeros(self.n)
        self.v = rng.normal(0, 0.02, (self.n, rank))
        self.mean, self.spread = np.zeros(STATISTICS), np.ones(STATISTICS)

    def _sums(self, borders, slots, stats):
        n = np.diff(borders)
        x = np.repeat(1 / np.sqrt(np.maximum(n, 1)), n)
        z = np.clip((stats - self.mean) / self.spread, -4, 4)
        v = self.v[slots] * x[:, None]
        doc = np.repeat(np.arange(len(n)), n)
        add = lambda values: np.add.reduceat(np.vstack([values, np.zeros((1, values.shape[1]))]), borders[:-1]) * (n > 0)[:, None]
        vs = self.v[-STATISTICS:]
        linear = np.bincount(doc, self.w[slots] * x, len(n)) + z @ self.w[-STATISTICS:]
        total = add(v) + z @ vs
        squares = add(v * v).sum(axis=1) + (z * z) @ (vs * vs).sum(axis=1)
        return self.bias + linear + 0.5 * ((total * total).sum(axis=1) - squares), x, z, total

    def score(self, borders, slots, stats) -> np.ndarray:
        raw = self._sums(borders, slots, stats)[0]
        return 1 / (1 + np.exp(-np.clip(raw, -30, 30)))

    def fit(self, borders, slots, stats, y, epochs: int = 12, batch: int = 128, rate: float = 0.05, decay: float = 1e-4, seed: int = 2) -> FactorisationMachine:
        """Logistic loss by adaptive gradients over shuffled batches."""
        self.mean, self.spread = stats.mean(axis=0), np.maximum(stats.std(axis=0), 1e-3)
        share = min(max(y.mean(), 1e-3), 1 - 1e-3)
        self.bias = float(np.log(share / (1 - share)))
        gw, gv, gb = np.full(self.n, 1e-6), np.full_like(self.v, 1e-6), 1e-6
        rng = np.random.default_rng(seed)
        n = np.diff(borders)
        epochs = max(epochs, min(60, 30_000 // max(len(y), 1)))
        for _ in range(epochs):
            order = rng.permutation(len(y))
            for at in range(0, len(y), batch):
                rows = order[at : at + batch]
                size = n[rows]
                cut = np.append(0, np.cumsum(size))
                some = slots[np.repeat(borders[rows] - cut[:-1], size) + np.arange(cut[-1])]
                raw, x, z, total = self._sums(cut, some, stats[rows])
                error = (1 / (1 + np.exp(-np.clip(raw, -30, 30))) - y[rows]) / len(rows)
                e = np.repeat(error, size)
                dw = np.bincount(some, e * x, self.n) + decay * self.w
                dw[-STATISTICS:] += error @ z
                t = np.repeat(total, size, axis=0)
                per = (e * x)[:, None] * (t - self.v[some] * x[:, None])
                dv = np.column_stack([np.bincount(some, per[:, k], self.n) for k in range(per.shape[1])]) + decay * self.v
                dv[-STATISTICS:] += (error[:, None] * z).T @ total - ((error @ (z * z))[:, None]) * self.v[-STATISTICS:]
                gw += dw * dw
                gv += dv * dv
                gb += error.sum() ** 2
                self.w -= rate * dw / np.sqrt(gw)
                self.v -= rate * 0.5 * dv / np.sqrt(gv)
                self.bias -= rate * error.sum() / np.sqrt(gb)
        return self


def _featured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for block in blocks(batch, 0):
            borders, slots, stats = features(block.column(0))
            words = pa.ListArray.from_arrays(pa.array(borders.astype(np.int32)), pa.array(slots.astype(np.int16)))
            rows = pa.ListArray.from_arrays(pa.array(np.arange(len(stats) + 1, dtype=np.int32) * STATISTICS), pa.array(stats.ravel()))
            yield pa.RecordBatch.from_arrays([words, rows, block.column(1)], ["slots", "stats", "y"])


def fit_quality(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS, divisor: int = 3, left_out: int = 1, label: str = "quality") -> FactorisationMachine:
    """Fits on a bounded sample of labelled rows; what reaches the driver is their features, two bytes for each distinct hashed word of a text: 64 KB a row at the very most, usually under
    one. Labelled rows without a text, or that repeat an id, count as they stand (the highest label of an id); with no
    labelled row the model scores one half everywhere."""
    sample = labelled_sample(docs, labels, label, divisor, left_out, most)
    rows = sample.mapInArrow(_featured, "slots array<smallint>, stats array<double>, y int").toArrow()
    model = FactorisationMachine()
    if not rows.num_rows:
        return model
    lists = rows.column("slots").combine_chunks()
    borders = lists.offsets.to_numpy().astype(np.int64)
    stats = rows.column("stats").combine_chunks().flatten().to_numpy().reshape(-1, STATISTICS)
    return model.fit(borders - borders[0], lists.flatten().to_numpy().astype(np.int64), stats, rows.column("y").to_numpy().astype(float))


def quality_scores(docs: DataFrame, model: FactorisationMachine) -> DataFrame:
    """(doc_id, score): the whole text of every row, nulls as empty texts. Equal texts have equal scores; rows that repeat an id, or have none, are scored each; an empty table gives no rows;
    other columns are ignored, whatever their names."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch, 1):
                yield pa.RecordBatch.from_arrays([block.column(0), pa.array(model.score(*features(block.column(1))))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "doc_id long, score double")


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    scored = quality_scores(docs, fit_quality(docs, labels))
    return scored.select("doc_id", (fold(3) == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
