"""Toxicity: significant toxic passages as maximum-scoring segments of token log-odds.

A token is a word or the beginning of one. Its score is the log-odds ratio of the labelled texts that use it, toxic against other, under an informative
Dirichlet prior (the pooled counts). A word takes the score of that of its tokens that stands out most; one none of whose tokens is ``LEAST_Z`` standard errors and ``LEAST_ODDS`` from even gets the drift, a small negative score, so that random text has negative
expectation. One linear scan finds all maximal scoring segments. Under that model the best score of n tokens follows an extreme-value law: E =
K n exp(-lambda S) chance segments reach score S; lambda solves E[exp(lambda X)] = 1 over the other class, K is fitted on it. A text's evidence is the sum of -log E over its
significant segments, or -log E of the best, turned into a probability by logistic calibration; beyond ``STRONG`` the logit grows with the logarithm of the evidence, so that strong texts
stay apart."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.llm.tokens import blocks
from entitygraph.llm.words import SIGNS, fold, labelled_sample, word_codes
from entitygraph.shared import materialise

#: Labelled rows that scores and calibration are fitted on, at most; they bound the tokens with a score of their own and all that reaches the driver.
TRAIN_ROWS = 16_000
LEAST_Z, LEAST_ODDS, DRIFT, PRIOR, SIGNIFICANT = 3.0, 1.5, -0.1, 20.0, 0.05
#: The logit up to which probabilities are the calibration's own.
STRONG = 4.0
#: Lengths of the word beginnings that are tokens too.
BEGINNINGS = (5, 6, 7)


def clean(word: str) -> str:
    return word.lower().strip(SIGNS)


def tokens_of(word: str) -> list[str]:
    word = clean(word)
    return [word, *(f"{word[:k]}*" for k in BEGINNINGS if len(word) > k)]


def segments(scores: list[float]) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (start, end, score) of a sequence, in linear time (Ruzzo and Tompa, 1999)."""
    found: list[list[float]] = []  # start, end, sum before it, sum up to its end
    back: list[int] = []  # for each candidate, the nearest one to the left with a lower sum before it
    total = 0.0
    for i, s in enumerate(scores):
        before, total = total, total + s
        if s <= 0:
            continue
        k = [i, i + 1, before, total]
        while True:
            j = len(found) - 1
            while j >= 0 and found[j][2] >= k[2]:
                j = back[j]
            if j < 0 or found[j][3] >= k[3]:
                found.append(k)
                back.append(j)
                break
            k = [found[j][0], k[1], found[j][2], k[3]]
            del found[j:], back[j:]
    return [(int(a), int(b), r - left) for a, b, left, r in found]


class ToxicityModel:
    """table: (score, standard errors) of tokens."""

    def __init__(self, table: dict[str, tuple[float, float]], rate: float = 1.0, scale: float = 1.0, slope: float = 0.0, base: float = 0.0):
        self.table, self.rate, self.scale, self.slope, self.base = table, rate, scale, slope, base

    def value(self, word: str) -> float:
        known = [self.table[t] for t in tokens_of(word) if t in self.table]
        return max(known, key=lambda x: abs(x[1]))[0] if known else DRIFT

    def passages(self, texts: pa.Array) -> list[tuple[int, list[tuple[int, int, float]]]]:
        """Of each text, its number of tokens and its maximal segments (first token, end, score)."""
        offsets, codes, words = word_codes(texts)
        own = np.fromiter(map(self.value, words), float, len(words)) if words else np.empty(0)
        score = own[codes] if len(codes) else np.empty(0)
        special = np.flatnonzero(score != DRIFT)
        first = np.searchsorted(special, offsets)
        out = []
        for i, (a, b) in enumerate(zip(offsets[:-1], offsets[1:], strict=True)):
            at = special[first[i] : first[i + 1]]
            if not len(at):
                out.append((int(b - a), []))
                continue
            # stretches of drift between the special tokens are one step each
            steps = np.empty(2 * len(at))
            steps[0::2] = DRIFT * np.diff(np.append(a - 1, at)) - DRIFT
            steps[1::2] = score[at]
            spans = [(int(at[s // 2] - a), int(at[(e - 1) // 2] - a) + 1, v) for s, e, v in segments(steps.tolist())]
            out.append((int(b - a), spans))
        return out

    def expected(self, score: float, n: int) -> float:
        """Segments of at least that score by chance among n tokens."""
        return self.scale * max(n, 1) * float(np.exp(-min(self.rate * score, 700.0)))

    def significant(self, n: int, spans: list[tuple[int, int, float]]) -> list[tuple[int, int, float]]:
        return [s for s in spans if self.expected(s[2], n) < SIGNIFICANT]

    def evidence(self, n: int, spans: list[tuple[int, int, float]]) -> float:
        if not spans:
            return 0.0
        logs = [-np.log(self.expected(s[2], n)) for s in spans]
        strong = [x for x in logs if x > -np.log(SIGNIFICANT)]
        return float(sum(strong) if strong else max(logs))

    def probability(self, evidence: np.ndarray) -> np.ndarray:
        if self.base == -np.inf:  # no labels
            return np.zeros(len(evidence))
        logit = self.slope * evidence + self.base
        logit = np.where(np.abs(logit) > STRONG, np.copysign(STRONG + np.log1p(np.maximum(np.abs(logit) - STRONG, 0)), logit), logit)
        return 1 / (1 + np.exp(-logit))


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for block in blocks(batch, 0):
            offsets, codes, words = word_codes(block.column(0))
            if not len(codes):
                continue
            toxic = block.column(1).to_numpy() > 0
            doc = np.repeat(np.arange(len(toxic)), np.diff(offsets))
            lists = list(map(tokens_of, words))
            names: dict[str, int] = {}
            flat = np.array([names.setdefault(t, len(names)) for x in lists for t in x])
            size = np.fromiter(map(len, lists), np.int64, len(lists))
            start = np.append(0, np.cumsum(size)[:-1])
            pairs = np.unique(doc * len(words) + codes)
            doc, codes = np.divmod(pairs, len(words))
            n = size[codes]
            which = flat[np.repeat(start[codes] - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())]
            doc, which = np.divmod(np.unique(np.repeat(doc, n) * len(names) + which), len(names))
            all_of, bad = np.bincount(which, minlength=len(names)), np.bincount(which, toxic[doc], len(names)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(list(names)), pa.array(bad), pa.array(all_of - bad)], ["token", "bad", "good"])


def token_scores(sample: DataFrame) -> dict[str, tuple[float, float]]:
    """Log-odds and standard errors of the tokens that stand out, either way, over the texts that hold them; only these reach the driver."""
    bad, good = (x or 0 for x in sample.agg(F.sum((F.col("y") > 0).cast("int")), F.sum((F.col("y") <= 0).cast("int"))).first())
    if not bad or not good:
        return {}
    counts = (
        sample.mapInArrow(_counted, "token string, bad long, good long").groupBy("token").agg(F.sum("bad").alias("bad"), F.sum("good").alias("good"))
    )
    share = F.lit(PRIOR) * (F.col("bad") + F.col("good")) / F.lit(bad + good)
    logit = lambda c, n: F.log((F.col(c) + share) / (F.lit(n + PRIOR) - F.col(c) - share))
    error = F.sqrt(1 / (F.col("bad") + share) + 1 / (F.col("good") + share))
    odds = (logit("bad", bad) - logit("good", good)).alias("odds")
    scored = counts.where("token != ''").select("token", odds, error.alias("error")).select("token", "odds", (F.col("odds") / F.col("error")).alias("z"))
    best = scored.where((F.abs("z") >= LEAST_Z) & (F.abs("odds") >= LEAST_ODDS))
    return {r["token"]: (float(r["odds"]), float(r["z"])) for r in best.collect()}


def _logistic(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and base by Newton's method with a weak prior."""
    a = np.column_stack([x, np.ones(len(x))])
    w = np.array([0.0, np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + 1e-3 * np.eye(2), a.T @ (y - p) - 1e-3 * w)
        w = w + np.clip(step, -2, 2)
    return float(w[0]), float(w[1])


def fit_toxicity(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS, divisor: int = 4, left_out: int = 2, label: str = "toxic") -> ToxicityModel:
    """Fits on a bounded sample of labelled rows. Where no token stands out or one class is missing, nothing is a passage and every score is the smoothed share
    of the toxic, or 0 without any labels."""
    sample = materialise(labelled_sample(docs, labels, label, divisor, left_out, most), "sample")
    model = ToxicityModel(token_scores(sample))

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row (y, n, best, none, 1) for each text, and rows (none, n, none, score, times) for the scores of the tokens of texts of the other class."""
        for batch in batches:
            for block in blocks(batch, 0):
                n, spans = zip(*model.passages(block.column(0)), strict=True)
                y = block.column(1).to_numpy()
                best = [max((s[2] for s in x), default=0.0) for x in spans]
                _, codes, words = word_codes(block.column(0).filter(pa.array(y <= 0)))
                own = np.fromiter(map(model.value, words), float, len(words)) if words else np.empty(0)
                values, times = np.unique(np.round(own[codes], 3) if len(codes) else own, return_counts=True)
                k, m = len(n), len(values)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([*y.tolist(), *[None] * m], pa.int32()), pa.array([*n, *[0] * m], pa.int64()), pa.array([*best, *[None] * m], pa.float64()),
                     pa.array([*[None] * k, *values.tolist()], pa.float64()), pa.array([*[1] * k, *times.tolist()], pa.int64())],
                    ["y", "n", "best", "value", "times"],
                )

    rows = []
    if model.table:  # at most a row for each labelled text and for each scored token
        found = sample.mapInArrow(measured, "y int, n long, best double, value double, times long")
        rows = found.groupBy("y", "n", "best", "value").agg(F.sum("times").alias("times")).collect()
    others = [r for r in rows if r["y"] is not None and r["y"] <= 0]
    if not others or not any(r["y"] is not None and r["y"] > 0 for r in rows):
        bad, n = sample.agg(F.sum((F.col("y") > 0).cast("int")), F.count("*")).first()
        model.table, model.base = {}, float(np.log((bad + 1) / (n - bad + 1))) if n else -np.inf
        return model
    seen = [r for r in rows if r["value"] is not None]
    values, times = np.array([r["value"] for r in seen], float), np.array([r["times"] for r in seen], float)
    low, high = 1e-3, 5.0
    mass = lambda t: (np.exp(t * values) * times).sum() - times.sum()
    for _ in range(60):  # the positive root: the mean is negative, so the mass is under its value at 0 before it
        middle = (low + high) / 2
        low, high = (middle, high) if mass(middle) < 0 else (low, middle)
    model.rate = max(low, 0.05)
    best = np.repeat([r["best"] for r in others], [r["times"] for r in others])
    n = np.maximum(np.repeat([r["n"] for r in others], [r["times"] for r in others]), 1)
    middle = np.median(best)  # half of the other texts have no better segment: 1 - exp(-E) = 1/2 at the median
    model.scale = float(np.clip(np.log(2) / np.median(n) * np.exp(min(model.rate * middle, 50)), 1e-6, 1.0))

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch, 0):
                evidence = [model.evidence(*x) for x in model.passages(block.column(0))]
                yield pa.RecordBatch.from_arrays([block.column(1), pa.array(evidence, pa.float64())], ["y", "evidence"])

    pairs = sample.mapInArrow(judged, "y int, evidence double").collect()  # two numbers for each labelled text
    model.slope, model.base = _logistic(np.array([r["evidence"] for r in pairs]), np.array([r["y"] > 0 for r in pairs], float))
    return model


def toxicity_scores(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """(doc_id, score, leaning, passages): the whole text of every row; leaning is whether any segment of it leans to the toxic, passages are the significant ones
    (first word, end, score).

    Null and empty texts have no segment; equal texts have equal scores; rows that repeat an id or have none are scored each; an empty table gives no rows; other columns are ignored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
        for batch in batches:
            for block in blocks(batch, 1):
                found = model.passages(block.column(1))
                score = model.probability(np.array([model.evidence(*x) for x in found]))
                spans = [[{"start": a, "end": b, "score": v} for a, b, v in model.significant(*x)] for x in found]
                yield pa.RecordBatch.from_arrays([block.column(0), pa.array(score), pa.array([bool(x[1]) for x in found], pa.bool_()), pa.array(spans, kind)], ["doc_id", "score", "leaning", "passages"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(
        run, "doc_id long, score double, leaning boolean, passages array<struct<start:long,end:long,score:double>>"
    )


def rejected(threshold: float = 0.3):
    """Scores at the threshold or above; a text without a segment that leans to the toxic stays, however large the share of the toxic."""
    return F.col("leaning") & (F.col("score") >= threshold)


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """The documents that are not rejected, with all their columns.

    Null and empty texts have no passage and stay; so do rows without an id, which no label or score can name; of rows that repeat an id all go where one is rejected; equal texts
    have equal scores; whole texts are read; without labels of both classes every row stays; an empty table gives no rows."""
    bad = toxicity_scores(docs, fit_toxicity(docs, labels)).where(rejected(threshold)).select(F.col("doc_id").alias("_bad")).distinct()
    return docs.join(bad, docs["doc_id"] == bad["_bad"], "left_anti")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    scored = toxicity_scores(docs, fit_toxicity(docs, labels))
    return scored.select("doc_id", (fold(4) == 2).alias("held_out"), "score", rejected().cast("int").alias("predicted"))
