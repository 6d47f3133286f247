"""Frequency blocking and its alternatives."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entitygraph.errors import LocalCapExceeded
from entitygraph.operators.closure import connected_components
from entitygraph.shared import materialise

#: Stop tokens that are broadcast, at most.
HEAVY = 100_000
#: Parts of a bucket of records with a common hash, at most, and pairs that are listed together.
PARTS, PAIRS = 16, 1 << 17


def cut_stop_tokens(tokens: DataFrame, freqs: DataFrame, sigma: int = 7, bounds: str = "inclusive", freq: str = "c") -> DataFrame:
    """record_id, pos, token, c of the tokens that are not too frequent.

    The ``HEAVY`` most frequent of the others, a bounded list, are filtered out where the tokens are read, so that no common token's occurrences meet in one task of the join."""
    limit = F.col(freq) < sigma if bounds == "inclusive" else F.col(freq) <= sigma
    heavy = freqs.where(~limit).orderBy(F.desc(freq), "token").limit(HEAVY).select("token")
    return tokens.join(F.broadcast(heavy), "token", "left_anti").join(freqs.where(limit).select("token", F.col(freq).alias("c")), "token").select("record_id", "pos", "token", "c")


def blocking_tokens(kept: DataFrame, beta: int = 6, bounds: str = "inclusive") -> DataFrame:
    """token, record_id, once each, of tokens rare enough to block on."""
    return kept.where(F.col("c") <= beta if bounds == "inclusive" else F.col("c") < beta).select("token", "record_id").distinct()


def filtered_records(kept: DataFrame) -> DataFrame:
    """record_id and its kept tokens in order of appearance."""
    listed = F.array_sort(F.collect_list(F.struct("pos", "token")))
    return kept.groupBy("record_id").agg(F.transform(listed, lambda x: x["token"]).alias("tokens"))


def blocks(blocking: DataFrame) -> DataFrame:
    """token, members (sorted) and size of blocks with two records at least; a block has at most beta members."""
    grouped = blocking.groupBy("token").agg(F.array_sort(F.collect_list("record_id")).alias("members"))
    return grouped.withColumn("size", F.size("members")).where("size > 1")


def candidate_pairs(blocked: DataFrame) -> DataFrame:
    """a < b, once each, with the number of blocks that they share."""
    pairs = F.flatten(
        F.transform("members", lambda x, i: F.transform(F.slice(F.col("members"), i + 2, F.size("members")), lambda y: F.struct(x.alias("a"), y.alias("b"))))
    )
    return blocked.select(F.explode(pairs).alias("p")).groupBy("p.a", "p.b").agg(F.count("*").alias("shared"))


def block_records(tokens: DataFrame, freqs: DataFrame, beta: int = 6, sigma: int = 7, bounds: str = "inclusive") -> tuple[DataFrame, DataFrame]:
    """(candidate pairs, filtered records)."""
    kept = cut_stop_tokens(tokens, freqs, sigma, bounds)
    return candidate_pairs(blocks(blocking_tokens(kept, beta, bounds))), filtered_records(kept)


def blocking_report(blocked: DataFrame, pairs: DataFrame, n_records: int, truth: DataFrame) -> DataFrame:
    """One row: blocks, largest, comparisons with repeats, distinct pairs, reduction ratio, pair completeness."""
    of = truth.select("record_id", "truth_id")
    left, right = of.select(F.col("record_id").alias("a"), F.col("truth_id").alias("ta")), of.select(F.col("record_id").alias("b"), F.col("truth_id").alias("tb"))
    true_found = pairs.join(left, "a").join(right, "b").where("ta = tb").agg(F.count("*").alias("true_found"))
    all_true = of.groupBy("truth_id").count().agg(F.sum(F.expr("count * (count - 1) / 2")).cast("long").alias("all_true"))
    sizes = blocked.agg(F.count("*").alias("n_blocks"), F.max("size").alias("largest"), F.sum(F.expr("size * (size - 1) / 2")).cast("long").alias("comparisons"))
    total = n_records * (n_records - 1) / 2
    return (
        sizes.crossJoin(pairs.agg(F.count("*").alias("n_pairs"))).crossJoin(true_found).crossJoin(all_true)  # one row each
        .select("n_blocks", "largest", "comparisons", "n_pairs", F.round(1 - F.col("n_pairs") / F.lit(total), 6).alias("reduction_ratio"), F.round(F.col("true_found") / F.col("all_true"), 6).alias("pair_completeness"))
    )


def _hash_keys(tokens: DataFrame, bands: int, rows: int) -> DataFrame:
    """record_id and keys: for each band a hash of its ``rows`` minimum token hashes."""
    hashes = [F.min(F.xxhash64("token", F.lit(i))).alias(f"h{i}") for i in range(bands * rows)]
    keys = F.array(*[F.xxhash64(*[F.col(f"h{b * rows + r}") for r in range(rows)]) for b in range(bands)])
    return tokens.groupBy("record_id").agg(*hashes).select("record_id", keys.alias("keys"))


def _list_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of cells (band, i, j, members as part, record_id, keys in that order): a < b and the number of bands that they share, in the cell of the first such band, ``PAIRS`` at a time."""
    for batch in batches:
        if not batch.num_rows:
            continue
        lists = batch.column("members")
        borders = lists.offsets.to_numpy().astype(np.int64)
        flat, borders = lists.flatten(), borders - borders[0]
        cell = np.repeat(np.arange(len(borders) - 1), np.diff(borders))
        band, i, j = (batch.column(c).to_numpy()[cell] for c in ("band", "i", "j"))
        part, coded = flat.field("part").to_numpy(), flat.field("record_id").dictionary_encode()
        keys = flat.field("keys").flatten().to_numpy().reshape(len(part), -1).T.copy()
        order = pc.sort_indices(coded.dictionary)
        names, rank = coded.dictionary.take(order).cast(pa.string()), np.empty(len(order), np.int64)
        rank[order.to_numpy()] = np.arange(len(order))
        code = rank[coded.indices.to_numpy()]
        # a member meets those after it, or where the cell is of two parts the whole of the second
        at, end = np.arange(len(part)), borders[1:][cell]
        second = np.zeros(len(borders), np.int64)
        np.add.at(second, cell, part == i)
        start = np.where(i == j, at + 1, np.where(part == i, borders[:-1][cell] + second[cell], end))
        todo = np.append(0, np.cumsum(end - start))
        for low in range(0, int(todo[-1]), PAIRS):
            pair = np.arange(low, min(low + PAIRS, int(todo[-1])))
            x = np.searchsorted(todo, pair, "right") - 1
            y = start[x] + pair - todo[x]
            shared, earlier, own = np.zeros(len(x), np.int64), np.zeros(len(x), bool), band[x]
            for b, key in enumerate(keys):
                same = key[x] == key[y]
                shared += same
                earlier |= same & (b < own)
            one, two = code[x[~earlier]], code[y[~earlier]]
            a, b = names.take(pa.array(np.minimum(one, two))), names.take(pa.array(np.maximum(one, two)))
            yield pa.RecordBatch.from_arrays([a, b, pa.array(shared[~earlier])], ["a", "b", "shared"])


def lsh_pairs(tokens: DataFrame, bands: int = 16, rows: int = 3, largest: int = 200) -> DataFrame:
    """Pairs that share a band of minimum token hashes: a < b, once each, with the number of bands that they share. A bucket above ``largest`` is cut into parts of about that size, or into
    ``PARTS`` where that would be more; each two parts meet in a cell of their own, so that all its pairs are made. A pair is listed in the first band that it shares, so that no pairs are gathered again."""
    spark = tokens.sparkSession
    marks = materialise(_hash_keys(tokens, bands, rows), "marks")
    held = marks.select("record_id", "keys", F.posexplode("keys").alias("band", "key"))
    sizes = held.groupBy("band", "key").agg(F.count("*").alias("size")).where("size > 1")
    parts = F.least(F.ceil(F.col("size") / largest), F.lit(PARTS)).cast("int")
    placed = held.join(sizes, ["band", "key"]).withColumn("parts", parts).withColumn("part", F.pmod(F.xxhash64("record_id", F.lit(1)), F.col("parts")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    cell = ["band", "key", "i", "j"]
    placed = placed.select("band", "key", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), F.struct("part", "record_id", "keys").alias("member"))
    # cells are small and their pairs many: as many tasks as the session names, however few the bytes
    placed = placed.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), *cell)
    cells = placed.groupBy(*cell).agg(F.array_sort(F.collect_list("member")).alias("members")).where(F.size("members") > 1)
    return cells.select("band", "i", "j", "members").mapInArrow(_list_pairs, "a string, b string, shared long")


def _count_links(rows: pa.Table) -> pa.Table:
    """Of cells of buckets (band, key, i, j): each record's links to the others of its cell (those of the other part, where a cell is of two parts) that no earlier band has, and the cell's least record."""
    rows = rows.sort_by([(c, "ascending") for c in ("band", "key", "i", "j", "record_id")]).combine_chunks()
    ids, band, i, j, part = (rows.column(c).to_numpy() for c in ("record_id", "band", "i", "j", "part"))
    keys = np.array(rows.column("keys").combine_chunks().flatten()).reshape(len(ids), -1)
    cell = np.stack([band, rows.column("key").to_numpy(), i, j])
    starts = np.flatnonzero(np.append(True, (cell[:, 1:] != cell[:, :-1]).any(axis=0)))
    links, least = np.zeros(len(ids), np.int64), ids.copy()
    for lo, hi in zip(starts, np.append(starts[1:], len(ids)), strict=True):
        own, side = keys[lo:hi, : band[lo]].T.copy(), part[lo:hi]
        least[lo:hi] = ids[lo]
        for at in range(0, hi - lo, 256):
            some = slice(at, at + 256)
            apart = side[some, None] != side[None] if i[lo] != j[lo] else np.ones((len(side[some]), hi - lo), bool)
            for k in own:
                apart &= k[some, None] != k[None]
            if i[lo] == j[lo]:
                np.fill_diagonal(apart[:, at:], False)  # itself
            links[lo + at : lo + at + len(apart)] = apart.sum(axis=1)
    return pa.table({"record_id": pa.array(ids, pa.string()), "n": links, "least": pa.array(least, pa.string())})


def lsh_links(tokens: DataFrame, bands: int = 16, rows: int = 3, largest: int = 2000) -> DataFrame:
    """record_id, n_links (other records that share a band of minimum token hashes), component_id (least record that such links reach, itself included): all links of ``lsh_pairs``, counted where a
    bucket's records meet, in the first band that they share, so that no pair becomes a row. A bucket above ``largest`` is cut into parts; each two meet in a cell of their own."""
    marks = materialise(_hash_keys(tokens, bands, rows), "marks")
    held = marks.select("record_id", "keys", F.posexplode("keys").alias("band", "key"))
    sizes = held.groupBy("band", "key").agg(F.count("*").alias("size")).where("size > 1")
    parts = F.ceil(F.col("size") / largest).cast("int")
    placed = held.join(sizes, ["band", "key"]).withColumn("parts", parts).withColumn("part", F.pmod(F.xxhash64("record_id", F.lit(1)), F.col("parts")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    placed = placed.withColumn("i", F.least("part", "other")).withColumn("j", F.greatest("part", "other"))
    # small buckets travel together
    group = F.when(F.col("size") > largest // 4, F.xxhash64("band", "key", "i", "j")).otherwise(F.pmod(F.xxhash64("band", "key"), F.lit(512)))
    met = placed.select(group.alias("group"), "record_id", "keys", "band", "key", "i", "j", "part").groupBy("group")
    counted = materialise(met.applyInArrow(_count_links, "record_id string, n long, least string"), "counted")
    reached = connected_components(counted.select(F.col("least").alias("a"), F.col("record_id").alias("b")))
    links = counted.groupBy("record_id").agg(F.sum("n").alias("n_links"))
    every = marks.select("record_id").join(links, "record_id", "left").join(reached, "record_id", "left")
    return every.select("record_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "record_id").alias("component_id"))


def random_blocks(records: DataFrame, n_blocks: int, seed: int = 0) -> DataFrame:
    """Blocks by a hash of seed and id."""
    number = F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.col("record_id"))), 1, 8), 16, 10).cast("long") % n_blocks
    grouped = records.groupBy(number.alias("token")).agg(F.array_sort(F.collect_list("record_id")).alias("members"))
    return grouped.withColumn("size", F.size("members")).where("size > 1")


def all_pairs(records: DataFrame, max_records: int = 2000) -> DataFrame:
    """Every pair, for reference; refuses more than ``max_records`` records."""
    n = records.count()
    if n > max_records:
        raise LocalCapExceeded(f"{n} records, at most {max_records} for all pairs")
    one = records.select("record_id")
    return one.select(F.col("record_id").alias("a")).join(one.select(F.col("record_id").alias("b")), F.col("a") < F.col("b"))


def union_pairs(*pairs: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, [p.select("a", "b") for p in pairs]).distinct()
