"""Embedding near-dedup: an exact metric range join of unit vectors within each label.

Cosine c and the chord d of unit vectors obey d * d = 2 - 2c, so cosine >= c is a range of radius r = sqrt(2 - 2c) in a metric space. Each label's own pivots cut
it into cells of nearest vectors; how many is chosen on a sample of the label, by the copies and comparisons that they would make. A vector v whose nearest pivot is h can reach a vector of cell c only if it is within r of the bisector of h and c;
the triangle inequality gives d(v, c) - d(v, h) <= 2r for that, and on the sphere the sharper (v.h - v.c) / |h - c| <= r. It is copied to
those cells, and each cell is joined on its own, in blocks of bounded size: a home vector meets all that can be within its reach in its own cell.
Equal vectors of a label are one class and never paired. Only a spanning forest of a block's links leaves it."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entitygraph.operators.closure import connected_components
from entitygraph.shared import materialise

#: Pivots of a label, at most; vectors of a label that the choice is made on, about; bytes of pivots that go to every worker (the largest labels', the others are one cell each).
PIVOTS, SAMPLE, PIVOT_BYTES = 64, 256, 8_000_000
#: What a copy of a vector costs, in comparisons.
COPY = 300
HOMES, OTHERS = 2048, 8192


def usable(label, vector):
    """Whether a vector can link at all: a label, and finite components that are not all zero."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce(label.isNotNull() & vector.isNotNull() & ~bad & F.exists(vector, lambda x: x != 0), F.lit(False))


def unit(rows: np.ndarray) -> np.ndarray:
    """Rows of length one; they are scaled first so that squares neither overflow nor vanish."""
    rows = rows / np.abs(rows).max(axis=1, keepdims=True)
    return rows / np.linalg.norm(rows, axis=1, keepdims=True)


def _reach(units: np.ndarray, pivots: np.ndarray, radius: float) -> tuple[np.ndarray, np.ndarray]:
    """Each vector's own cell, and the cells that it can reach."""
    dots = units @ pivots.T
    home = dots.argmax(axis=1)
    gaps = np.linalg.norm(pivots[:, None] - pivots[None], axis=2)
    reach = dots[np.arange(len(units)), home][:, None] - dots <= (radius + 1e-9) * gaps[home]
    reach[np.arange(len(units)), home] = True
    return home, reach


def _choose(radius: float, most: int):
    """Of a label's sample (rows of label, crowd, vector): the number of pivots with the least cost, by the copies that they make and the comparisons that they leave."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        sizes = rows.vector.map(len)
        same = np.array(rows.vector[sizes == sizes.mode()[0]].tolist(), float)
        units = unit(same)
        apart = np.unique(units.round(9), axis=0, return_index=True)[1]
        units = units[np.sort(apart)]
        crowd, best = int(rows.crowd.iloc[0]), (np.inf, 1)
        count = 2
        while count <= min(most, len(units)):
            home, reach = _reach(units, units[:count], radius)
            work = (np.bincount(home, minlength=count) * reach.sum(axis=0)).sum() / len(units) ** 2
            best = min(best, (reach.sum() / len(units) * COPY + work * crowd, count))
            count *= 2
        kept = units[: best[1]] if best[1] > 1 else units[:0]
        return pd.DataFrame({"label": [rows.label.iloc[0]] * len(kept), "crowd": crowd, "number": range(len(kept)), "pivot": [x.tobytes() for x in kept]})

    return run


def pivots_of(sized: DataFrame, radius: float, most: int = PIVOTS) -> dict[object, np.ndarray]:
    """Pivots by label, from a sample by hash of about SAMPLE classes a label. sized: label, rep, vector, crowd."""
    draw = F.pmod(F.xxhash64("rep"), F.lit(1 << 30)) / float(1 << 30) * F.col("crowd") < SAMPLE
    sample = sized.where(draw).select("label", "crowd", F.transform("vector", lambda x: x.cast("double")).alias("vector"), F.xxhash64("rep", F.lit(1)).alias("draw"))
    kind = sized.schema["label"].dataType.simpleString()
    found = sample.groupBy("label").applyInPandas(lambda rows: _choose(radius, most)(rows.sort_values("draw")), f"label {kind}, crowd long, number int, pivot binary")
    rows, left, out = found.orderBy(F.desc("crowd"), "label", "number").limit(PIVOT_BYTES // 8).toLocalIterator(), PIVOT_BYTES, {}
    for r in rows:
        left -= len(r["pivot"])
        if left < 0:
            out.pop(r["label"], None)  # not all of its own
            break
        out.setdefault(r["label"], []).append(np.frombuffer(r["pivot"], float))
    return {k: np.array(v) for k, v in out.items()}


def _cells(pivots: dict[object, np.ndarray], radius: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(3)
            flat = lists.flatten().to_numpy(zero_copy_only=False).astype(float)
            borders = lists.offsets.to_numpy().astype(np.int64)
            borders = borders - borders[0]
            sizes = np.diff(borders)
            coded = batch.column(0).dictionary_encode()
            code = coded.indices.to_numpy()
            rows, cells, homes = [], [], []
            for k, label in enumerate(coded.dictionary.to_pylist()):
                mine = np.flatnonzero(code == k)
                own = pivots.get(label)
                split = mine[sizes[mine] == own.shape[1]] if own is not None else mine[:0]
                single = np.setdiff1d(mine, split)
                rows.append(single)
                cells.append(np.full(len(single), -1))
                homes.append(np.ones(len(single), bool))
                for at in range(0, len(split), 4096):
                    index = split[at : at + 4096]
                    home, reach = _reach(unit(flat[borders[index][:, None] + np.arange(own.shape[1])]), own, radius)
                    r, c = np.nonzero(reach)
                    rows.append(index[r])
                    cells.append(c)
                    homes.append(c == home[r])
            row, cell, is_home = np.concatenate(rows), np.concatenate(cells), np.concatenate(homes)
            take = pa.array(row)
            data = pa.Array.from_buffers(pa.large_binary(), len(sizes), [None, pa.py_buffer(borders * 8), pa.py_buffer(np.ascontiguousarray(flat))])
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(take), batch.column(1).take(take), batch.column(2).take(take), pa.array(sizes[row].astype(np.int32)),
                 pa.array(cell.astype(np.int32)), pa.array(is_home), data.take(take).cast(pa.binary())],
                ["label", "rep", "copies", "size", "cell", "home", "vector"],
            )

    return run


def _join_block(threshold: float):
    def run(rows: pa.Table) -> pa.Table:
        rows = rows.combine_chunks()
        column = lambda name: rows.column(name).to_numpy()
        data = np.frombuffer(b"".join(rows.column("vector").to_pylist()), float).reshape(rows.num_rows, -1)
        own = unit(data)
        left, right = np.flatnonzero(column("left")), np.flatnonzero(column("right"))
        rep = column("rep")
        ra, rb, ua, ub, copies = rep[left], rep[right], own[left], own[right], column("copies")[right]
        links, label = np.zeros(len(ra), np.int64), rb.copy()  # label: the least class known to be joined with a class of the right side
        out: list[tuple[int, int]] = []
        for at in range(0, len(ra), 256):
            dots = ua[at : at + 256] @ ub.T
            for i, j in np.argwhere(np.abs(dots - threshold) < 1e-9):  # to the last bit
                x, y = (z / np.abs(z).max() for z in (data[left[at + i]], data[right[j]]))
                dots[i, j] = (x @ y) / (np.linalg.norm(x) * np.linalg.norm(y))
            near = (dots >= threshold) & (ra[at : at + 256, None] != rb[None])
            links[at : at + 256] = near @ copies
            for i in np.flatnonzero(near.any(axis=1)):
                seen = np.unique(label[near[i]])
                if len(seen) > 1:
                    label[np.isin(label, seen)] = seen[0]
                out.append((int(ra[at + i]), int(seen[0])))
        merged, some = np.flatnonzero(label != rb), np.array(out, np.int64).reshape(-1, 2)
        k = links > 0
        return pa.table({
            "rep": np.concatenate([ra[k], some[:, 0], rb[merged]]), "links": np.concatenate([links[k], np.zeros(len(some) + len(merged), np.int64)]),
            "other": np.concatenate([np.full(k.sum(), -1), some[:, 1], label[merged]]),
        })

    return run


def embedding_near_dedup(vectors: DataFrame, threshold: float = 0.98, most_pivots: int = PIVOTS, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label") -> DataFrame:
    """vec_id, n_links (other vectors of the label with cosine >= threshold), component_id (least vec_id reachable), kept.

    Vectors that are null, zero, or hold null or non-finite components, and those without a label, link with nothing; vectors
    of other sizes are never compared; equal vectors of a label link, cosines at the threshold are compared to the last bit; an empty table gives no rows; other columns are ignored, whatever their names; ids are distinct and not negative."""
    radius = float(np.sqrt(2 - 2 * threshold))
    own = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(label_col).alias("label"), F.col(vector_col).alias("vector"))
    good = own.where(usable(F.col("label"), F.col("vector")))
    classes = materialise(good.groupBy("label", "vector").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies")), "classes")
    crowd = classes.groupBy("label").agg(F.count("*").alias("crowd"))
    sized = classes.join(crowd, "label").select("label", "rep", "copies", "vector", "crowd")
    kind = classes.schema["label"].dataType.simpleString()
    pivots = pivots_of(sized, radius, most_pivots)
    placed = materialise(sized.select("label", "rep", "copies", "vector").mapInArrow(_cells(pivots, radius), f"label {kind}, rep long, copies long, size int, cell int, home boolean, vector binary"), "cells")
    cell = ["label", "size", "cell"]
    counts = placed.groupBy(cell).agg(
        F.greatest(F.lit(1), F.ceil(F.sum(F.col("home").cast("int")) / HOMES)).cast("int").alias("nh"), F.greatest(F.lit(1), F.ceil(F.count("*") / OTHERS)).cast("int").alias("no"),
        F.sum(F.col("home").cast("int")).alias("at_home"), F.count("*").alias("all"),
    ).where("at_home > 0 and all > 1").drop("at_home", "all")
    dealt = placed.join(counts, cell).withColumn("hi", F.expr("cast(pmod(xxhash64(rep), nh) as int)")).withColumn("oj", F.expr("cast(pmod(xxhash64(rep), no) as int)"))
    spot = lambda i, j, left, right: F.struct(i.alias("i"), j.alias("j"), left.alias("left"), right.alias("right"))
    as_home = F.transform(F.sequence(F.lit(0), F.col("no") - 1), lambda j: spot(F.col("hi"), j, F.lit(True), j == F.col("oj")))
    as_other = F.transform(F.filter(F.sequence(F.lit(0), F.col("nh") - 1), lambda i: ~F.col("home") | (i != F.col("hi"))), lambda i: spot(i, F.col("oj"), F.lit(False), F.lit(True)))
    blocks = dealt.withColumn("at", F.explode(F.when(F.col("home"), F.concat(as_home, as_other)).otherwise(as_other))).select(*cell, "at.*", "rep", "copies", "vector")
    found = materialise(blocks.groupBy(*cell, "i", "j").applyInArrow(_join_block(threshold), "rep long, links long, other long"), "links")
    links = found.groupBy("rep").agg(F.sum("links").alias("links"))
    groups = connected_components(found.where("other >= 0").select(F.col("rep").alias("a"), F.col("other").alias("b")))
    about = (
        classes.join(links, "rep", "left")
        .join(groups.select(F.col("record_id").alias("rep"), "component_id"), "rep", "left")
        .select("label", "vector", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
    )
    member = good.join(about, ["label", "vector"]).select("vec_id", "n_links", "component_id")
    lone = own.where(~usable(F.col("label"), F.col("vector"))).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return member.union(lone).withColumn("kept", F.col("vec_id") == F.col("component_id"))


def op10_vector_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_near_dedup(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))
