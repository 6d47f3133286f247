"""Modularity refinement of soft clusters: a kernel for small components, the same search over arrays for large ones that fit a task, and a distributed form for those that don't."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import count

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entitygraph.operators.modularity import contract, move_gain
from entitygraph.shared import discard, materialise


#: Edges that one call of the kernel gets, about.
GROUP_EDGES = 40_000
#: Edges of a component that the search over arrays takes, at most: some 300 bytes an edge.
ARRAY_EDGES = 2_000_000
#: Links, and pairs of a node and a community, that the search over arrays looks at together, about.
STRETCH = 1 << 18


@dataclass(frozen=True)
class RefineConfig:
    """move: 'best' takes the community with the largest gain, 'first_gain' the first neighbour (by weight) with a positive one. passes: 'one' a level, or
    'until_stable'. A component of more than ``local_edge_cap`` edges is refined over arrays where it fits a task, else (or by another move than the best) by the distributed form,
    which stops when neither parity gains, or sooner at ``max_levels`` and ``max_passes`` where they are given; those are of the distributed form alone."""

    move: str = "best"
    passes: str = "until_stable"
    weighted: bool = True
    resolution: float = 1.0
    seed: int = 0
    local_edge_cap: int = 500_000
    max_levels: int | None = None
    max_passes: int | None = None


def _order(seed: int, node: str) -> tuple[str, str]:
    return hashlib.md5(f"{seed}:{node}".encode()).hexdigest(), node


def louvain(edges: list[tuple[str, str, float]], cfg: RefineConfig = RefineConfig(), whole: float | None = None) -> list[tuple[dict[str, str], float]]:
    """Levels of (node to community, modularity), from the single nodes on; communities are named by their least node. Deterministic:
    nodes are visited in the order of a seeded hash, and ties go to the least community. ``whole``: the weight of a graph that these edges are a component of."""
    adjacent: dict[str, dict[str, float]] = {}
    loops: dict[str, float] = {}
    total = 0.0
    for u, v, w in sorted(edges):
        w = float(w) if cfg.weighted else 1.0
        total += w
        for x in (u, v):
            adjacent.setdefault(x, {})
        if u == v:
            loops[u] = loops.get(u, 0.0) + w
        else:
            adjacent[u][v] = adjacent[u].get(v, 0.0) + w
            adjacent[v][u] = adjacent[v].get(u, 0.0) + w
    member = {x: x for x in adjacent}
    if total <= 0:
        return [(member, 0.0)]
    total = total if whole is None else whole

    def quality(adj, loop, community) -> float:
        inside, degree = {}, {}
        for x, near in adj.items():
            c = community[x]
            degree[c] = degree.get(c, 0.0) + sum(near.values()) + 2 * loop.get(x, 0.0)
            inside[c] = inside.get(c, 0.0) + loop.get(x, 0.0) + sum(w for y, w in near.items() if community[y] == c) / 2
        return sum(inside[c] / total - cfg.resolution * (degree[c] / (2 * total)) ** 2 for c in degree)

    levels = [(dict(member), quality(adjacent, loops, {x: x for x in adjacent}))]
    while True:
        community = {x: x for x in adjacent}
        k = {x: sum(near.values()) + 2 * loops.get(x, 0.0) for x, near in adjacent.items()}
        degree = dict(k)
        order = sorted(adjacent, key=lambda x: _order(cfg.seed, x))
        moved = True
        while moved:
            moved = False
            for x in order:
                links: dict[str, float] = {}
                for y, w in adjacent[x].items():
                    links[community[y]] = links.get(community[y], 0.0) + w
                own = community[x]
                degree[own] -= k[x]
                gain = lambda c: move_gain(k[x], links.get(c, 0.0), degree[c], links.get(own, 0.0), degree[own], total, cfg.resolution)  # noqa: B023, E731
                if cfg.move == "first_gain":
                    near = sorted(adjacent[x].items(), key=lambda t: (-t[1], t[0]))
                    best = next((community[y] for y, _ in near if community[y] != own and gain(community[y]) > 1e-12), own)
                else:
                    top = max(((gain(c), c) for c in links if c != own), key=lambda t: (round(t[0], 12), _Reverse(t[1])), default=(0.0, own))
                    best = top[1] if top[0] > 1e-12 else own
                degree[best] += k[x]
                if best != own:
                    community[x] = best
                    moved = True
            if cfg.passes == "one":
                break
        least: dict[str, str] = {}
        for x, c in community.items():
            least[c] = min(least.get(c, x), x)
        community = {x: least[c] for x, c in community.items()}
        m = quality(adjacent, loops, community)
        if m <= levels[-1][1] + 1e-9:
            return levels
        member = {x: community[c] for x, c in member.items()}
        levels.append((dict(member), m))
        new: dict[str, dict[str, float]] = {c: {} for c in community.values()}
        new_loops: dict[str, float] = {}
        for x, w in loops.items():
            new_loops[community[x]] = new_loops.get(community[x], 0.0) + w
        for x, near in adjacent.items():
            for y, w in near.items():
                a, b = community[x], community[y]
                if a == b:
                    new_loops[a] = new_loops.get(a, 0.0) + w / 2
                else:
                    new[a][b] = new[a].get(b, 0.0) + w
        adjacent, loops = new, new_loops


class _Reverse:
    """Orders names the other way round."""

    def __init__(self, name: str):
        self.name = name

    def __lt__(self, other) -> bool:
        return self.name > other.name

    def __eq__(self, other) -> bool:
        return self.name == other.name


def refine_local(edges: DataFrame, cfg: RefineConfig = RefineConfig(), all_levels: bool = False, n_edges: int | None = None, whole: float | None = None) -> DataFrame:
    """component_id, record_id, community, level, m of components that fit a task; small ones travel together, about ``GROUP_EDGES`` edges a call,
    so that a billion small components don't mean a billion calls and no call grows with the input."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        for component, part in rows.groupby("component_id"):
            levels = louvain(list(zip(part.u, part.v, part.w, strict=True)), cfg, whole)
            for level, (member, m) in list(enumerate(levels))[0 if all_levels else -1 :]:
                out += [(component, x, c, level, m) for x, c in member.items()]
        return pd.DataFrame(out, columns=["component_id", "record_id", "community", "level", "m"])

    sized = edges.groupBy("component_id").agg(F.count("*").alias("n"))
    groups = max(64, -(-(edges.count() if n_edges is None else n_edges) // GROUP_EDGES))
    bucket = F.when(F.col("n") > GROUP_EDGES // 4, F.xxhash64("component_id")).otherwise(F.pmod(F.xxhash64("component_id"), F.lit(groups)))
    dealt = edges.join(sized, "component_id").withColumn("bucket", bucket)
    return dealt.groupBy("bucket").applyInPandas(run, "component_id string, record_id string, community string, level int, m double")


def _still(first: int, at: np.ndarray, links: tuple[np.ndarray, ...], own: np.ndarray, drag: np.ndarray, k: np.ndarray, community: np.ndarray, degree: np.ndarray, slack: float) -> int:
    """How many nodes from the one visited as number ``first`` on gain by no move as things are; one too few where a gain is hardly any. Node i's links are those from at[i] to at[i + 1]: other
    end, weight, number of the visit, and drag (what a community's degree costs the node, as a weight of links); own, drag, k: each node's community, drag and degree."""
    size, n = len(degree), len(own)
    if at[0] == at[-1]:
        return n
    dst, ww, turn, pull = (x[at[0] : at[-1]] for x in links)
    row, to = turn - first, community[dst]
    cell, mine = row * size + to, np.arange(n) * size + own
    weight = np.bincount(cell, ww, n * size)
    stay = weight[mine] - drag * (degree[own] - k) + slack
    weight[mine] = -np.inf
    gains = weight[cell] - pull * degree[to] > stay[row]
    best = gains.argmax()
    return int(row[best]) if gains[best] else n


def louvain_arrays(names: list[str], u: np.ndarray, v: np.ndarray, w: np.ndarray, cfg: RefineConfig = RefineConfig(), whole: float | None = None) -> list[tuple[np.ndarray, float]]:
    """``louvain`` by the best move, with nodes as numbers in the order of their names and links as whole arrays: levels of (each node's community, modularity). The same visits, gains
    and ties; sums of weights that are not whole numbers may differ in their last place. names: ascending."""
    w = w.astype(float) if cfg.weighted else np.ones(len(w))
    total = float(w.sum()) if whole is None or not w.sum() else whole
    n = len(names)
    member = np.arange(n)
    if total <= 0:
        return [(member, 0.0)]
    node = member  # the name's number of each node of this level
    levels: list[tuple[np.ndarray, float]] = []
    while True:
        size, loop = len(node), u == v
        loops = np.bincount(u[loop], w[loop], size)
        src, dst, ww = (np.concatenate(x) for x in ((u[~loop], v[~loop]), (v[~loop], u[~loop]), (w[~loop], w[~loop])))
        visits = np.array(sorted(range(size), key=lambda x: _order(cfg.seed, names[node[x]])), np.int64)  # noqa: B023
        turn = np.empty(size, np.int64)
        turn[visits] = np.arange(size)
        order = np.argsort(turn[src] * size + dst)  # links lie in the order of visits
        src, dst, ww = src[order], dst[order], ww[order]
        at = np.searchsorted(turn[src], np.arange(size + 1))
        k = np.bincount(src, ww, size) + 2 * loops
        drag = cfg.resolution * k / (2 * total)
        reach = dst, ww, turn[src], drag[src]

        def quality(community: np.ndarray) -> float:
            inside = loops.sum() + ww[community[src] == community[dst]].sum() / 2  # noqa: B023
            return float(inside / total - cfg.resolution * ((np.bincount(community, k) / (2 * total)) ** 2).sum())  # noqa: B023

        if not levels:
            levels.append((member, quality(np.arange(size))))
        community, degree, moved = np.arange(size), k.copy(), True
        quiet = 0.0  # visits between two moves, about
        while moved:
            moved = False
            live, community = np.unique(community, return_inverse=True)
            degree = degree[live]
            i, last, ahead = 0, 0, int(quiet)
            while i < size:
                if ahead >= 4:  # a stretch of visits without a move is passed over at once
                    end = max(i + 1, min(i + ahead, size, int(np.searchsorted(at, at[i] + STRETCH, "right")) - 1, i + STRETCH // len(degree)))
                    nodes = visits[i:end]
                    skip = _still(i, at[i : end + 1], reach, community[nodes], drag[nodes], k[nodes], community, degree, 5e-13 * total)
                    i += skip
                    if i == end:
                        ahead *= 2
                        continue
                x, near = visits[i], slice(at[i], at[i + 1])
                i += 1
                if near.start == near.stop:
                    continue
                to = community[dst[near]]
                links = np.bincount(to, ww[near], len(degree))
                own, mine = community[x], k[x]
                k_own, links[own] = links[own], 0.0
                other = np.unique(to) if len(degree) > 8 * len(to) else np.arange(len(degree))
                other = other[links[other] != 0]
                if not len(other):
                    continue
                gain = move_gain(mine, links[other], degree[other], k_own, degree[own] - mine, total, cfg.resolution)
                top = gain.max()
                if top > 1e-12:
                    ties = np.flatnonzero(gain >= top - 2e-12)
                    best = other[ties[0]] if len(ties) == 1 else other[max((round(float(gain[j]), 12), -j) for j in ties)[1] * -1]
                    degree[own] -= mine
                    degree[best] += mine
                    community[x] = best
                    moved = True
                    quiet += (i - last - quiet) / 8
                    last, ahead = i, int(quiet)
                elif i - last > 2 * ahead:
                    ahead = i - last
            if cfg.passes == "one":
                break
        # communities by their least node
        least = np.full(len(degree), size)
        np.minimum.at(least, community, np.arange(size))
        community = least[community]
        m = quality(community)
        if m <= levels[-1][1] + 1e-9:
            return levels
        keep, community = np.unique(community, return_inverse=True)
        inner = np.zeros(n, np.int64)
        inner[node] = node[keep][community]
        member = inner[member]
        levels.append((member, m))
        a, b = community[u], community[v]
        cell, back = np.unique(np.minimum(a, b) * len(keep) + np.maximum(a, b), return_inverse=True)
        u, v = np.divmod(cell, len(keep))
        w, node = np.bincount(back, w), node[keep]


def refine_arrays(edges: DataFrame, cfg: RefineConfig = RefineConfig(), whole: float | None = None) -> DataFrame:
    """component_id, record_id, community, level, m of components of up to ``ARRAY_EDGES`` edges, a task's each."""

    def run(rows: pa.Table) -> pa.Table:
        component, n = rows.column("component_id")[0].as_py(), rows.num_rows
        w = rows.column("w").to_numpy().astype(float)
        ends = pa.chunked_array([*rows.column("u").chunks, *rows.column("v").chunks]).combine_chunks().dictionary_encode()
        ends = ends.combine_chunks() if isinstance(ends, pa.ChunkedArray) else ends
        order = pc.sort_indices(ends.dictionary).to_numpy()
        rank = np.empty(len(order), np.int64)
        rank[order] = np.arange(len(order))
        names = ends.dictionary.take(pa.array(order))
        codes = rank[ends.indices.to_numpy()]
        del rows, ends
        levels = louvain_arrays(names.to_pylist(), codes[:n], codes[n:], w, cfg, whole)
        member, m = levels[-1]
        size = len(names)
        return pa.table({
            "component_id": pa.array([component] * size, pa.string()), "record_id": names.cast(pa.string()), "community": names.take(pa.array(member)).cast(pa.string()),
            "level": pa.array(np.full(size, len(levels) - 1, np.int32)), "m": pa.array(np.full(size, m)),
        })

    return edges.select("component_id", "u", "v", F.col("w").cast("double").alias("w")).groupBy("component_id").applyInArrow(run, "component_id string, record_id string, community string, level int, m double")


def refine_large(edges: DataFrame, sizes: DataFrame, cfg: RefineConfig = RefineConfig(), whole: float | None = None) -> DataFrame:
    """component_id, record_id, community, level, m of large components, those that fit a task over arrays, the others by the distributed form. sizes: component_id, n_edges."""
    fits = F.lit(cfg.move == "best" and cfg.max_levels is None and cfg.max_passes is None) & (F.col("n_edges") <= ARRAY_EDGES)
    out = refine_arrays(edges.join(sizes.where(fits).select("component_id"), "component_id", "left_semi"), cfg, whole)
    beyond = sizes.where(~fits).select("component_id")
    if beyond.limit(1).count():
        out = out.unionByName(refine_distributed(edges.join(beyond, "component_id", "left_semi"), cfg, whole))
    return out


def refine_distributed(edges: DataFrame, cfg: RefineConfig = RefineConfig(), whole: float | None = None) -> DataFrame:
    """The same search with nodes moving in parallel: in each pass the nodes of one hash parity move, of two communities that would swap
    only toward the lesser, and a pass that doesn't raise a component's modularity is taken back. component_id, record_id, community, level, m.

    Nodes carry their degree and their graph's weight, and one table of links from nodes to communities gives both the modularity of a partition and the
    gains of the next moves; nothing of an edge's size is joined by the component alone. Components that a level doesn't improve leave the search.
    Components without weight are left out; an empty table gives no rows."""
    weight = F.col("w").cast("double") if cfg.weighted else F.lit(1.0)
    graph = materialise(edges.select("component_id", "u", "v", weight.alias("w")), "graph")
    total = F.sum("w") if whole is None else F.lit(float(whole))
    totals = materialise(graph.groupBy("component_id").agg(total.alias("total")).where("total > 0"), "totals")
    state, links, score = _single_nodes(graph, totals, cfg)
    names, best, level = state.select("component_id", "record_id", "community"), score, 0
    for _ in count() if cfg.max_levels is None else range(cfg.max_levels):
        state, score = _passes(graph, state, links, score, cfg)
        gained = score.join(best.withColumnRenamed("m", "before"), "component_id").where("m > before + 1e-9").select("component_id", "m")
        gained = materialise(gained, "gained")
        if gained.limit(1).count() == 0:
            break
        level += 1
        least = state.groupBy("component_id", "community").agg(F.min("record_id").alias("least"))
        merged = state.join(gained.select("component_id"), "component_id", "left_semi").join(least, ["component_id", "community"])
        merged = materialise(merged.select("component_id", "record_id", F.col("least").alias("community")), "merged")
        step_of = merged.select("component_id", F.col("record_id").alias("community"), F.col("community").alias("to"))
        names = names.join(step_of, ["component_id", "community"], "left").select("component_id", "record_id", F.coalesce("to", "community").alias("community"))
        names = materialise(names, "names")
        best = materialise(best.join(gained.withColumnRenamed("m", "after"), "component_id", "left").select("component_id", F.coalesce("after", "m").alias("m")), "quality")
        before, graph = graph, materialise(contract(graph, merged), "graph")
        discard(before)
        state, links, score = _single_nodes(graph, totals, cfg)
    return names.join(best, "component_id").select("component_id", "record_id", "community", F.lit(level).alias("level"), "m")


def _single_nodes(graph: DataFrame, totals: DataFrame, cfg: RefineConfig) -> tuple[DataFrame, DataFrame, DataFrame]:
    """State (component_id, record_id, community, k, loop, total), links and modularity of the partition into single nodes."""
    loop = F.when(F.col("u") == F.col("v"), F.col("w")).otherwise(0.0)
    end = lambda x: F.struct(F.col(x).alias("record_id"), (loop / 2).alias("loop"))
    ends = graph.select("component_id", "w", F.explode(F.array(end("u"), end("v"))).alias("e"))
    nodes = ends.groupBy("component_id", F.col("e.record_id").alias("record_id")).agg(F.sum("w").alias("k"), F.sum("e.loop").alias("loop"))
    state = nodes.join(totals, "component_id").select("component_id", "record_id", F.col("record_id").alias("community"), "k", "loop", "total")
    state = materialise(state, "state")
    links = materialise(_links(graph, state), "links")
    return state, links, materialise(_quality(state, links, cfg), "quality")


def _passes(graph: DataFrame, state: DataFrame, links: DataFrame, score: DataFrame, cfg: RefineConfig) -> tuple[DataFrame, DataFrame]:
    """State and modularity after passes over one level, until neither parity gains."""
    first, idle = state, 0
    for step in count() if cfg.max_passes is None else range(cfg.max_passes):
        moved = materialise(_one_pass(state, links, cfg, step), "state")
        moved_links = materialise(_links(graph, moved), "links")
        new = _quality(moved, moved_links, cfg).withColumnRenamed("m", "new")
        better = F.coalesce(F.col("new") > F.col("m") + 1e-9, F.lit(False))
        judged = score.join(new, "component_id", "left").select("component_id", F.when(better, F.col("new")).otherwise(F.col("m")).alias("m"), better.alias("better"))
        judged = materialise(judged, "quality")
        n = judged.agg(F.count("*").alias("all"), F.count_if("better").alias("better")).first()
        idle = 0 if n["better"] else idle + 1
        spent = []
        if n["better"] == n["all"] > 0:
            spent, state, links = [state, links], moved, moved_links
        elif n["better"] == 0:
            spent = [moved, moved_links]
        else:
            up = judged.where("better").select("component_id")
            pick = lambda new, old: materialise(new.join(up, "component_id", "left_semi").unionByName(old.join(up, "component_id", "left_anti")), "state")  # noqa: B023, E731
            spent = [state, links, moved, moved_links]
            state, links = pick(moved, state), pick(moved_links, links)
        score = judged.select("component_id", "m")
        for df in spent:
            if df is not first:  # the level's names are read from it
                discard(df)
        if idle == 2:
            break
    return state, score


def _links(graph: DataFrame, state: DataFrame) -> DataFrame:
    """component_id, record_id, community, k, total, to, k_to: the weight from each node to each community next to it, its own too; loops apart."""
    cross = graph.where("u != v")
    ends = cross.select("component_id", F.col("u").alias("record_id"), F.col("v").alias("n"), "w").union(cross.select("component_id", F.col("v").alias("record_id"), F.col("u").alias("n"), "w"))
    there = state.select("component_id", F.col("record_id").alias("n"), F.col("community").alias("to"))
    own = state.select("component_id", "record_id", "community", "k", "total")
    placed = ends.join(there, ["component_id", "n"]).join(own, ["component_id", "record_id"])
    return placed.groupBy("component_id", "record_id", "community", "k", "total", "to").agg(F.sum("w").alias("k_to"))


def _quality(state: DataFrame, links: DataFrame, cfg: RefineConfig) -> DataFrame:
    """component_id, m, from sums that nodes and links hold already."""
    expected = F.lit(cfg.resolution) * F.pow(F.sum("k") / (2 * F.max("total")), 2)
    per = state.groupBy("component_id", "community").agg((F.sum("loop") / F.max("total") - expected).alias("share"))
    inside = links.where("to = community").groupBy("component_id").agg((F.sum("k_to") / (2 * F.max("total"))).alias("inside"))
    shares = per.groupBy("component_id").agg(F.sum("share").alias("share")).join(inside, "component_id", "left")
    return shares.select("component_id", (F.col("share") + F.coalesce("inside", F.lit(0.0))).alias("m"))


def _one_pass(state: DataFrame, links: DataFrame, cfg: RefineConfig, step: int) -> DataFrame:
    key = ["component_id", "record_id"]
    degree = state.groupBy("component_id", "community").agg(F.sum("k").alias("d"))
    parity = F.pmod(F.xxhash64(F.lit(cfg.seed), "record_id"), F.lit(2)) == step % 2
    k_own = F.max(F.when(F.col("to") == F.col("community"), F.col("k_to"))).over(Window.partitionBy(*key))
    options = links.where(parity).withColumn("k_own", F.coalesce(k_own, F.lit(0.0))).where("to != community")
    options = options.join(degree, ["component_id", "community"]).withColumn("d_own", F.col("d") - F.col("k")).drop("d")
    options = options.join(degree.select("component_id", F.col("community").alias("to"), F.col("d").alias("d_to")), ["component_id", "to"])
    gain = move_gain(*[F.col(c) for c in ("k", "k_to", "d_to", "k_own", "d_own", "total")], cfg.resolution)
    best = F.min_by("to", F.struct(-F.col("gain"), F.col("to"))).alias("to")
    wish = options.withColumn("gain", F.round(gain, 12)).where("gain > 0").groupBy(*key, "community").agg(best)
    back = wish.select("component_id", F.col("community").alias("to"), F.col("to").alias("community")).distinct().withColumn("swap", F.lit(True))
    allowed = wish.join(back, ["component_id", "to", "community"], "left").where("swap is null or to < community").select(*key, "to")
    return state.join(allowed, key, "left").select(*key, F.coalesce("to", "community").alias("community"), "k", "loop", "total")
