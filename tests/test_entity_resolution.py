import itertools

import pytest

from entitygraph.errors import LocalCapExceeded
from entitygraph.operators import closure as cl
from entitygraph.operators.hierarchical import cluster_hierarchical
from entitygraph.operators.louvain import RefineConfig, louvain
from entitygraph.operators.matching import scoring_matrix
from entitygraph.plans.pipeline import ResolveConfig, cluster, resolve, resolve_iterative, score_records
from entitygraph.sources.fixtures import worked_example

TWO_TRIANGLES = [("1", "2"), ("2", "3"), ("1", "3"), ("4", "5"), ("5", "6"), ("4", "6"), ("3", "4")]


def modularity(edges, member):
    total = sum(w for *_, w in edges)
    out = 0.0
    for c in set(member.values()):
        inside = sum(w for u, v, w in edges if member[u] == c == member[v])
        degree = sum(w * ((member[u] == c) + (member[v] == c)) for u, v, w in edges)
        out += inside / total - (degree / (2 * total)) ** 2
    return out


def partitions(items):
    if not items:
        yield []
        return
    first, *rest = items
    for part in partitions(rest):
        for i in range(len(part)):
            yield [*part[:i], [first, *part[i]], *part[i + 1 :]]
        yield [[first], *part]


@pytest.mark.parametrize("move", ["best", "first_gain"])
def test_two_triangles(move):
    member, m = louvain([(u, v, 1.0) for u, v in TWO_TRIANGLES], RefineConfig(move=move))[-1]
    assert sorted(set(member.values())) == ["1", "4"] and m == pytest.approx(5 / 14)


def test_kernel_against_all_partitions():
    for seed in range(12):
        nodes = [str(i) for i in range(6)]
        edges = [(u, v, ((hash_(u, v, seed) % 9) + 1) / 10) for u, v in itertools.combinations(nodes, 2) if hash_(v, u, seed) % 3]
        levels = louvain(edges)
        optimum = max(modularity(edges, {x: str(i) for i, g in enumerate(p) for x in g}) for p in partitions(sorted({x for e in edges for x in e[:2]})))
        for member, m in levels:
            assert m == pytest.approx(modularity(edges, member))
        assert all(a[1] < b[1] for a, b in itertools.pairwise(levels))
        assert optimum - 0.1 <= levels[-1][1] <= optimum + 1e-9


def hash_(a, b, seed):
    return (int(a) * 7919 + int(b) * 104729 + seed * 1299709) % 1009


@pytest.mark.parametrize("method", cl.METHODS)
def test_closure_methods_agree(spark, method):
    edges = [("a", "b"), ("b", "c"), ("d", "c"), ("x", "y"), ("y", "x"), ("z", "z"), *[(f"p{i}", f"p{i + 1}") for i in range(9)]]
    got = {r["record_id"]: r["component_id"] for r in cl.connected_components(spark.createDataFrame(edges, "a string, b string"), method).collect()}
    want = {k: "a" for k in "abcd"} | {"x": "x", "y": "x"} | {f"p{i}": "p0" for i in range(10)}
    assert got == want


@pytest.mark.parametrize("method", cl.METHODS)
def test_closure_of_nothing(spark, method):
    assert cl.connected_components(spark.createDataFrame([], "a string, b string"), method).collect() == []


def test_local_closure_has_a_cap(spark):
    with pytest.raises(LocalCapExceeded):
        cl.connected_components(spark.createDataFrame(TWO_TRIANGLES, "a string, b string"), "local", local_cap=3)


def test_worked_example(spark):
    refs = worked_example(spark)
    scores = {(r["a"][-1], r["b"][-1]): r["score"] for r in score_records(refs).collect()}
    assert len(scores) == 15
    for pair, want in {("1", "2"): 0.914493, ("1", "3"): 0.844928, ("1", "4"): 0.968254, ("3", "4"): 0.833796, ("5", "6"): 0.987179, ("1", "6"): 0.755072}.items():
        assert scores[pair] == pytest.approx(want, abs=1e-6)
    assert clusters(resolve(refs, ResolveConfig(mu=0.8))) == [("1", "2", "3", "4"), ("5", "6")]
    assert clusters(resolve(refs, ResolveConfig(mu=0.75))) == [("1", "2", "3", "4", "5", "6")]
    assert clusters(resolve(refs, ResolveConfig(mu=0.75, refine_edges="above_mu"))) == [("1", "2", "3", "4"), ("5", "6")]


def clusters(df):
    groups = {}
    for r in df.collect():
        groups.setdefault(r["cluster_id"], []).append(r["record_id"][-1])
    return sorted(tuple(sorted(g)) for g in groups.values())


def test_bridge_is_cut_and_lonely_records_stay(spark):
    scored = spark.createDataFrame([(u, v, 1.0) for u, v in TWO_TRIANGLES], "a string, b string, score double")
    records = spark.createDataFrame([(str(i), "") for i in range(1, 8)], "record_id string, body string")
    assert clusters(cluster_hierarchical(scored, records, 0.5)) == [("1", "2", "3"), ("4", "5", "6"), ("7",)]
    distributed = ResolveConfig(mu=0.5, refine=RefineConfig(local_edge_cap=1, max_levels=2, max_passes=4))
    assert clusters(cluster(scored, records, distributed)) == [("1", "2", "3"), ("4", "5", "6"), ("7",)]


def test_two_phases_give_the_same_clusters(spark):
    from entitygraph.sources.fixtures import WORKED_EXAMPLE

    rows = [(a, t, b if i else b.replace("KELDO", "KELDOO")) for i, (a, t, b) in enumerate(WORKED_EXAMPLE)]
    refs = spark.createDataFrame(rows, "record_id string, truth_id long, body string")
    assert clusters(resolve(refs, ResolveConfig(mu=0.8))) == clusters(resolve(refs, ResolveConfig(mu=0.8, two_phase=True)))


def test_baseline_ends_and_covers_all(spark):
    found, rounds = resolve_iterative(worked_example(spark), 0.7, 0.9)
    assert rounds <= 4 and sorted(r["record_id"][-1] for r in found.collect()) == list("123456")


def test_empty_token_lists_score_nothing(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([([], ["A"]), (["A"], ["A"])], "a array<string>, b array<string>")
    assert [r[0] for r in df.select(scoring_matrix(F.col("a"), F.col("b"))).collect()] == [0.0, 1.0]


def test_copurchase_graph_is_whole(spark):
    from entitygraph.plans.catalogue import QUERIES

    sf = "/root/testdata/sf0.001"
    orders = {}
    for r in spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey", "l_partkey").collect():
        orders.setdefault(r[0], set()).add(f"{r[1]:012d}")
    parent = {p: p for o in orders.values() if len(o) > 1 for p in o}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for o in orders.values():
        for p in o if len(o) > 1 else ():
            x, y = sorted((root(p), root(min(o))))
            parent[y] = x
    got = {r["record_id"]: r["component_id"] for r in QUERIES["w9_copurchase_components"](spark, sf).collect()}
    assert got == {p: root(p) for p in parent}


def test_operators_take_all_references(spark):
    from entitygraph.plans import queries

    QUERIES = {**queries.QUERIES, **queries.LATE_QUERIES}
    sf = "/root/testdata/sf0.01"
    copies = sum(1 + 7919 * r[0] % 5 for r in spark.read.parquet(f"{sf}/customer.parquet").select("c_custkey").collect())
    assert copies > 1000 and QUERIES["p0_references_whole"](spark, sf).distinct().count() == copies
    report = QUERIES["k6_blocking_report_whole"](spark, sf).first()
    assert report["reduction_ratio"] == pytest.approx(1 - report["n_pairs"] / (copies * (copies - 1) / 2), abs=1e-6)
    assert QUERIES["p0_references"](spark, sf).count() == 1000


def test_lsh_makes_all_pairs_of_a_large_bucket(spark):
    from entitygraph.operators.blocking import lsh_pairs

    tokens = spark.createDataFrame([(f"{i:03d}", t) for i in range(23) for t in ("A", "B")] + [("x", "C")], "record_id string, token string")
    got = {(r["a"], r["b"]): r["shared"] for r in lsh_pairs(tokens, largest=5).collect()}
    assert got == {(f"{i:03d}", f"{j:03d}"): 16 for i in range(23) for j in range(i + 1, 23)}


def test_distributed_search_goes_on_until_stable(spark):
    from entitygraph.operators.louvain import refine_distributed

    edges = [(f"{i:02d}", f"{i + 1:02d}", 1.0) for i in range(31)]
    graph = spark.createDataFrame([("c", *e) for e in edges], "component_id string, u string, v string, w double")
    found = refine_distributed(graph).collect()
    assert found[0]["m"] == pytest.approx(modularity(edges, {r["record_id"]: r["community"] for r in found}))
    assert found[0]["m"] >= louvain(edges)[-1][1] - 0.05
