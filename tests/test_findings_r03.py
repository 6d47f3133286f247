"""One small test for each finding of the third review that led to a change outside the training-data operators."""

from entitygraph.plans.queries import LATE_QUERIES

SF = "/root/testdata/sf0.001"


def test_visits_without_a_move_are_passed_over_together(spark, monkeypatch):
    """r03 F1: w9_copurchase_two_step's search looked at each node of each pass by itself."""
    import numpy as np

    from entitygraph.operators import louvain as lo

    r = np.random.default_rng(1)
    a = r.integers(0, 400, 6000)
    b = np.where(r.random(6000) < 0.4, a // 20 * 20 + r.integers(0, 20, 6000), r.integers(0, 400, 6000))
    a, b = np.divmod(np.unique(np.minimum(a, b) * 400 + np.maximum(a, b)), 400)
    names, gain, seen = [f"{x:03d}" for x in range(400)], lo.move_gain, []
    for w in (np.ones(len(a)), 1.0 + (a * b) % 4):
        want = lo.louvain([(names[x], names[y], z) for x, y, z in zip(a, b, w, strict=True)])
        monkeypatch.setattr(lo, "move_gain", lambda *x: seen.append(1) or gain(*x))
        got = lo.louvain_arrays(names, a, b, w)
        monkeypatch.setattr(lo, "move_gain", gain)
        assert [({names[x]: names[c] for x, c in enumerate(member)}, round(m, 9)) for member, m in got] == [(member, round(m, 9)) for member, m in want]
    assert len(seen) < 3000


def test_pairs_of_all_references_are_listed(spark):
    """r03 F3: over all references the pairs were counted and not listed; with them, each bucket's members in one part and in several."""
    import itertools

    from entitygraph.operators import blocking as bl
    from entitygraph.operators import parsing as pr
    from entitygraph.sources.fixtures import WHOLE, references

    tokens = pr.explode_tokens(references(spark, SF, WHOLE)).cache()
    marks = sorted((r["record_id"], r["keys"]) for r in bl._hash_keys(tokens, 16, 3).collect())
    want = {(x, y): n for (x, p), (y, q) in itertools.combinations(marks, 2) if (n := sum(s == t for s, t in zip(p, q, strict=True)))}
    for found in (LATE_QUERIES["k7_lsh_pairs_whole"](spark, SF), bl.lsh_pairs(tokens, largest=4)):
        rows = found.collect()
        assert found.columns == ["a", "b", "shared"] and len(rows) == len(want) > 1000 and {(r["a"], r["b"]): r["shared"] for r in rows} == want
