"""All queries by name, and the SQL twins of those that SQL can express."""

from __future__ import annotations

from entitygraph.plans import catalogue, surface, workloads

catalogue.add_whole_forms()
#: Queries that run for minutes come last: the experiment's grid, its ablations, the distributed refinement, and the forms over all references.
_LATE = ("w1_two_step_runs", "w2_", "w3_", "w4_", "w12_ablations", "e16_", "c10_")
_late = [n for n in catalogue.QUERIES if n.startswith(_LATE) or n.endswith("_whole")]
QUERIES = {n: f for n, f in catalogue.QUERIES.items() if n not in _late}
LATE_QUERIES = {n: catalogue.QUERIES[n] for n in sorted(_late, key=lambda n: not n.endswith("_whole"))}
ORACLE_SQL, link_index_query = catalogue.ORACLE_SQL, catalogue.link_index_query

__all__ = ["LATE_QUERIES", "ORACLE_SQL", "QUERIES", "link_index_query", "surface", "workloads"]
