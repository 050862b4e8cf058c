"""Walks expanded from their edge ids, in their rows and by joined steps."""

import __spark_entry__
from carrierpath.plans import queries

from .test_runs import lines, moved  # noqa: F401


def test_edges_expand_without_moving_steps(spark, lines, monkeypatch):  # noqa: F811
    run = lambda name="edge_expand": __spark_entry__.queries()[name](spark, lines)
    got, rows = moved(spark, lambda: run().collect())
    assert got and all(r["ok"] for r in got) and rows < 15_000  # the walks have some 36,000 nodes
    nodes = {}
    for r in sorted(run("walk_nodes").collect()):
        nodes.setdefault(r["path_id"], []).append(r["node"])
    assert {r["path_id"]: r["labels"] for r in got} == {i: ",".join(x) for i, x in nodes.items()}
    monkeypatch.setattr(queries, "EDGE_ROWS", 0)
    assert sorted(run().collect()) == sorted(got)
