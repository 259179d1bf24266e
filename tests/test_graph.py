import random

import pytest

from corpusdedup.operators.graph import DisjointSets, connected_components, local_forest


def truth(edges):
    sets = DisjointSets()
    for u, v in edges:
        if u != v:
            sets.union(u, v)
    return {x: sets.find(x) for x in list(sets.up)}


random.seed(5)
GRAPHS = {
    "path": [(i, i + 1) for i in range(20)],
    "reversed path": [(20 - i, 19 - i) for i in range(20)],
    "star": [(500, i) for i in range(1, 30)],
    "cycle": [(i, (i + 1) % 12) for i in range(12)],
    "cliques and a bridge": [(i, j) for i in range(8) for j in range(i)] + [(i, j) for i in range(20, 28) for j in range(20, i)] + [(3, 25)],
    "random": [(random.randint(0, 60), random.randint(0, 60)) for _ in range(45)],
    "loops and repeats": [(1, 1), (2, 3), (3, 2), (2, 3), (7, 7)],
    "none": [],
}


@pytest.mark.parametrize("name", GRAPHS)
@pytest.mark.parametrize("method", ["contract", "star", "driver"])
def test_components(spark, name, method):
    edges = spark.createDataFrame(GRAPHS[name], "u long, v long")
    assert {r.node: r.component for r in connected_components(edges, method).collect()} == truth(GRAPHS[name])


@pytest.mark.parametrize("name", GRAPHS)
@pytest.mark.parametrize("local_edges", [0, 12])
def test_rounds_and_the_end_in_one_task_agree(spark, name, local_edges):
    edges = spark.createDataFrame(GRAPHS[name], "u long, v long")
    assert {r.node: r.component for r in connected_components(edges, local_edges=local_edges).collect()} == truth(GRAPHS[name])


def test_label_propagation(spark):
    edges = spark.createDataFrame(GRAPHS["random"], "u long, v long")
    assert {r.node: r.component for r in connected_components(edges, "label").collect()} == truth(GRAPHS["random"])


def test_long_path(spark):
    edges = spark.range(10_000).selectExpr("id AS u", "id + 1 AS v")
    found = connected_components(edges, local_edges=0)
    assert found.count() == 10_001 and found.where("component <> 0").count() == 0


def test_nulls_and_limits(spark):
    edges = spark.createDataFrame([(1, None), (None, 2), (3, 4)], "u long, v long")
    assert {r.node: r.component for r in connected_components(edges).collect()} == {3: 3, 4: 3}
    with pytest.raises(ValueError):
        connected_components(spark.range(5).selectExpr("id AS u", "id + 1 AS v"), "driver", driver_edge_limit=2)
    with pytest.raises(ValueError):
        connected_components(edges, "guess")


def test_forest_connects_alike_with_fewer_edges():
    edges = GRAPHS["cliques and a bridge"]
    u, v = local_forest(*zip(*edges))
    assert truth(zip(u.tolist(), v.tolist())) == truth(edges) and len(u) == 15
