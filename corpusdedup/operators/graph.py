"""Union graph: spanning forests inside a task, connected components across the cluster."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusdedup.plans.shared import materialise

#: Written edges up to which one task connects what is left of a graph.
LOCAL_EDGES = 1 << 18
#: Edges beyond which the driver's union-find refuses to work.
DRIVER_EDGE_LIMIT = 2_000_000


class DisjointSets:
    """Union by smallest member, with path halving."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        up = self.up
        up.setdefault(x, x)
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def union(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        if a == b:
            return False
        if b < a:
            a, b = b, a
        self.up[b] = a
        return True


def local_forest(u: Iterable[int], v: Iterable[int]) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the edges: as connected as they are, with fewer edges than nodes."""
    sets = DisjointSets()
    kept = [(a, b) for a, b in zip(u, v) if sets.union(a, b)]
    out = np.array(kept, dtype=np.int64).reshape(-1, 2)
    return out[:, 0], out[:, 1]


def _both_ways(edges: DataFrame) -> DataFrame:
    """Every edge in both directions, once.  They are made by one generator: a union would compute the edges twice."""
    own = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).where("u is not null and v is not null and u <> v")
    way = lambda a, b: F.struct(F.col(a).alias("u"), F.col(b).alias("v"))
    return own.select(F.explode(F.array(way("u", "v"), way("v", "u"))).alias("e")).select("e.u", "e.v").distinct()


def _empty(edges: DataFrame) -> bool:
    return not edges.head(1)


def _in_one_task(edges: DataFrame) -> DataFrame:
    """(x, to): each node and the least of its component, by union-find in one task over edges of a checked number."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = DisjointSets()
        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                sets.union(a, b)
        nodes = list(sets.up)
        yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([sets.find(x) for x in nodes], pa.int64())], names=["x", "to"])

    return edges.select("u", "v").coalesce(1).mapInArrow(run, "x long, to long")


def contract(edges: DataFrame, local: int = 0) -> DataFrame:
    """(node, root): nodes of one component share a root, which is any one of them.

    Each round sends every node to the neighbour (or itself) of least hash and joins the edges' ends to where they went.
    The hash makes the order random, so the graph shrinks by a constant factor a round whatever its shape; aggregates are
    partial on the map side and the joins are those that adaptive execution can split.  Once at most ``local`` edges are left, one
    task connects them instead of further rounds.
    """
    edges = materialise(_both_ways(edges), "cc-edges")
    labels = None
    while not _empty(edges):
        if local and edges.count() <= local:
            moves = materialise(_in_one_task(edges.where("u < v")), "cc-moves")
            if labels is None:
                return moves.select(F.col("x").alias("node"), F.col("to").alias("root"))
            return labels.join(moves, labels["root"] == moves["x"], "left").select("node", F.coalesce("to", "root").alias("root"))
        key = lambda c: F.struct(F.xxhash64(c).alias("h"), F.col(c).alias("x"))
        near = edges.groupBy("u").agg(F.min(key("v")).alias("m"))
        moves = materialise(near.select(F.col("u").alias("x"), F.least(F.col("m"), key("u"))["x"].alias("to")), "cc-moves")
        if labels is None:
            labels = moves.select(F.col("x").alias("node"), F.col("to").alias("root"))
        else:
            labels = materialise(labels.join(moves, labels["root"] == moves["x"], "left").select("node", F.coalesce("to", "root").alias("root")), "cc-labels")
        there = moves.select(F.col("x").alias("v"), F.col("to").alias("tv"))
        edges = edges.join(moves.withColumnRenamed("x", "u"), "u").join(there, "v").select(F.col("to").alias("u"), F.col("tv").alias("v")).where("u <> v").distinct()
        edges = materialise(edges, "cc-edges")
    return labels if labels is not None else edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _by_labels(edges: DataFrame) -> DataFrame:
    """Each node takes the least label among its neighbours until none changes: as many rounds as the widest component is wide."""
    edges = materialise(_both_ways(edges), "cc-edges")
    labels = materialise(edges.select(F.col("u").alias("node"), F.col("u").alias("root")).distinct(), "cc-labels")
    while True:
        heard = edges.join(labels.withColumnRenamed("node", "v"), "v").groupBy(F.col("u").alias("node")).agg(F.min("root").alias("heard"))
        new = materialise(labels.join(heard, "node", "left").select("node", F.least("root", F.coalesce("heard", "root")).alias("root"), (F.coalesce("heard", "root") < F.col("root")).alias("changed")), "cc-labels")
        labels = new.select("node", "root")
        if not new.where("changed").head(1):
            return labels


def _by_stars(edges: DataFrame) -> DataFrame:
    """Alternate two rewrites until the edges are stars around the least node of each component.

    The large step links the greater neighbours of a node, the small step its lesser neighbours, to the least of them all.
    """
    now = materialise(_both_ways(edges).where("u > v"), "cc-stars")  # u greater than v
    while True:
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = materialise(large, "cc-stars")
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(least, "u")
        small = moved.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").union(least.select("u", F.col("m").alias("v"))).distinct()
        small = materialise(small, "cc-stars")
        if not small.exceptAll(now).head(1) and not now.exceptAll(small).head(1):
            return small.select(F.col("u").alias("node"), F.col("v").alias("root")).union(small.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
        now = small


def _on_driver(edges: DataFrame, limit: int) -> DataFrame:
    """Union-find on the driver, for graphs of a checked size."""
    spark = edges.sparkSession
    rows = edges.select("u", "v").limit(limit + 1).collect()
    if len(rows) > limit:
        raise ValueError(f"more than {limit} edges: use a distributed method")
    sets = DisjointSets()
    for r in rows:
        if r["u"] is not None and r["v"] is not None and r["u"] != r["v"]:
            sets.union(r["u"], r["v"])
    return spark.createDataFrame([(x, sets.find(x)) for x in list(sets.up)], "node long, root long")


def connected_components(edges: DataFrame, method: str = "contract", driver_edge_limit: int = DRIVER_EDGE_LIMIT, local_edges: int = LOCAL_EDGES, written: bool = False) -> DataFrame:
    """(node, component): component is the least node that the edges (u, v) connect a node with.

    Nodes without an edge to another don't appear.  Methods: ``contract`` (default), ``star``, ``label``, ``driver``.
    ``contract`` leaves the last ``local_edges`` (each counted both ways) to one task, all of them if there are no more; 0 never
    does.  ``written`` says that the edges are a written table, which can be counted and read again.
    """
    if method == "contract" and local_edges:
        edges = edges if written else materialise(edges.select("u", "v"), "cc-given")
        if 2 * edges.count() <= local_edges:
            own = edges.select(F.col("u").cast("long").alias("u"), F.col("v").cast("long").alias("v")).where("u is not null and v is not null and u <> v")
            return _in_one_task(own).select(F.col("x").alias("node"), F.col("to").alias("component"))
    if method == "driver":
        found = _on_driver(edges, driver_edge_limit)
    elif method in ("contract", "label", "star"):
        found = contract(edges, local_edges) if method == "contract" else {"label": _by_labels, "star": _by_stars}[method](edges)
    else:
        raise ValueError(f"no such method: {method}")
    least = found.groupBy("root").agg(F.min("node").alias("component"))
    return found.join(least, "root").select("node", "component")
