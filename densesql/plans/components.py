"""Connected components of an edge table.

Large edge sets are contracted by alternating stars: each round links every node's
larger neighbours to its smallest neighbour and then every node to the smallest of its
smaller neighbours, until the edges are stars.  Rounds are staged, so lineage stays
short.  Once no more than a stated number of edges is left, one executor task finishes
them with a disjoint-set forest, which takes a fixed amount of memory and saves the
last rounds.  Edges never reach the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from densesql.plans.staging import Staging

#: Edges that one task finishes: 16 MB of them.
FINISH_EDGES = 1 << 20


def forest_roots(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, roots) of an edge list; a root is its component's smallest node."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[a], root[b])
        new = root.copy()
        np.minimum.at(new, root[a], low)
        np.minimum.at(new, root[b], low)
        while True:
            hop = new[new]
            if (hop == new).all():
                break
            new = hop
        if (new == root).all():
            return nodes, nodes[root]
        root = new


def _finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = list(batches)
    if held:
        u, v = (np.concatenate([b.column(k).to_numpy() for b in held]) for k in (0, 1))
        nodes, roots = forest_roots(u, v)
        yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(roots)], names=["node", "root"])


def connected_components(edges: DataFrame, staging: Staging, finish_edges: int = FINISH_EDGES, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node that has an edge; ``edges`` has two long columns.

    The root is the smallest node of the component.  Self-loops, repeated edges and
    either direction are allowed; a null end drops the edge.
    """
    a, b = edges.columns[:2]
    plain = edges.where(F.col(a) != F.col(b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    current, seen = staging.table(plain, "edges-0"), None
    for k in range(1, max_rounds + 1):
        state = tuple(current.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state[0] <= finish_edges:
            return staging.table(current.coalesce(1).mapInArrow(_finish, "node long, root long"), "roots")
        if state == seen:
            own = current.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
            return current.select(F.col("u").alias("node"), F.col("v").alias("root")).union(own)
        seen = state
        both = current.union(current.select(F.col("v").alias("u"), F.col("u").alias("v")))
        near = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(near, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = staging.table(large.where("u != v").distinct(), f"large-{k}")
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low)
        current = staging.table(small.where("u != v").distinct(), f"edges-{k}")
        staging.drop(f"large-{k}")
        staging.drop(f"edges-{k - 1}")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
