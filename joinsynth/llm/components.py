"""Distributed connected components by rounds of hooking, pointer jumping and contraction.

Each round lets every vertex that has edges hook to its smallest neighbour if that is smaller
than itself, flattens the resulting forest by pointer jumping, and replaces edge ends by the
roots.  Every vertex that is not a local minimum disappears, so vertices at least halve and
the number of rounds is logarithmic.  No vertex, edge or label reaches the driver; the driver
sees one number a round (edges left).  Minima are partial aggregates, so a star of any degree
puts one row per map task in the reducer; look-ups are equi-joins that AQE may split.

Once at most ``ONE_TASK`` edges are left, one task solves what is left: a round is a dozen short
steps, whose plans and exchange threads take the driver more memory than such edges take a task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

#: Most edges between whole numbers (8 MB) that one task takes.
ONE_TASK = 500_000


def _solve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All edges (x, y) to (v, p) with p the least vertex of v's component; (v, v) is left out."""
    held = [b for b in batches if b.num_rows]
    if not held:
        return
    edges = pa.Table.from_batches(held)
    ids, at = np.unique(np.concatenate([edges["x"].to_numpy(), edges["y"].to_numpy()]), return_inverse=True)
    x, y = at[: edges.num_rows], at[edges.num_rows :]
    own = np.arange(len(ids))
    label = own
    while True:
        # every root hooks to the least root that an edge of its tree leads to
        least, root = np.minimum(label[x], label[y]), label.copy()
        np.minimum.at(root, label[x], least)
        np.minimum.at(root, label[y], least)
        while not np.array_equal(up := root[root], root):
            root = up
        if np.array_equal(root, label):
            break
        label = root
    moved = label != own
    yield pa.RecordBatch.from_arrays([pa.array(ids[moved]), pa.array(ids[label[moved]])], ["v", "p"])


def _flatten(parent: DataFrame) -> DataFrame:
    """Pointer jumping: (v, p) with p the root of v's tree; ``parent`` holds no roots."""
    while True:
        up = parent.select(F.col("v").alias("p"), F.col("p").alias("g"))
        jumped = cut(parent.join(up, "p", "left").select("v", F.coalesce("g", "p").alias("p"), F.col("g").isNotNull().alias("moved")))
        moved = jumped.filter("moved").limit(1).count()
        parent = jumped.select("v", "p")
        if not moved:
            return parent


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``edges`` to (v, component): the least vertex reachable, for every vertex that is not itself the least.

    Null ends and self loops carry no information and are ignored; repeated edges are fine;
    an empty edge table gives an empty result.  Vertex type: any orderable type.
    """
    left = edges.select(F.col(a).alias("x"), F.col(b).alias("y")).filter("x != y")
    left = cut(left.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y")).distinct())
    whole = left.schema["x"].dataType.typeName() in ("integer", "long") and left.schema["x"].dataType == left.schema["y"].dataType
    total: DataFrame | None = None
    while edges_left := left.count():
        last = whole and edges_left <= ONE_TASK
        if last:
            kind = left.schema["x"].dataType.simpleString()
            forest = cut(left.coalesce(1).mapInArrow(_solve, f"v {kind}, p {kind}"))
        else:
            # y < x on every edge, so the least neighbour below a vertex is its least y
            forest = _flatten(left.groupBy(F.col("x").alias("v")).agg(F.min("y").alias("p")))
        if total is None:
            total = forest
        else:
            step = forest.select(F.col("v").alias("p"), F.col("p").alias("root"))
            total = cut(total.join(step, "p", "left").select("v", F.coalesce("root", "p").alias("p")).unionByName(forest))
        if last:
            break
        at = lambda c: forest.select(F.col("v").alias(c), F.col("p").alias(f"{c}_root"))
        moved = left.join(at("x"), "x", "left").join(at("y"), "y", "left").select(F.coalesce("x_root", "x").alias("x"), F.coalesce("y_root", "y").alias("y")).filter("x != y")
        left = cut(moved.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y")).distinct())
    if total is None:
        return left.select(F.col("x").alias("v"), F.col("y").alias("component"))
    return total.select("v", F.col("p").alias("component"))
