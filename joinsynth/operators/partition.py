"""Partitioning an instance into sub-instances of similar sensitivity, as label columns.

No sub-instance is copied: a partition adds a label to the rows of each relation (and, for
hierarchical joins, repeats a row once per configuration that it belongs to).
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.noise import NoiseSource, tau, tlap_below, tlap_col, uniform_col
from ..hyper import AttrTree, Node, boundary, meet
from ..relation import Instance
from ..sources.formats import cut
from .sensitivity import aggregate_max, degree_table, hier_degree, join_attrs, residual_sensitivity, subsets

#: Buckets beyond which no degree of a 64-bit count can lie.
LAST_BUCKET = 64


def bucket_of(degree: Column, lam: float, last: int = LAST_BUCKET) -> Column:
    """1 for degrees up to 2 * lam, then one bucket per doubling; a threshold belongs to the bucket below it.

    A ladder of comparisons: no rounding of logarithms decides a tie.
    """
    out = F.lit(last)
    for i in reversed(range(1, last)):
        out = F.when(degree <= F.lit(lam * 2.0**i), i).otherwise(out)
    return out


def noisy(degree: Column, eps: float, delta: float, noise: NoiseSource, *key: Column | str) -> Column:
    if noise.kind == "zero":
        return degree.cast("double")
    return degree + tlap_col(1 / eps, tau(eps, delta, 1), uniform_col(noise.secret, *key))


@dataclass(frozen=True)
class Partition:
    """Labels: join values (or tuples) with a bucket or configuration; relations with their labels added."""

    labels: DataFrame
    instance: Instance
    by: tuple[str, ...]


def partition_two_table(inst: Instance, domain: DataFrame, eps: float, delta: float, lam: float, noise: NoiseSource, pairs: bool = False) -> Partition:
    """Buckets of every join value of the public domain, those without rows included, by the noisy larger degree.

    ``pairs``: a bucket for each side, as the hierarchical partition of the same join has it.
    """
    on = list(join_attrs(inst.spec))
    known = domain.select(*on).join(degree_table(inst), on, "left").select(*on, F.coalesce("deg1", F.lit(0)).alias("deg1"), F.coalesce("deg2", F.lit(0)).alias("deg2"))
    key = F.concat_ws(",", *(F.col(c).cast("string") for c in on))
    # the noisy degree is a column of its own: inside the ladder it would be evaluated once a rung
    if pairs:
        noised = known.select(*on, *(noisy(F.col(f"deg{i}"), eps, delta, noise, f"deg{i}", key).alias(f"x{i}") for i in (1, 2)))
        labels = noised.select(*on, F.concat_ws(",", bucket_of(F.col("x1"), lam), bucket_of(F.col("x2"), lam)).alias("bucket"))
    else:
        noised = known.select(*on, noisy(F.greatest("deg1", "deg2"), eps, delta, noise, "deg", key).alias("x"))
        labels = noised.select(*on, bucket_of(F.col("x"), lam).alias("bucket"))
    # an equi-join on the join value: broadcast if small by the planner's own size check, else co-partitioned
    frames = tuple(f.join(labels, on) for f in inst.frames)
    return Partition(labels, Instance(inst.spec, frames), ("bucket",))


def partition_open_domain(inst: Instance, size: int, eps: float, delta: float, lam: float, noise: NoiseSource) -> tuple[Partition, DataFrame]:
    """The same partition over a public domain of ``size`` join values that can't be listed, and (sub_id, share of the domain).

    Join values without rows are alike: their noise is drawn for all of them at once, as the numbers of them that fall into
    each bucket, with the law that noise for each would give.  A bucket of such values only is a part without rows.
    """
    on = list(join_attrs(inst.spec))
    seen = degree_table(inst).select(*on)
    part = partition_two_table(inst, seen, eps, delta, lam, noise)
    held = {r["bucket"]: r["count"] for r in part.labels.groupBy("bucket").count().collect()}  # one a bucket
    absent = size - sum(held.values())
    if absent < 0:
        raise ValueError("more join values than the public domain has")
    radius = tau(eps, delta, 1)
    below = [tlap_below(lam * 2.0**i, 1 / eps, radius) for i in range(1, LAST_BUCKET)]
    chance = np.diff([0.0, *below, 1.0]) if noise.kind != "zero" else np.eye(1, LAST_BUCKET)[0]
    drawn = noise.generator("absent").multinomial(absent, chance) if noise.kind != "zero" else (chance * absent).astype(int)
    empty = {i + 1: int(n) for i, n in enumerate(drawn) if n}
    share = inst.spark.createDataFrame([(str(b), (held.get(b, 0) + empty.get(b, 0)) / size) for b in sorted({*held, *empty})], "sub_id string, share double")
    names = inst.spark.createDataFrame([(b,) for b in sorted(empty)], "bucket int")
    labels = part.labels.unionByName(names.select(*(F.lit(None).cast(part.labels.schema[c].dataType).alias(c) for c in on), "bucket"))
    return Partition(labels, part.instance, part.by), share


def partition_true_degrees(inst: Instance, domain: DataFrame, lam: float, pairs: bool = False) -> Partition:
    """The yardstick of the analysis: buckets of exact degrees (not private)."""
    return partition_two_table(inst, domain, 1.0, 1e-6, lam, NoiseSource.zero(), pairs)


def label_col(node: Node) -> str:
    return f"c_{node.name}"


#: The public domain of some attributes as a table.
Domain = Callable[[tuple[str, ...]], DataFrame]


def _configurations(tree: AttrTree, node: Node, splits: dict[str, DataFrame]) -> DataFrame | None:
    """Labels of all nodes below, as they follow from the noisy degrees of the whole domain; None for a leaf."""
    grid = None
    for child in tree.children(node):
        part = splits[child.name].select(*(label_col(n) for n in (*tree.below(child), child))).distinct()
        grid = part if grid is None else grid.crossJoin(part)
    return grid


def split_on_attribute(inst: Instance, tree: AttrTree, node: Node, labels: dict[int, tuple[str, ...]], splits: dict[str, DataFrame], domain: Domain, eps: float, delta: float, lam: float, noise: NoiseSource, last: int = LAST_BUCKET) -> tuple[Instance, dict[int, tuple[str, ...]], DataFrame]:
    """One node's split of every live configuration.

    Degrees are taken per configuration of the nodes below and for every value of the public domain above the node, with
    rows or without; each relation of the node gets the labels of all those nodes (a row is repeated for labels of subtrees
    that it has no part in) and the new one.  ``splits``: the tables (values, labels) of the nodes below.
    """
    rels = tuple(sorted(node.atom))
    given = tree.ancestors(node)
    below = tuple(label_col(n) for n in tree.below(node))
    degree = hier_degree(inst, rels, given, labels)
    grid = _configurations(tree, node, splits)
    keys = domain(given)
    grid = keys if grid is None else keys.crossJoin(grid)
    on = [*given, *below]
    known = grid.join(degree, on, "left") if on else grid.crossJoin(degree)
    key = F.concat_ws(",", *(F.col(c).cast("string") for c in on)) if on else F.lit("")
    known = known.withColumn("x", noisy(F.coalesce("deg", F.lit(0)), eps, delta, noise, label_col(node), key))
    known = cut(known.select(*on, bucket_of(F.col("x"), lam, last).alias(label_col(node))))
    frames, out = [], dict(labels)
    for i, f in enumerate(inst.frames):
        if i in node.atom:
            shared = [c for c in f.columns if c in known.columns]
            f = cut(f.join(known, shared) if shared else f.crossJoin(known))
            out[i] = (*below, label_col(node))
        frames.append(f)
    return Instance(inst.spec, tuple(frames)), out, known


def partition_hierarchical(inst: Instance, eps: float, delta: float, lam: float, noise: NoiseSource, domain: Domain, skip_root: bool = False, last: int = LAST_BUCKET) -> Partition:
    """Bottom-up over the attribute tree; afterwards rows bear one label per node and configurations are disjoint in the join.

    The configurations are all that the noisy degrees of the public ``domain`` give, whether rows have them or not.
    ``last``: larger degrees share this bucket, so that the number of buckets is a public figure.
    ``skip_root``: the root's split has one group and separates nothing but configurations; leaving it out saves its noise.
    """
    tree = AttrTree(inst.spec)
    labels: dict[int, tuple[str, ...]] = {}
    splits: dict[str, DataFrame] = {}
    roots = {n.name for n in tree.roots()}
    for node in tree.post_order():
        if skip_root and node.name in roots and tree.children(node):
            inst, labels, splits[node.name] = _merge_root(inst, tree, node, labels, splits)
        else:
            inst, labels, splits[node.name] = split_on_attribute(inst, tree, node, labels, splits, domain, eps, delta, lam, noise, last)
    every = tuple(label_col(n) for n in tree.post_order() if not (skip_root and n.name in roots and tree.children(n)))
    live = None
    for root in tree.roots():
        one = splits[root.name].select(*(c for c in splits[root.name].columns if c in every)).distinct()
        live = one if live is None else live.crossJoin(one)
    if len(tree.roots()) > 1:
        return Partition(live, inst, every)
    label = F.concat_ws(",", *every).alias("config")
    frames = tuple(f.withColumn("config", label).drop(*every) for f in inst.frames)
    return Partition(live.select(label).distinct(), Instance(inst.spec, frames), ("config",))


def _merge_root(inst: Instance, tree: AttrTree, node: Node, labels: dict[int, tuple[str, ...]], splits: dict[str, DataFrame]) -> tuple[Instance, dict[int, tuple[str, ...]], DataFrame]:
    """Gives every relation the labels of all nodes below the root, without splitting on it."""
    grid = _configurations(tree, node, splits)
    frames, out = [], dict(labels)
    for i, f in enumerate(inst.frames):
        shared = [c for c in f.columns if c in grid.columns]
        frames.append(f.join(grid, shared) if shared else f.crossJoin(grid))
        out[i] = tuple(grid.columns)
    return Instance(inst.spec, tuple(frames)), out, grid


def bucket_count(n_max: float, lam: float) -> int:
    """Buckets that degrees up to a public ``n_max`` need."""
    return max(1, math.ceil(math.log2(n_max / lam + 1)))


def replication_bound(inst: Instance, n_max: float, lam: float) -> int:
    """Public bound on the parts that one tuple may be in: buckets to the number of nodes its relation has no part in."""
    buckets = bucket_count(n_max, lam)
    tree = AttrTree(inst.spec)
    return max(math.prod(buckets for n in tree.nodes if i not in n.atom) for i in range(inst.spec.m))


def degree_bound(inst: Instance, n_max: float, lam: float) -> int:
    """Public bound on the noisy degrees that one tuple changes, over all nodes of its relation.

    At a node a tuple changes one degree for each configuration of the labels below that its values leave open: those of
    nodes without its relation whose own key has more attributes than the tuples that the degree counts.
    """
    buckets, tree = bucket_count(n_max, lam), AttrTree(inst.spec)
    open_ = lambda x, i: [n for n in tree.below(x) if i not in n.atom and set(tree.ancestors(n)) > set(meet(inst.spec, x.atom))]
    return max(sum(buckets ** len(open_(x, i)) for x in tree.nodes if i in x.atom) for i in range(inst.spec.m))


def partition_stats(part: Partition) -> DataFrame:
    """(relation, parts, tuples, copies, most): sub-instances that its rows lie in, and repetition of its tuples."""
    out = None
    for r, f in zip(part.instance.spec.relations, part.instance.frames, strict=True):
        per = f.groupBy(*r.attrs).agg(F.count("*").alias("copies"))
        one = per.agg(F.count("*").alias("tuples"), F.coalesce(F.sum("copies"), F.lit(0)).alias("copies"), F.coalesce(F.max("copies"), F.lit(0)).alias("most"))
        one = one.crossJoin(f.select(*part.by).distinct().agg(F.count("*").alias("parts"))).select(F.lit(r.name).alias("relation"), "parts", "tuples", "copies", "most")
        out = one if out is None else out.unionByName(one)
    return out


def explore_path_partitions(inst: Instance, lam: float) -> DataFrame:
    """Two dead ends for a path of three relations: a part per middle tuple, and independent partitions of both middle attributes.

    One row: middle tuples (parts of the first), largest copies of an outer tuple under it, parts of the second, and the spread of
    the join degrees that are left in its worst part.
    """
    first, middle, last = inst.frames
    t, u = meet(inst.spec, (0, 1))[0], meet(inst.spec, (1, 2))[0]
    fan = middle.groupBy(t).agg(F.count("*").alias("n")).agg(F.max("n").alias("copies_first"))
    left, right = first.groupBy(t).agg(F.sum("freq").alias("dl")), last.groupBy(u).agg(F.sum("freq").alias("dr"))
    labelled = middle.join(left, t).join(right, u).withColumn("part", F.concat_ws(",", bucket_of(F.col("dl"), lam), bucket_of(F.col("dr"), lam)))
    inside = labelled.groupBy("part", t).agg(F.sum("freq").alias("n")).groupBy("part").agg(F.max("n").alias("hi"), F.min("n").alias("lo"))
    second = inside.agg(F.count("*").alias("independent_parts"), F.max(F.col("hi") / F.col("lo")).alias("worst_spread"))
    return middle.agg(F.count("*").alias("middle_parts")).crossJoin(fan).crossJoin(second)


def label_bounds(part: Partition, beta: float) -> DataFrame:
    """(sub_id, bound, local): residual and local sensitivity of every sub-instance with rows, from boundary maxima grouped by label."""
    inst, label, m = part.instance, part.by[0], part.instance.spec.m
    rows = None
    for e in subsets(m):
        if e:
            one = aggregate_max(inst, e, boundary(inst.spec, e), (label,)).select(F.col(label).cast("string").alias("sub_id"), F.lit(",".join(map(str, e))).alias("rels"), F.col("t").cast("double").alias("t"))
            rows = one if rows is None else rows.unionByName(one)

    def bound(frame: pd.DataFrame) -> pd.DataFrame:
        table = {frozenset(e): 0.0 for e in subsets(m)}
        table[frozenset()] = 1.0
        for r, t in zip(frame["rels"], frame["t"], strict=True):
            table[frozenset(map(int, r.split(",")))] = t
        local = max(table[frozenset(range(m)) - {i}] for i in range(m))
        return pd.DataFrame({"sub_id": [frame["sub_id"].iloc[0]], "bound": [residual_sensitivity(table, m, beta)], "local": [local]})

    return rows.groupBy("sub_id").applyInPandas(bound, "sub_id string, bound double, local double")
