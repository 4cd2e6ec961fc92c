"""Embedding near-dedup by dual traversal of cover trees.

Vectors are scaled to unit length, where cosine >= t means a distance of at most sqrt(2 - 2t).
Equal vectors are one point with a weight.  The top level of the tree is global: centres from a
bounded sample, each point in the cell of its nearest centre, with the cells' true covering radii
over all points.  Cells that lie together form groups of bounded bytes; a pair of groups is one
task, and a point goes there only if some cell of the other group is not pruned for it: by the ball
around the cell's centre, or by the plane half way between both centres, which every point of that
cell lies behind.  Both bounds hold for every linked pair, so nothing is lost, and on clustered
vectors few pairs of groups are sent at all.

In a task points are cut, cell by cell, into blocks; each gets a cover tree whose levels are
nested nets with halving radii and true covering radii.  Node pairs of two trees are taken from the
top; a pair is dropped if the distance of the centres less both covering radii exceeds the limit,
taken whole if the distance plus both radii stays within it, and opened otherwise.  Bounds use a safety
margin for single precision that grows with the number of dimensions; pairs of points that are left
are decided by their cosine in double precision, so the result is exact.

A task returns, per point, the number of linked rows it found and one edge to a local
representative, so a dense group costs a row a point and not a row a pair.

Defined results: a null vector, a zero one, and one with a null or non-finite component link
with nothing; vectors of different lengths never link; repeated rows link with each other; a
null id counts as a row but takes no part; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, look_up
from .components import components

#: Radii of the nested nets, coarsest first; a point is its own finest level.
RADII = (0.8, 0.4, 0.2, 0.1)
#: Most points of a block: its distance matrix is 16 MB in single precision.
BLOCK_MOST = 2_048
#: Bytes of vectors that a group is meant to hold; a task holds two groups.
GROUP_BYTES = 32 << 20
#: Points of the sample that centres and the sizes of cells are taken from (the least by a hash), and most centres.
SAMPLE, CENTRES = 4_096, 1_024
#: Rows of a distance matrix computed at once.
STRIP = 512

_SENT = "d int, lo int, hi int, home int, cell int, vec_id bigint, weight bigint, vector array<double>"
_FOUND = "vec_id bigint, n bigint, root bigint"


def margin(dims: int) -> float:
    """How far single precision may be off for a distance: an inner product of unit vectors by ``dims`` roundings, and its root."""
    return float(2 * np.sqrt(2 * dims * 2.0**-24) + dims * 2.0**-22)


def _net(close: np.ndarray) -> np.ndarray:
    """Greedy net over a boolean closeness matrix: for each point the centre that covers it (a centre covers itself)."""
    owner = np.full(len(close), -1)
    for i in range(len(close)):
        if owner[i] < 0:
            owner[i] = i
            free = close[i] & (owner < 0)
            owner[free] = i
    return owner


def build_nets(x: np.ndarray) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Nested nets of one block, coarsest first: the centre of each point, and the covering radius of each centre.

    Coarser centres are chosen among finer ones.
    """
    x = x.astype(np.float32)
    n = len(x)
    gap = np.empty((n, n), np.float32)
    for a in range(0, n, STRIP):
        gap[a : a + STRIP] = np.sqrt(np.maximum(0, 2 - 2 * (x[a : a + STRIP] @ x.T)))
    centre = np.arange(n)  # of every point, at the level above
    chain, cover = [], []
    for radius in reversed(RADII):
        live = np.unique(centre)
        owner = live[_net(gap[np.ix_(live, live)] <= radius)]
        up = np.empty(n, np.int64)
        up[live] = owner
        centre = up[centre]
        reach = np.zeros(n, np.float32)
        np.maximum.at(reach, centre, gap[centre, np.arange(n)])
        chain.insert(0, centre)
        cover.insert(0, reach)
    return chain, cover


class _Tree:
    """A block's points as arrays; nodes of each level with members and children."""

    def __init__(self, ids: np.ndarray, weight: np.ndarray, x: np.ndarray) -> None:
        self.ids, self.weight, self.x = ids, weight, x
        self.x32 = x.astype(np.float32)
        chain, cover = build_nets(x)
        n = len(ids)
        self.centres = [*chain, np.arange(n)]
        self.radii = [*cover, np.zeros(n, np.float32)]
        self.nodes = [np.unique(c) for c in self.centres]
        self.children = []
        for above, below in zip(self.centres, self.nodes[1:], strict=False):
            parent = above[below]
            order = np.argsort(parent, kind="stable")
            start = np.searchsorted(parent[order], np.arange(n))
            count = np.bincount(parent, minlength=n)
            self.children.append((below[order], start, count))

    def members(self, level: int, node: int) -> np.ndarray:
        return np.flatnonzero(self.centres[level] == node)


def _opened(tree: _Tree, level: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(index into nodes, child) for every child of every node."""
    below, start, count = tree.children[level]
    n = count[nodes]
    each = np.repeat(np.arange(len(nodes)), n)
    return each, below[start[nodes][each] + np.arange(len(each)) - np.repeat(np.cumsum(n) - n, n)]


class _Links:
    """Weights linked to each point of two trees, and local components of the links."""

    def __init__(self, a: _Tree, b: _Tree, same: bool) -> None:
        self.same, self.shift = same, 0 if same else len(a.ids)
        self.ids = a.ids if same else np.concatenate([a.ids, b.ids])
        self.weight = a.weight if same else np.concatenate([a.weight, b.weight])
        self.n = np.zeros(len(self.ids), np.int64)
        self.edges: list[tuple[np.ndarray, np.ndarray]] = []

    def pairs(self, i: np.ndarray, j: np.ndarray) -> None:
        j = j + self.shift
        np.add.at(self.n, i, self.weight[j])
        np.add.at(self.n, j, self.weight[i])
        self.edges.append((i, j))

    def whole(self, i: np.ndarray, j: np.ndarray | None) -> None:
        """Every pair of i with j, or (j None) every pair within i, without listing them."""
        if j is None:
            self.n[i] += self.weight[i].sum() - self.weight[i]
            self.edges.append((i, np.full(len(i), i[0])))
            return
        j = j + self.shift
        self.n[i] += self.weight[j].sum()
        self.n[j] += self.weight[i].sum()
        both = np.concatenate([i, j])
        self.edges.append((both, np.full(len(both), i[0])))

    def rows(self) -> pd.DataFrame:
        label = self.ids.copy()
        if self.edges:
            i, j = (np.concatenate(x) for x in zip(*self.edges, strict=True))
            while True:
                before = label.copy()
                least = np.minimum(label[i], label[j])
                np.minimum.at(label, i, least)
                np.minimum.at(label, j, least)
                if (label == before).all():
                    break
        some = self.n > 0
        return pd.DataFrame({"vec_id": self.ids[some], "n": self.n[some], "root": label[some]})


def traverse(a: _Tree, b: _Tree, same: bool, cosine: float) -> pd.DataFrame:
    """Links between two blocks, or (same) within one."""
    limit, slack = np.sqrt(2 - 2 * cosine), margin(a.x.shape[1])
    links = _Links(a, b, same)
    last = len(RADII)
    for at in range(0, len(a.nodes[0]), STRIP):
        top = a.nodes[0][at : at + STRIP]
        gap = np.sqrt(np.maximum(0, 2 - 2 * (a.x32[top] @ b.x32[b.nodes[0]].T)))
        near = gap <= limit + slack + a.radii[0][top][:, None] + b.radii[0][b.nodes[0]][None, :]
        i, j = np.nonzero(near)
        i, j = top[i], b.nodes[0][j]
        if same:
            i, j = i[i <= j], j[i <= j]
        for level in range(last + 1):
            if not len(i):
                break
            if level == last:
                step = 1 << 18
                for s in range(0, len(i), step):
                    u, v = i[s : s + step], j[s : s + step]
                    if same:
                        u, v = u[u != v], v[u != v]
                    ok = np.einsum("ij,ij->i", a.x[u], b.x[v]) >= cosine
                    links.pairs(u[ok], v[ok])
                break
            gap = np.sqrt(np.maximum(0, 2 - 2 * np.einsum("ij,ij->i", a.x32[i], b.x32[j])))
            reach = a.radii[level][i] + b.radii[level][j]
            alone = same & (i == j)
            gap[alone] = 0
            keep = gap <= limit + slack + reach
            sure = keep & (gap + reach <= limit - slack) & (reach > 0)
            for u, v in zip(i[sure].tolist(), j[sure].tolist(), strict=True):
                links.whole(a.members(level, u), None if same and u == v else b.members(level, v))
            i, j = i[keep & ~sure], j[keep & ~sure]
            each, ci = _opened(a, level, i)
            again, cj = _opened(b, level, j[each])
            ci, cj, own = ci[again], cj, (i == j)[each][again] & same
            i, j = ci[~own | (ci <= cj)], cj[~own | (ci <= cj)]
    return links.rows()


@dataclass
class Dealing:
    """How the vectors of one length are dealt: centres, the groups of each cell (several where it is large), covering radii."""

    centres: np.ndarray
    groups: list[list[int]]
    radii: np.ndarray | None = None

    @property
    def n_groups(self) -> int:
        return 1 + max(g[-1] for g in self.groups)

    def cells(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(distances to all centres, nearest)."""
        gap = np.sqrt(np.maximum(0, 2 - 2 * (x @ self.centres.T)))
        return gap, gap.argmin(axis=1)

    def visits(self, x: np.ndarray, cosine: float) -> tuple[np.ndarray, np.ndarray]:
        """(home cell, points by groups: may a point have links there?)."""
        limit, slack = np.sqrt(2 - 2 * cosine), margin(x.shape[1])
        gap, home = self.cells(x)
        own = gap[np.arange(len(x)), home][:, None]
        apart = np.sqrt(np.maximum(0, 2 - 2 * (self.centres[home] @ self.centres.T)))
        # distance to the plane half way between the centres; every point of the other cell is behind it
        plane = np.where(apart > slack, (gap**2 - own**2) / np.maximum(2 * apart, slack), 0.0)
        open_ = (gap <= limit + self.radii + slack) & (plane <= limit + slack)
        at = np.zeros((len(self.centres), self.n_groups), np.float32)
        for c, groups in enumerate(self.groups):
            at[c, groups] = 1
        return home, open_.astype(np.float32) @ at > 0


def deal(sample: np.ndarray, total: int, width: int) -> Dealing:
    """Centres and groups for about ``total`` vectors of the sample's length."""
    gap = np.sqrt(np.maximum(0, 2 - 2 * (sample @ sample.T)))
    centres = sample[np.unique(_net(gap <= RADII[0]))[:CENTRES]]
    n = max(1, -(-total * sample.shape[1] * 8 // GROUP_BYTES), min(int(np.ceil(np.sqrt(2 * width))), total // 256))
    share = np.bincount((sample @ centres.T).argmax(axis=1), minlength=len(centres)) / len(sample)
    # cells in a chain of near neighbours, cut into runs of equal share
    apart, order = centres @ centres.T, [0]
    left = np.ones(len(centres), bool)
    left[0] = False
    while left.any():
        order.append(int(np.where(left, apart[order[-1]], -np.inf).argmax()))
        left[order[-1]] = False
    end = np.cumsum(share[order])
    groups: list[list[int]] = [[] for _ in centres]
    for c, a, b in zip(order, end - share[order], end, strict=True):
        first = min(n - 1, int(a * n + 1e-9))
        groups[c] = list(range(first, max(first, min(n - 1, int(np.ceil(b * n - 1e-9)) - 1)) + 1))
    return Dealing(centres, groups)


def _vectors(batch: pa.RecordBatch | pa.Table, dims: int) -> np.ndarray:
    column = batch.column("vector")
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(column.flatten()).reshape(-1, dims)


def _by_length(batch: pa.RecordBatch) -> Iterator[tuple[int, pa.RecordBatch]]:
    for d in np.unique(batch.column("d").to_numpy()).tolist():
        yield d, batch.filter(pa.array(batch.column("d").to_numpy() == d))


def _covering(dealt: dict[int, Dealing]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The largest distance from each centre in a batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for d, part in _by_length(batch):
                if d in dealt:
                    gap, home = dealt[d].cells(_vectors(part, d))
                    cells = np.unique(home)
                    far = np.zeros(len(dealt[d].centres))
                    np.maximum.at(far, home, gap[np.arange(len(home)), home])
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cells), d, np.int32)), pa.array(cells.astype(np.int32)), pa.array(far[cells])], ["d", "cell", "radius"])

    return run


def _sending(dealt: dict[int, Dealing], cosine: float) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A row for each pair of groups that a point takes part in."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, STRIP):
                for d, part in _by_length(whole.slice(at, STRIP)):
                    ids = part.column("vec_id").to_numpy()
                    if d in dealt:
                        cell, visits = dealt[d].visits(_vectors(part, d), cosine)
                        home = np.array([(g := dealt[d].groups[c])[i % len(g)] for c, i in zip(cell.tolist(), ids.tolist(), strict=True)])
                        visits[np.arange(len(ids)), home] = True
                    else:  # a length that the sample didn't meet: few vectors
                        cell = home = np.zeros(len(ids), int)
                        visits = np.ones((len(ids), 1), bool)
                    i, other = np.nonzero(visits)
                    sent = part.take(pa.array(i))
                    number = lambda x: pa.array(x.astype(np.int32))
                    columns = [number(np.full(len(i), d)), number(np.minimum(home[i], other)), number(np.maximum(home[i], other)), number(home[i]), number(cell[i])]
                    yield pa.RecordBatch.from_arrays([*columns, *(sent.column(c) for c in ("vec_id", "weight", "vector"))], [c.split()[0] for c in _SENT.split(", ")])

    return run


def _blocks(table: pa.Table, home: int) -> list[_Tree]:
    """Trees of the points of one group, cell by cell."""
    part = table.filter(pa.array(table.column("home").to_numpy() == home))
    if not part.num_rows:
        return []
    x = _vectors(part, part.column("d")[0].as_py())
    ids, weight, cell = (part.column(c).to_numpy() for c in ("vec_id", "weight", "cell"))
    order = np.lexsort((ids, cell))
    return [_Tree(ids[at], weight[at], x[at]) for at in np.split(order, range(BLOCK_MOST, len(order), BLOCK_MOST))]


def _task(cosine: float) -> Callable[[pa.Table], pa.Table]:
    def run(table: pa.Table) -> pa.Table:
        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        low = _blocks(table, lo)
        high = low if lo == hi else _blocks(table, hi)
        found = [traverse(a, b, a is b, cosine) for i, a in enumerate(low) for b in (high[i:] if lo == hi else high)]
        rows = pd.concat([*found, pd.DataFrame({c: pd.Series(dtype="int64") for c in ("vec_id", "n", "root")})])
        rows = rows.groupby(["vec_id", "root"], as_index=False)["n"].sum()
        return pa.table({c: pa.array(rows[c].to_numpy(), pa.int64()) for c in ("vec_id", "n", "root")})

    return run


def _dealings(points: DataFrame, width: int, cosine: float) -> dict[int, Dealing]:
    """For every length of the sample its dealing, with covering radii over all points."""
    sample = points.select("d", "vector", F.xxhash64(F.lit(10), "vec_id").alias("h"), "vec_id").orderBy("h", "vec_id").limit(SAMPLE).collect()
    number = points.count()
    by: dict[int, list] = {}
    for r in sample:
        by.setdefault(r["d"], []).append(r["vector"])
    dealt = {d: deal(np.array(rows), -(-number * len(rows) // len(sample)), width) for d, rows in by.items()}
    radii = points.mapInArrow(_covering(dealt), "d int, cell int, radius double").groupBy("d", "cell").agg(F.max("radius").alias("radius")).collect()
    for d, x in dealt.items():
        x.radii = np.full(len(x.centres), -np.inf)  # a cell without points is never visited
        for r in radii:
            if r["d"] == d:
                x.radii[r["cell"]] = r["radius"]
    return dealt


def embedding_near_duplicates(vectors: DataFrame, cosine: float = 0.9, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """One row per vector: ``vec_id, n_links, component_id, kept``."""
    spark = vectors.sparkSession
    raw = F.col(vector_col).cast("array<double>")
    rows = vectors.select(F.col(id_col).cast("bigint").alias("vec_id"), raw.alias("v"))
    length = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, c: s + c * c))
    ok = F.col("v").isNotNull() & F.col("vec_id").isNotNull() & F.forall("v", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf")))
    rows = rows.withColumn("len", F.when(ok, length)).withColumn("unit", F.when((F.col("len") > 0) & (F.col("len") < float("inf")), F.transform("v", lambda c: c / F.col("len"))))
    marked = cut(rows.select("vec_id", "unit", F.xxhash64("unit").alias("h1"), F.hash("unit").alias("h2"), F.coalesce(F.size("unit"), F.lit(-1)).alias("d")))
    live = marked.filter("unit is not null")
    points = cut(live.groupBy("h1", "h2", "d").agg(F.min("vec_id").alias("vec_id"), F.count("*").alias("weight"), F.first("unit").alias("vector")))
    dealt = _dealings(points, int(spark.conf.get("spark.sql.shuffle.partitions")), cosine)
    sent = points.select("d", "vec_id", "weight", "vector").mapInArrow(_sending(dealt, cosine), _SENT)
    found = cut(sent.groupBy("d", "lo", "hi").applyInArrow(_task(cosine), _FOUND))
    counts = found.groupBy("vec_id").agg(F.sum("n").alias("n"))
    tree = components(found.select(F.col("vec_id").alias("a"), F.col("root").alias("b")))
    named = points.select("h1", "h2", "d", F.col("vec_id").alias("rep"), "weight")
    named = named.join(counts.withColumnRenamed("vec_id", "rep"), "rep", "left").join(tree.withColumnRenamed("v", "rep"), "rep", "left")
    named = cut(named.select("h1", "h2", "d", (F.coalesce("n", F.lit(0)) + F.col("weight") - 1).cast("bigint").alias("n_links"), F.coalesce("component", "rep").alias("component_id"), "weight"))
    out = look_up(live.drop("unit"), named, ["h1", "h2", "d"], "weight").select("vec_id", "n_links", "component_id")
    alone = marked.filter("unit is null").select("vec_id", F.lit(0).cast("bigint").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
