"""MinHash near-dedup with tensored banding.

Only ``LEFT * LEFT_ROWS + RIGHT * RIGHT_ROWS`` minimum hashes are computed.  They form two small
collections of bundles, and every pair (left bundle, right bundle) is the key of one table, so
54 tables of 3 rows cost 24 hashes in place of 162.  At similarity 0.75 two documents meet in at least one table with probability
(1 - (1 - 0.75**2)**9) * (1 - (1 - 0.75)**6) > 0.999.

Copies (equal shingle sets) are one vertex from the start.  In every table cell each member is
compared with the cell's least member only, a linear number of pairs, confirmed on full sets;
components are taken; then only cells that still hold several components are compared pair by
pair.  Their members are dealt once a left bundle rather than once a table (a pair counts where both
bundles of a table agree).  A group beyond a block is parted by set size, as 0.75 allows sizes of
the same or the next class of ratio 4/3 only, and into members of its largest component, which need
no comparison with each other, and the rest; what is larger still goes to pairs of blocks.  Sizes and
signatures come first, and full sets are brought only for members of pairs that are left; a task
returns a spanning forest of the links that it finds.  So a link is lost only if its documents never
meet, or if fewer than ``AGREE`` of 24 hashes agree (at similarity 0.75 with probability below 1e-4),
and no cell however large meets in one task.

Documents are rows: an id on rows of different texts counts as several vertices.  Null, empty
and blank texts have no shingles and link with nothing; a null id never is a component's name
unless the row is alone; repeated rows fall into one component; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, look_up, small_batches
from .components import components
from .shingles import MinHasher, set_prints, shingle_set

#: Words of a shingle, and the similarity that makes a link, in hundredths.
WORDS, PERCENT = 5, 75
#: Bundles and hashes in a bundle of the two collections.
LEFT, LEFT_ROWS, RIGHT, RIGHT_ROWS = 9, 2, 6, 1
HASHES = LEFT * LEFT_ROWS + RIGHT * RIGHT_ROWS
#: Equal hashes of 24 from which a pair is confirmed on full sets.
AGREE = 9
#: Members of a group that one block of the second round holds, and fewer where sets are large: shingles of a block.
BLOCK, BLOCK_SHINGLES = 512, 2**21
#: Pairs of a block pair that are looked at at once.
STRIP = 2**18
#: Most ids of documents under comparison (3 MB) that are broadcast rather than joined by a shuffle.
BROADCAST_IDS = 400_000


def _describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hasher = MinHasher(HASHES)
    for batch in batches:
        for at in range(0, batch.num_rows, 512):
            part = batch.slice(at, 512)
            sets = [shingle_set(t.as_py(), WORDS) for t in part.column(1)]
            p1, p2 = set_prints(sets)
            sig = hasher.signatures(sets)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(p1), pa.array(p2), pa.array(list(sig), pa.list_(pa.int32()))], ["doc_id", "n_shingles", "p1", "p2", "sig"]
            )


def _linked(a: np.ndarray, b: np.ndarray) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= PERCENT * (len(a) + len(b) - both)


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Pairs with both texts to the pairs that are links; a text that is not the vertex's is passed over."""
    kept: dict[tuple, np.ndarray] = {}
    for batch in batches:
        rows = batch.to_pydict()
        out: list[list[int]] = [[], [], [], []]
        for x1, x2, y1, y2, tx, ty in zip(*(rows[c] for c in ("x1", "x2", "y1", "y2", "tx", "ty")), strict=True):
            pair = []
            for v, text in (((x1, x2), tx), ((y1, y2), ty)):
                own = kept.get(v)
                if own is None:
                    own = shingle_set(text, WORDS)
                    p1, p2 = set_prints([own])
                    if (p1[0], p2[0]) != v:
                        break
                    if len(kept) > 256:
                        kept.clear()
                    kept[v] = own
                pair.append(own)
            if len(pair) == 2 and _linked(*pair):
                for column, v in zip(out, (x1, x2, y1, y2), strict=True):
                    column.append(v)
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], ["x1", "x2", "y1", "y2"])


_PAIR = "x1 bigint, x2 bigint, y1 bigint, y2 bigint"


def _close(n: str, m: str) -> str:
    return f"100 * least({n}, {m}) >= {PERCENT} * greatest({n}, {m})"


def _open_pairs(rows: dict, first: int, last: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of one block pair that may be links of different components: by sizes, tables and signatures.

    A pair meets in several groups; it counts in that of its first common left bundle.
    """
    n, sig, comp, slot = (rows[c][first:last] for c in ("n", "sig", "comp", "slot"))
    same = rows["lo"][first] == rows["hi"][first]
    left = np.arange(last - first) if same else np.flatnonzero(slot == rows["lo"][first])
    right = left if same else np.flatnonzero(slot == rows["hi"][first])
    at = LEFT * LEFT_ROWS
    found = [(np.empty(0, np.int64), np.empty(0, np.int64))]
    step = max(1, STRIP // max(1, len(right)))
    for k in range(0, len(left), step):
        part = left[k : k + step]
        ok = (comp[part][:, None] != comp[right]) & (100 * np.minimum(n[part][:, None], n[right]) >= PERCENT * np.maximum(n[part][:, None], n[right]))
        if same:
            ok &= part[:, None] < right
        i, j = np.nonzero(ok)
        i, j = part[i], right[j]
        # a right bundle of one hash or several: does any agree?
        ok = (sig[i, at:] == sig[j, at:]).reshape(len(i), RIGHT, RIGHT_ROWS).all(axis=2).any(axis=1)
        i, j = i[ok], j[ok]
        equal = sig[i] == sig[j]
        ok = equal.sum(axis=1) >= AGREE
        i, j, equal = i[ok], j[ok], equal[ok]
        bundles = equal[:, :at].reshape(len(i), LEFT, LEFT_ROWS).all(axis=2)
        ok = bundles.any(axis=1) & (np.argmax(bundles, axis=1) == rows["bundle"][first])
        found.append((i[ok], j[ok]))
    i, j = zip(*found, strict=True)
    return np.concatenate(i), np.concatenate(j)


def _by_group(batches: Iterator[pa.RecordBatch], names: tuple[str, ...]) -> Iterator[tuple[dict, np.ndarray, np.ndarray]]:
    """Sorted rows as columns with the edges of their whole groups (gid, lo, hi)."""
    held: list[pa.RecordBatch] = []

    def columns(rows: list[pa.RecordBatch], whole: bool) -> tuple[dict, np.ndarray, np.ndarray, list[pa.RecordBatch]]:
        table = pa.Table.from_batches(rows).combine_chunks()
        col = {c: table[c].to_numpy(zero_copy_only=False) if c != "sig" else np.array(table[c].combine_chunks().flatten().to_numpy()).reshape(-1, HASHES) for c in names}
        new = np.zeros(table.num_rows, bool)
        new[0] = True
        for c in ("gid", "lo", "hi"):
            new[1:] |= col[c][1:] != col[c][:-1]
        start = np.flatnonzero(new)
        end = np.append(start[1:], table.num_rows)
        if whole:
            return col, start, end, []
        return col, start[:-1], end[:-1], table.slice(int(start[-1])).to_batches()

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            if sum(b.num_rows for b in held) >= 4096:
                col, start, end, held = columns(held, False)
                yield col, start, end
    if held:
        col, start, end, _ = columns(held, True)
        yield col, start, end


_GROUP = ("gid", "bundle", "lo", "hi", "slot", "n", "comp", "p1", "p2", "sig")


def _wanted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(gid, vertex) of every member that has such a pair in its group."""
    for col, start, end in _by_group(batches, _GROUP):
        some = np.zeros(len(col["n"]), bool)
        for a, b in zip(start.tolist(), end.tolist(), strict=True):
            i, j = _open_pairs(col, a, b)
            some[a + i] = some[a + j] = True
        yield pa.RecordBatch.from_arrays([pa.array(col[c][some]) for c in ("gid", "bundle", "p1", "p2")], ["gid", "bundle", "p1", "p2"])


def _common(sets: list[np.ndarray], i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Sizes of the common parts of pairs of sets."""
    if len(i) <= 32:
        return np.array([len(np.intersect1d(sets[a], sets[b], assume_unique=True)) for a, b in zip(i.tolist(), j.tolist(), strict=True)], np.int64)
    size = [len(s) for s in sets]
    _, number = np.unique(np.concatenate(sets), return_inverse=True)
    row = np.repeat(np.arange(len(sets)), size)
    out = np.zeros((len(sets), len(sets)), np.float32)
    for at in range(0, int(number.max()) + 1, 4096):  # a strip of the shingles at a time
        mine = (number >= at) & (number < at + 4096)
        strip = np.zeros((len(sets), 4096), np.float32)
        strip[row[mine], number[mine] - at] = 1
        out += strip @ strip.T
    return out[i, j].astype(np.int64)


def _decide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links between different components, on full sets; of those in one block pair a spanning forest."""
    for col, start, end in _by_group(batches, (*_GROUP, "shingles")):
        out: list[list[int]] = [[], [], [], []]
        for a, b in zip(start.tolist(), end.tolist(), strict=True):
            i, j = _open_pairs(col, a, b)
            if not len(i):
                continue
            used, at = np.unique(np.concatenate([i, j]), return_inverse=True)
            sets = [np.frombuffer(col["shingles"][a + u], np.uint64) for u in used.tolist()]
            i, j = at[: len(i)], at[len(i) :]
            both = _common(sets, i, j)
            size = np.array([len(s) for s in sets])
            ok = 100 * both >= PERCENT * (size[i] + size[j] - both)
            root: dict[int, int] = {}

            def find(c: int, root: dict[int, int] = root) -> int:
                while root.get(c, c) != c:
                    c = root[c]
                return c

            for u, v in zip(used[i[ok]].tolist(), used[j[ok]].tolist(), strict=True):
                x, y = find(int(col["comp"][a + u])), find(int(col["comp"][a + v]))
                if x != y:
                    root[max(x, y)] = min(x, y)
                    for column, value in zip(out, (col["p1"][a + u], col["p2"][a + u], col["p1"][a + v], col["p2"][a + v]), strict=True):
                        column.append(int(value))
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], ["x1", "x2", "y1", "y2"])


def _as_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets = [shingle_set(t.as_py(), WORDS) for t in batch.column(0)]
        p1, p2 = set_prints(sets)
        yield pa.RecordBatch.from_arrays([pa.array(p1), pa.array(p2), pa.array([s.tobytes() for s in sets], pa.binary())], ["p1", "p2", "shingles"])


def _blocked(members: DataFrame) -> DataFrame:
    """Members (gid, bundle, vertex, n, sig, comp) dealt to pairs of slots (lo, hi).

    A group within a block is one slot, met with itself.  A larger one has slots by (in the largest component,
    size class, block by hash); slots meet unless both lie in the largest component or their classes are not neighbours.
    """
    size = members.groupBy("gid", "comp").agg(F.count("*").alias("m"), F.sum("n").alias("w")).groupBy("gid").agg(F.max(F.struct("m", "comp")).alias("top"), F.sum("m").alias("all"), F.sum("w").alias("weight"))
    size = cut(size.filter("top.m < all").select("gid", F.col("top.comp").alias("top"), ((F.col("all") <= BLOCK) & (F.col("weight") <= BLOCK_SHINGLES)).alias("whole")))
    rows = members.join(size, "gid")
    kind = F.struct((F.col("comp") == F.col("top")).alias("major"), F.floor(F.log("n") / math.log(100 / PERCENT)).cast("int").alias("class"))
    alone = rows.filter("whole").select("*", F.lit(0).cast("bigint").alias("slot"), F.lit(0).cast("bigint").alias("lo"), F.lit(0).cast("bigint").alias("hi"))
    parted = rows.filter("not whole").withColumn("kind", kind)
    room = F.greatest(F.lit(1.0), F.least(F.lit(float(BLOCK)), F.lit(BLOCK_SHINGLES * PERCENT / 100) / F.pow(F.lit(100 / PERCENT), F.col("kind.class"))))
    held = cut(parted.groupBy("gid", "kind").agg(F.count("*").alias("m")).select("gid", "kind", F.ceil(F.col("m") / room).cast("bigint").alias("blocks")))
    slot = lambda kind, block: F.shiftleft(kind["major"].cast("bigint"), 60) + F.shiftleft(kind["class"].cast("bigint"), 48) + block
    other = held.select("gid", F.col("kind").alias("other"), F.col("blocks").alias("others"))
    meets = (F.col("kind") <= F.col("other")) & ~(F.col("kind.major") & F.col("other.major")) & (F.abs(F.col("kind.class") - F.col("other.class")) <= 1)
    pairs = held.join(other, "gid").filter(meets).withColumn("x", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("blocks") - 1)))
    pairs = pairs.withColumn("y", F.explode(F.sequence(F.when(F.col("kind") == F.col("other"), F.col("x")).otherwise(F.lit(0).cast("bigint")), F.col("others") - 1)))
    pairs = pairs.select("gid", slot(F.col("kind"), F.col("x")).alias("lo"), slot(F.col("other"), F.col("y")).alias("hi"))
    ends = cut(pairs.select("gid", F.explode(F.array_distinct(F.array("lo", "hi"))).alias("slot"), "lo", "hi"))
    placed = parted.join(held, ["gid", "kind"]).withColumn("slot", slot(F.col("kind"), F.pmod(F.xxhash64("p1", "p2"), F.col("blocks")))).drop("kind", "blocks")
    return alone.unionByName(placed.join(ends, ["gid", "slot"])).drop("top", "whole")


def _texts(rows: DataFrame, ids: DataFrame) -> DataFrame:
    """The documents (doc_id, text) of a distinct list of ids."""
    wanted = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    return rows.join(wanted, "doc_id", "left_semi")


def _star_links(members: DataFrame, reps: DataFrame, rows: DataFrame) -> DataFrame:
    """Pairs of a member and its cell's least member to confirmed links."""
    pairs = members.filter("x1 != y1 or x2 != y2").select("x1", "x2", "y1", "y2").distinct()
    side = lambda s: reps.select(F.col("p1").alias(f"{s}1"), F.col("p2").alias(f"{s}2"), F.col("rep").alias(f"{s}r"), F.col("n").alias(f"{s}n"), F.col("sig").alias(f"{s}s"))
    pairs = pairs.join(side("x"), ["x1", "x2"]).join(side("y"), ["y1", "y2"]).filter(_close("xn", "yn"))
    pairs = pairs.filter(f"aggregate(zip_with(xs, ys, (a, b) -> if(a = b, 1, 0)), 0, (s, v) -> s + v) >= {AGREE}")
    pairs = cut(pairs.select("x1", "x2", "y1", "y2", "xr", "yr"))
    ids = cut(pairs.select(F.col("xr").alias("doc_id")).union(pairs.select("yr")).distinct())
    texts = cut(_texts(rows, ids))
    both = pairs.join(texts.select(F.col("doc_id").alias("xr"), F.col("text").alias("tx")), "xr").join(texts.select(F.col("doc_id").alias("yr"), F.col("text").alias("ty")), "yr")
    return cut(both.select("x1", "x2", "y1", "y2", "tx", "ty").mapInArrow(_confirm, _PAIR))


def _block_links(members: DataFrame, placed: DataFrame, rows: DataFrame) -> DataFrame:
    """Links between members of one cell that lie in different components so far."""
    width = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = ("gid", "lo", "hi")
    inside = members.select("cell", "gid", "bundle", F.col("x1").alias("p1"), F.col("x2").alias("p2")).join(placed.select("p1", "p2", "comp"), ["p1", "p2"])
    open_cells = cut(inside.groupBy("cell").agg(F.min("comp").alias("c0"), F.max("comp").alias("c1")).filter("c0 != c1").select("cell"))
    grouped = cut(members.join(open_cells, "cell").select("gid", "bundle", F.col("x1").alias("p1"), F.col("x2").alias("p2")).distinct())
    info = placed.select("p1", "p2", "n", "sig", "comp")
    dealt = _blocked(grouped.join(info, ["p1", "p2"])).select(*_GROUP)
    wanted = cut(dealt.repartition(width, *order).sortWithinPartitions(*order).mapInArrow(_wanted, "gid bigint, bundle int, p1 bigint, p2 bigint").distinct())
    ids = cut(wanted.select("p1", "p2").distinct().join(placed, ["p1", "p2"]).select(F.col("rep").alias("doc_id")).distinct())
    # an id on several texts brings them all; only the vertex's own set joins
    sets = cut(_texts(rows, ids).select("text").mapInArrow(_as_sets, "p1 bigint, p2 bigint, shingles binary").dropDuplicates(["p1", "p2"]))
    again = _blocked(wanted.join(info, ["p1", "p2"])).select(*_GROUP).join(sets, ["p1", "p2"])
    return cut(again.repartition(width, *order).sortWithinPartitions(*order).mapInArrow(_decide, _PAIR))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id, n_shingles, component_id, kept``; ``component_id`` is the least id reachable by links."""
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    small_batches(docs.sparkSession)
    described = cut(rows.mapInArrow(_describe, "doc_id bigint, n_shingles bigint, p1 bigint, p2 bigint, sig array<int>"))
    live = described.filter("n_shingles > 0 and doc_id is not null")
    reps = cut(live.groupBy("p1", "p2").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("sig").alias("sig"), F.count("*").alias("copies")))

    bundle = lambda i: F.struct((i).alias("bundle"), F.xxhash64(i, *(F.element_at("sig", (i * LEFT_ROWS + r + 1).cast("int")) for r in range(LEFT_ROWS))).alias("gid"))
    left = F.explode(F.transform(F.sequence(F.lit(0), F.lit(LEFT - 1)), bundle)).alias("l")
    at = LEFT * LEFT_ROWS
    right = F.explode(F.transform(F.sequence(F.lit(0), F.lit(RIGHT - 1)), lambda j: F.xxhash64(j + 1000, *(F.element_at("sig", (j * RIGHT_ROWS + r + at + 1).cast("int")) for r in range(RIGHT_ROWS)))))
    vertex = reps.select("p1", "p2", left, "sig").select("p1", "p2", "l", right.alias("r")).select(F.xxhash64("l.gid", "r").alias("cell"), "p1", "p2", "l.bundle", "l.gid")

    cells = cut(vertex.groupBy("cell").agg(F.count("*").alias("members"), F.min(F.struct("p1", "p2")).alias("y")).filter("members > 1").select("cell", F.col("y.p1").alias("y1"), F.col("y.p2").alias("y2")))
    members = cut(vertex.join(cells, "cell").select("cell", "gid", "bundle", F.col("p1").alias("x1"), F.col("p2").alias("x2"), "y1", "y2"))

    name = reps.select("p1", "p2", "rep")
    named = lambda pairs: cut(pairs.join(name.select(F.col("p1").alias("x1"), F.col("p2").alias("x2"), F.col("rep").alias("a")), ["x1", "x2"]).join(name.select(F.col("p1").alias("y1"), F.col("p2").alias("y2"), F.col("rep").alias("b")), ["y1", "y2"]).select("a", "b"))
    edges = named(_star_links(members, reps, rows))
    tree = components(edges)
    placed = cut(reps.join(tree.select(F.col("v").alias("rep"), F.col("component").alias("comp")), "rep", "left").select("p1", "p2", "rep", "n", "sig", "copies", F.coalesce("comp", "rep").alias("comp")))
    more = named(_block_links(members, placed, rows))
    # components of components
    at = lambda c: placed.select(F.col("rep").alias(c), F.col("comp").alias(f"{c}_c"))
    merged = components(more.join(at("a"), "a").join(at("b"), "b").select(F.col("a_c").alias("a"), F.col("b_c").alias("b")))
    name = cut(placed.join(merged.select(F.col("v").alias("comp"), F.col("component").alias("whole")), "comp", "left").select("p1", "p2", F.coalesce("whole", "comp").alias("component_id"), "copies"))
    found = look_up(live, name, ["p1", "p2"]).select("doc_id", "n_shingles", "component_id")
    # rows without shingles or id are alone; they share no key with anything
    alone = described.filter("n_shingles = 0 or doc_id is null").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return found.unionByName(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))
