"""Sharding by histogram sort.

Rows are ordered by (hash of text, id).  The driver holds only candidate boundaries: in each
round one aggregate job counts the exact bytes (and rows) in every cell between neighbouring
probes, and the cells that still hold a wanted boundary are probed more finely, until every
splitter is within tolerance or its cell is one hash value.  A hash value heavier than the
tolerance (many copies of one text) is divided further by id, otherwise equal texts stay in one
shard.  Rows find their cell and their range by binary search in a sorted array of boundaries, and
are then exchanged once.  A round returns at most ``PROBES`` counts a splitter.

Defined results: a null text has no bytes (size 8) and the checksum of the empty string; a null
id sorts first; repeated rows are placed each; an empty table gives an empty result; extra
columns are ignored.  A single text larger than a shard cannot be divided and is placed whole.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import cut

#: Probes in one interval and round; intervals are at most as many as splitters.
PROBES = 256
#: A splitter may miss its target by this share of a shard.
TOLERANCE = 0.002
#: Copies of one text stay together if that costs at most this share of a shard.
GROUP_TOLERANCE = 0.01
#: Rows that one exchange range is meant to hold.
RANGE_ROWS = 500_000

_LOW, _HIGH = -(2**63), 2**63


@dataclass
class _Hunt:
    """One wanted boundary: bytes below it, the open interval, and the result."""

    target: float
    low: int = _LOW
    high: int = _HIGH
    below: int = 0
    key: int | None = None  # set once the key interval is a single value that must be divided
    found: tuple[int, int] | None = None


def _cells(low: int, high: int) -> int:
    """Width of a probe cell: a power of two, at most PROBES cells in the interval."""
    width = 1
    while (high - low + width - 1) // width > PROBES:
        width *= 2
    return width


def _located(keys: np.ndarray, ties: np.ndarray | None, of_key: np.ndarray, start: np.ndarray) -> np.ndarray:
    """For each row the number of starts (sorted by key, then tie) that are not above it; without ties by key alone."""
    if ties is None:
        return np.searchsorted(start, keys, "right")
    low, high = np.searchsorted(of_key, keys, "left"), np.searchsorted(of_key, keys, "right")
    out = low.copy()
    for first in np.unique(low[low < high]).tolist():  # rows of a key that is divided
        mine = np.flatnonzero((low == first) & (high > low))
        out[mine] += np.searchsorted(start[first : high[mine[0]]], ties[mine], "right")
    return out


def _counting(column: str, intervals: list[tuple[int | None, int, int]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Sums of sizes by interval and cell, one row each a batch."""
    of_key = np.array([k or 0 for k, _, _ in intervals], np.int64)
    low, last = (np.array(x, np.int64) for x in ([lo for _, lo, _ in intervals], [hi - 1 for _, _, hi in intervals]))
    shift = np.array([_cells(lo, hi).bit_length() - 1 for _, lo, hi in intervals], np.int64)
    keyed = intervals[0][0] is not None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, ties, size = (batch.column(c).to_numpy() for c in ("key", "tie", "size"))
            value = ties if keyed else keys
            i = _located(keys, ties if keyed else None, of_key, low) - 1
            ok = i >= 0
            ok &= (value <= last[i]) & ((of_key[i] == keys) if keyed else True)
            i, value, size = i[ok], value[ok], size[ok]
            # shifts first: the difference of two longs could overflow, that of shifted ones cannot
            cell = (value >> shift[i]) - (low[i] >> shift[i])
            both, at = np.unique(i * (2 * PROBES + 2) + cell, return_inverse=True)
            total = np.zeros(len(both), np.int64)
            np.add.at(total, at, size)
            yield pa.RecordBatch.from_arrays([pa.array(both // (2 * PROBES + 2)), pa.array(both % (2 * PROBES + 2)), pa.array(total)], ["i", "c", "bytes"])

    return run


def _count(digest: DataFrame, column: str, intervals: list[tuple[int | None, int, int]]) -> dict[tuple[int, int], int]:
    """Exact bytes in each cell of each interval (key or None, low, high; disjoint and sorted): {(interval, cell): bytes}."""
    sums = digest.select("key", "tie", "size").mapInArrow(_counting(column, intervals), "i bigint, c bigint, bytes bigint")
    return {(r.i, r.c): r.bytes for r in sums.groupBy("i", "c").agg(F.sum("bytes").alias("bytes")).collect()}


def _refine(hunts: list[_Hunt], counts: dict[tuple[int, int], int], order: dict[tuple, int], slack: float) -> None:
    """Moves every open hunt into the cell that holds its target, or ends it at a cell edge within ``slack``."""
    grouped: dict[int, list[tuple[int, int]]] = {}
    for (i, c), n in sorted(counts.items()):
        grouped.setdefault(i, []).append((c, n))
    for h in hunts:
        if h.found:
            continue
        width = _cells(h.low, h.high)
        shift = width.bit_length() - 1
        first, below, place = h.low >> shift, h.below, None
        for c, n in grouped.get(order[h.key, h.low, h.high], []):
            place = (max(h.low, (first + c) << shift), min(h.high, (first + c + 1) << shift), below, n)
            if below + n >= h.target:
                break
            below += n
        if place is None:
            h.found = (h.low, _LOW) if h.key is None else (h.key, h.low)
            continue
        low, high, below, n = place
        edge = high if below + n - h.target < h.target - below else low
        miss = min(abs(below + n - h.target), abs(h.target - below))
        if miss <= slack:
            h.found = (edge, _LOW) if h.key is None else (h.key, edge)
        h.low, h.high, h.below = low, high, below
        if not h.found and high - low == 1:
            if h.key is None:  # one hash value
                if miss <= slack * GROUP_TOLERANCE / TOLERANCE:
                    h.found = (edge, _LOW)
                else:
                    h.key, h.low, h.high = low, _LOW, _HIGH
            else:
                h.found = (h.key, edge)


def splitters(digest: DataFrame, parts: int, total: int) -> list[tuple[int, int]]:
    """``parts - 1`` boundaries (key, id): a row belongs right of one if (key, id) is not below it."""
    hunts = [_Hunt(total * j / parts) for j in range(1, parts)]
    slack = TOLERANCE * total / parts
    while open_hunts := [h for h in hunts if not h.found]:
        for column, divided in (("key", False), ("tie", True)):
            live = [h for h in open_hunts if (h.key is not None) == divided]
            if not live:
                continue
            intervals = sorted({(h.key, h.low, h.high) for h in live}, key=lambda x: (x[0] or 0, x[1]))
            counts = _count(digest, column, intervals)
            _refine(live, counts, {x: i for i, x in enumerate(intervals)}, slack)
    return [h.found for h in hunts]


def _placing(bounds: list[tuple[int, int]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Adds ``part``: the number of boundaries not above the row, by binary search."""
    real = [(k, min(t, _HIGH - 1)) for k, t in bounds if k < _HIGH]
    of_key, start = (np.array(x, np.int64) for x in ([k for k, _ in real], [t for _, t in real]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, ties = (batch.column(c).to_numpy() for c in ("key", "tie"))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(_located(keys, ties, of_key, start).astype(np.int32))], [*batch.schema.names, "part"])

    return run


def shard_by_bytes(docs: DataFrame, shards: int = 24, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, size, text_crc32, law, shard, slot, grown_shard``: shards of near-equal bytes, slots gapless from 0."""
    raw = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    digest = cut(
        docs.select(F.col(id_col).cast("bigint").alias("doc_id"), (F.octet_length(raw) + 8).cast("bigint").alias("size"), F.crc32(raw.cast("binary")).alias("text_crc32"), F.xxhash64(raw).alias("key"))
        .withColumn("tie", F.coalesce("doc_id", F.lit(_LOW)))
    )
    total, rows = digest.agg(F.coalesce(F.sum("size"), F.lit(0)), F.count("*")).first()
    finer = max(1, -(-rows // (shards * RANGE_ROWS)))
    bounds = sorted(splitters(digest, shards * finer, total)) if rows else []
    ranged = digest.mapInArrow(_placing(bounds), "doc_id bigint, size bigint, text_crc32 bigint, key bigint, tie bigint, part int")
    held = {r.part: r["count"] for r in ranged.groupBy("part").count().collect()}
    starts, at = [], 0
    for part in range(shards * finer):
        at = 0 if part % finer == 0 else at
        starts.append(at)
        at += held.get(part, 0)
    # one row a range: as many as the plan has partitions
    first = F.broadcast(docs.sparkSession.createDataFrame(list(enumerate(starts)), "part int, start bigint"))
    local = F.row_number().over(W.partitionBy("part").orderBy("key", "tie"))
    return ranged.withColumn("local", local).join(first, "part").select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.floor(F.col("part") / finer).cast("int").alias("shard"),
        (F.col("start") + F.col("local") - 1).cast("bigint").alias("slot"), F.lit(None).cast("int").alias("grown_shard"),
    )
