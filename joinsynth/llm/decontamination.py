"""Benchmark decontamination with suffix arrays of the training text.

The corpus is cut into shards of whole documents inside the map tasks.  Words are numbered by
the benchmark's vocabulary (a word outside it can be part of no match), and every shard gets a
suffix array of its word sequence by prefix doubling on tied suffixes only.  All benchmark
suffixes are then binary-searched at once: for each word of depth the interval of equal
prefixes is narrowed, which yields the longest verbatim match of every benchmark suffix, its
locations, and the occurrences of every window of ``window`` words.  No document is shuffled.

The benchmark is sent to the workers in blocks of bounded bytes (``BLOCK_BYTES``), one at a time:
the driver holds one block, and a larger benchmark becomes a chain of map steps, each of which adds
its hits to the rows that the step before has written.

Defined results: null or word-less text has no words and no hits; a benchmark item without
words is ignored, one of fewer words than the window is a window of its own; rows of one item id are
one item (all without an id, too, which counts but has no name in a digest); repeated documents
count each; with an empty benchmark no document is hit; extra columns ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, small_batches

#: Bytes of benchmark text sent to the workers at once.
BLOCK_BYTES = 16 << 20
#: Bytes of text in one suffix-array shard (a longer document is a shard of its own).
SHARD_BYTES = 4 << 20
#: Occurrences expanded at once while hits are marked.
HIT_STEP = 1 << 21

_WORD_BYTES = bytes(c + 32 if 0x41 <= c <= 0x5A else c if c >= 0x80 or 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A else 0x20 for c in range(256))


def words(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z) runs of digits, letters and non-ASCII characters, as UTF-8."""
    return text.encode().translate(_WORD_BYTES).split() if text else []


def suffix_array(ids: np.ndarray) -> np.ndarray:
    """Positions of ``ids >= 0`` sorted by the words from there to the next negative number."""
    n = len(ids)
    start = np.flatnonzero(ids >= 0)
    if not len(start):
        return start
    stops = np.flatnonzero(np.append(ids, -1) < 0)
    run = stops[np.searchsorted(stops, start)] - start  # words up to the next break
    rank = np.zeros(n + 1, np.int64)  # 0: break or end; else 1 + index of the first suffix of the tie group
    order = np.argsort(ids[start], kind="stable")
    active, runs = start[order], run[order]
    value = ids[active]
    new = np.append(True, value[1:] != value[:-1])
    head = np.flatnonzero(new)[np.cumsum(new) - 1]
    rank[active] = head + 1
    sa, depth = active.copy(), 1
    base = head  # slot of the group of each active suffix
    slot = np.arange(len(active))
    while True:
        size = np.bincount(base, minlength=len(sa))[base]
        keep = (size > 1)
        if not keep.any():
            return sa
        active, runs, base, slot = active[keep], runs[keep], base[keep], slot[keep]
        if not (runs > depth).any():
            return sa
        follow = rank[np.minimum(active + depth, n)]
        follow[runs <= depth] = 0
        order = np.argsort(base * (n + 2) + follow, kind="stable")
        active, runs, base, follow = active[order], runs[order], base[order], follow[order]
        sa[slot] = active  # slots ascend and groups keep theirs
        new = np.append(True, (base[1:] != base[:-1]) | (follow[1:] != follow[:-1]))
        base = slot[np.flatnonzero(new)[np.cumsum(new) - 1]]
        rank[active] = base + 1
        done = runs <= depth  # equal to their end: nothing can tell them apart
        group_open = np.zeros(len(sa), bool)
        group_open[base[~done]] = True
        stay = group_open[base]
        active, runs, base, slot = active[stay], runs[stay], base[stay], slot[stay]
        if not len(active):
            return sa
        depth *= 2


@dataclass
class Block:
    """A bounded part of the benchmark: items as one word-number sequence with breaks between."""

    vocabulary: dict[bytes, int]
    sequence: np.ndarray
    item_of: np.ndarray  # item number at each position of the sequence
    left: np.ndarray  # words from a position to its item's end
    length: np.ndarray  # words of each item
    names: list[str | None]


def make_block(rows: list[tuple[object, str | None]]) -> Block:
    vocabulary: dict[bytes, int] = {}
    parts, owner, left, length, names = [], [], [], [], []
    for name, text in rows:
        own = words(text)
        if not own:
            continue
        n = len(own)
        parts += [vocabulary.setdefault(w, len(vocabulary)) for w in own] + [-1]
        owner += [len(names)] * (n + 1)
        left += [*range(n, 0, -1), 0]
        length.append(n)
        names.append(None if name is None else str(name))
    as_int = lambda x: np.array(x, np.int64)
    return Block(vocabulary, as_int(parts), as_int(owner), as_int(left), as_int(length), names)


def _bound(ids: np.ndarray, sa: np.ndarray, low: np.ndarray, high: np.ndarray, depth: int, word: np.ndarray, after: bool) -> np.ndarray:
    """First slot in [low, high) whose word at ``depth`` is not below ``word`` (after: is above it)."""
    low, high = low.copy(), high.copy()
    last = len(ids) - 1
    while (open_ := low < high).any():
        mid = (low + high) >> 1
        here = ids[np.minimum(sa[np.minimum(mid, len(sa) - 1)] + depth, last)]
        up = open_ & ((here <= word) if after else (here < word))
        low = np.where(up, mid + 1, low)
        high = np.where(open_ & ~up, mid, high)
    return low


def search(ids: np.ndarray, sa: np.ndarray, block: Block, window: int) -> tuple[np.ndarray, ...]:
    """Every benchmark suffix in the shard: (longest match, its first and end slot, window starts, their first and end slots).

    Window starts are positions of the benchmark sequence where a whole window (or short item) begins and occurs.
    """
    tests = np.flatnonzero(block.left > 0)
    longest = np.zeros(len(block.sequence), np.int64)
    first, end = np.zeros_like(longest), np.zeros_like(longest)
    need = np.minimum(window, block.length[block.item_of]) if len(block.length) else longest
    hits = [(np.empty(0, np.int64),) * 3]
    low, high = np.zeros(len(tests), np.int64), np.full(len(tests), len(sa), np.int64)
    depth = 0
    while len(tests) and len(sa):
        word = block.sequence[tests + depth]
        low, high = _bound(ids, sa, low, high, depth, word, False), _bound(ids, sa, low, high, depth, word, True)
        live = low < high
        tests, low, high = tests[live], low[live], high[live]
        depth += 1
        longest[tests], first[tests], end[tests] = depth, low, high
        full = need[tests] == depth
        hits.append((tests[full], low[full], high[full]))
        go = block.left[tests] > depth
        tests, low, high = tests[go], low[go], high[go]
    return longest, first, end, *map(np.concatenate, zip(*hits, strict=True))


def scan_shard(texts: list[str | None], block: Block, window: int) -> tuple[list[int], list[np.ndarray], list[np.ndarray], np.ndarray, np.ndarray]:
    """For each document of a shard: words, hit positions, item numbers; and for each benchmark position the longest match and a document it lies in (-1: none)."""
    get = block.vocabulary.get
    counts, parts = [], []
    for text in texts:
        own = words(text)
        counts.append(len(own))
        parts.append(np.fromiter((get(w, -1) for w in own), np.int64, len(own)))
        parts.append(np.array([-1]))
    ids = np.concatenate(parts) if parts else np.empty(0, np.int64)
    starts = np.concatenate([[0], np.cumsum(np.array(counts, np.int64) + 1)])
    sa = suffix_array(ids)
    longest, first, _, at, low, high = search(ids, sa, block, window)
    where = np.full(len(longest), -1)
    some = longest > 0
    where[some] = np.searchsorted(starts, sa[first[some]], "right") - 1
    cover = np.zeros(len(ids) + 1, np.int64)
    pairs = [np.empty(0, np.int64)]
    number = high - low
    chunk = np.cumsum(number) // HIT_STEP
    for c in np.unique(chunk):
        mine = chunk == c
        n, lo = number[mine], low[mine]
        each = np.repeat(np.arange(len(n)), n)
        slots = lo[each] + np.arange(len(each)) - np.repeat(np.cumsum(n) - n, n)
        begin = sa[slots]
        item = block.item_of[at[mine]][each]
        size = np.minimum(window, block.length[item])
        np.add.at(cover, begin, 1)
        np.add.at(cover, begin + size, -1)
        doc = np.searchsorted(starts, begin, "right") - 1
        pairs.append(np.unique(doc * len(block.names) + item))
    covered = np.flatnonzero(np.cumsum(cover[:-1]) > 0)
    by_doc = np.split(covered, np.searchsorted(covered, starts[1:-1]))
    both = np.unique(np.concatenate(pairs))
    doc, item = both // max(1, len(block.names)), both % max(1, len(block.names))
    items = np.split(item, np.searchsorted(doc, np.arange(1, len(texts))))
    return counts, [p - s for p, s in zip(by_doc, starts, strict=False)], items, longest, where


def _shards(batch: pa.RecordBatch, at: int = 1) -> Iterator[pa.RecordBatch]:
    """Slices of whole rows of about SHARD_BYTES of text."""
    sizes = pc.fill_null(pc.binary_length(batch.column(at)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    cuts = np.cumsum(sizes) // SHARD_BYTES
    edges = [0, *(np.flatnonzero(np.diff(cuts)) + 1).tolist(), len(sizes)]
    for a, b in zip(edges, edges[1:], strict=False):
        if b > a:
            yield batch.slice(a, b - a)


_STEP = "doc_id {id}, text string, n_words bigint, hits array<int>, items array<string>"


def _scan(block_of: Callable[[], Block], window: int, id_type: pa.DataType) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Adds one block's hits to the rows' state."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = block_of()
        for batch in batches:
            for part in _shards(batch):
                texts = part.column(1).to_pylist()
                counts, hits, items, _, _ = scan_shard(texts, block, window)
                hits = [sorted({*(old or ()), *new.tolist()}) if old else new.tolist() for old, new in zip(part.column(3).to_pylist(), hits, strict=True)]
                items = [list({*(old or ()), *(block.names[i] for i in new)}) for old, new in zip(part.column(4).to_pylist(), items, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0).cast(id_type), part.column(1), pa.array(counts, pa.int64()), pa.array(hits, pa.list_(pa.int32())), pa.array(items, pa.list_(pa.string()))], ["doc_id", "text", "n_words", "hits", "items"])

    return run


def benchmark_blocks(benchmark: DataFrame, id_col: str = "item_id", text_col: str = "text") -> Iterator[list[tuple[object, str | None]]]:
    """The benchmark's rows in blocks of about BLOCK_BYTES, dealt by a hash of id and text."""
    rows = benchmark.select(F.col(id_col).cast("string").alias("item_id"), F.col(text_col).cast("string").alias("text")).filter("text is not null")
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text") + 16), F.lit(0))).first()[0]
    n = -(-size // BLOCK_BYTES)
    for b in range(n):
        yield [(r.item_id, r.text) for r in rows.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == b).toLocalIterator()]


def find_hits(docs: DataFrame, benchmark: DataFrame, window: int = 10, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """``doc_id, text, n_words, hits, items``: hit word positions and item ids of every document."""
    spark = docs.sparkSession
    small_batches(spark)
    id_field = docs.schema[id_col]
    state = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.lit(0).cast("bigint").alias("n_words"), F.array().cast("array<int>").alias("hits"), F.array().cast("array<string>").alias("items"))
    from pyspark.sql.pandas.types import to_arrow_type

    id_type = to_arrow_type(id_field.dataType)
    sent = None
    for rows in chain(benchmark_blocks(benchmark, item_col, item_text_col), [None]):
        if rows is None and sent is not None:
            break
        state = _written(state, sent)
        sent = spark.sparkContext.broadcast(make_block(rows or []))
        state = state.mapInArrow(_scan(lambda sent=sent: sent.value, window, id_type), _STEP.format(id=id_field.dataType.simpleString()))
    return state


def _written(state: DataFrame, sent: Broadcast | None) -> DataFrame:
    """The rows of a step, written, so that its block may go."""
    if sent is not None:
        state = cut(state)
        sent.destroy()
    return state


def decontaminate(docs: DataFrame, benchmark: DataFrame, window: int = 10, max_share: float = 0.0, **names: str) -> DataFrame:
    """The documents (``doc_id, text``) whose hit words are at most ``max_share`` of their words."""
    found = find_hits(docs, benchmark, window, **names)
    return found.filter(F.size("hits") <= F.lit(max_share) * F.col("n_words")).select("doc_id", "text")


def _clean(block_of: Callable[[], Block], window: int, at: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Rows whose text (column ``at``) has no hit of one block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = block_of()
        for batch in batches:
            for part in _shards(batch, at):
                hits = scan_shard(part.column(at).to_pylist(), block, window)[1]
                yield part.filter(pa.array([not len(h) for h in hits], pa.bool_()))

    return run


def clean_only(docs: DataFrame, benchmark: DataFrame, window: int = 10, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """The documents, with all their columns, that hold no window of the benchmark."""
    small_batches(docs.sparkSession)
    out, sent = docs, None
    for rows in benchmark_blocks(benchmark, item_col, item_text_col):
        out = _written(out, sent)
        sent = docs.sparkSession.sparkContext.broadcast(make_block(rows))
        out = out.mapInArrow(_clean(lambda sent=sent: sent.value, window, docs.columns.index(text_col)), docs.schema)
    return out


def contamination_report(docs: DataFrame, benchmark: DataFrame, window: int = 10, **names: str) -> DataFrame:
    """``doc_id, n_words, n_hit, n_items, items_sha256, contaminated``: one row per document, no shuffle."""
    found = find_hits(docs, benchmark, window, **names)
    joined = F.array_join(F.sort_array("items"), ",")
    return found.select(
        "doc_id", "n_words", F.size("hits").cast("bigint").alias("n_hit"), F.size("items").cast("bigint").alias("n_items"),
        F.sha2(joined.cast("binary"), 256).alias("items_sha256"), (F.size("hits") > 0).alias("contaminated"),
    )


def _longest(block_of: Callable[[], Block], window: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = block_of()
        best: dict[int, tuple[int, int]] = {}
        for batch in batches:
            for part in _shards(batch):
                ids = part.column(0).to_pylist()
                *_, longest, where = scan_shard(part.column(1).to_pylist(), block, window)
                for at in np.flatnonzero(longest > 0).tolist():
                    if longest[at] > best.get(at, (0, 0))[0]:
                        best[at] = (int(longest[at]), ids[where[at]])
        at = sorted(best)
        offset = [int(block.length[block.item_of[a]] - block.left[a]) for a in at]
        yield pa.RecordBatch.from_arrays([pa.array([block.names[block.item_of[a]] for a in at], pa.string()), pa.array(offset, pa.int64()), pa.array([best[a][0] for a in at], pa.int64()), pa.array([best[a][1] for a in at], pa.int64())], ["item_id", "word", "longest", "doc_id"])

    return run


def longest_matches(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """``item_id, word, longest, doc_id``: for every benchmark suffix its longest verbatim match and one document (integer id) holding it."""
    spark, out, sent = docs.sparkSession, None, None
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    for part in benchmark_blocks(benchmark, item_col, item_text_col):
        out = _written(out, sent)
        sent = spark.sparkContext.broadcast(make_block(part))
        found = rows.mapInArrow(_longest(lambda sent=sent: sent.value, 10), "item_id string, word bigint, longest bigint, doc_id bigint")
        out = found if out is None else out.unionByName(found)
    if out is None:
        return spark.createDataFrame([], "item_id string, word bigint, longest bigint, doc_id bigint")
    best = F.max(F.struct("longest", F.negative("doc_id").alias("d"))).alias("best")
    return out.groupBy("item_id", "word").agg(best).select("item_id", "word", "best.longest", F.negative("best.d").alias("doc_id"))
