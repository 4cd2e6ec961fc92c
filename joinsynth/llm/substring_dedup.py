"""Exact substring dedup: every byte of a ``WINDOW``-byte string that starts twice is found.

Candidates first.  In each document the smallest hash of ``GRAM`` bytes within a window is its
anchor (winnowing: the choice depends on the window's bytes only, so equal windows have equal
anchors at equal offsets).  Window starts that share an anchor form a run, about one a
``(WINDOW - GRAM) / 2`` bytes, and one aggregate over (anchor hash: number, least and greatest
hash of the run's whole bytes) splits the runs into three: anchor unique - nothing repeats;
one run hash, several runs - every window repeats; several run hashes - the windows must be
compared.

Only those last runs, one for each distinct run hash, are suffix-sorted, in tasks dealt by
anchor.  The sort is two-stage: suffixes smaller than their successors are sorted directly, all
others are induced from them by a scan over the first-byte buckets; then common prefixes of
neighbours are computed, and windows whose neighbour shares ``WINDOW`` bytes repeat.  An anchor
with more than ``HOT`` distinct runs (a passage in very many surroundings) isn't gathered in one
task: parts of it are sorted, and what no part finds is compared over the parts by 128-bit hashes,
first of blocks of windows, then only within blocks that agree, at last of single windows.

Defined results: null is the empty text; texts shorter than the window lose nothing; strings
are judged on the input; repeated rows are copies of each other; a null id is an id like others.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, look_up, small_batches
from .shingles import POWERS, mix

_U = np.uint64
_BYTE = mix(np.arange(1, 257, dtype=_U) * _U(0x9FB21C651E98DF25))
#: Length of a string whose repetition counts; bytes of the gram that anchors it.
WINDOW, GRAM = 200, 48
#: Distinct runs of one anchor up to which they are suffix-sorted together.
HOT = 1_000
#: Bytes of text in one suffix sort.
SORT_BYTES = 4 << 20


#: Bits of a packed minimum that hold the place; longer texts are cut into overlapping parts.
_PLACE = 24


def _last_minimum(values: np.ndarray, size: int) -> np.ndarray:
    """Place of the last minimum in every run of ``size`` values (block minima from both sides).

    Value and place are packed into one number: 40 bits of hash, and the place counted backwards.
    """
    n = len(values)
    mask = _U((1 << _PLACE) - 1)
    if n > int(mask):
        half = 1 << (_PLACE - 1)
        parts = [_last_minimum(values[a : a + half + size - 1], size) + a for a in range(0, n - size + 1, half)]
        return np.concatenate(parts)
    packed = (values & ~mask) | (mask - np.arange(n, dtype=_U))
    rows = np.concatenate([packed, np.full(-n % size, np.iinfo(np.uint64).max, _U)]).reshape(-1, size)
    ahead = np.minimum.accumulate(rows, axis=1).ravel()
    behind = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
    out = n - size + 1
    least = np.minimum(behind[:out], ahead[size - 1 : size - 1 + out])
    return (mask - (least & mask)).astype(np.int64)


def runs(data: np.ndarray) -> tuple[np.ndarray, ...]:
    """(anchor hash, run hash, first window, last window) of each run of windows of one text."""
    if len(data) < WINDOW:
        return (np.empty(0, _U), np.empty(0, _U), *(np.empty(0, np.int64),) * 2)
    up, down = POWERS.to(len(data) + 1)
    prefix = np.concatenate([np.zeros(1, _U), np.cumsum(_BYTE[data] * up[: len(data)])])
    gram = mix((prefix[GRAM:] - prefix[:-GRAM]) * down[: len(data) - GRAM + 1])
    anchor = _last_minimum(gram, WINDOW - GRAM + 1)
    first = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1]))
    last = np.append(first[1:], len(anchor)) - 1
    at, end = anchor[first], last + WINDOW
    place = ((at - first) * 1024 + (last - first)).astype(_U)
    whole = mix((prefix[end] - prefix[first]) * down[first] + _U(0xA24BAED4963EE407))
    return gram[at], mix(whole + place), first, last


_RUN = "fp bigint, span bigint, key bigint, first int, last int"


def _emit_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(key, text) to the runs of every text."""
    for batch in batches:
        for part in (batch.slice(at, 256) for at in range(0, batch.num_rows, 256)):
            cols: list[list[np.ndarray]] = [[] for _ in range(5)]
            for key, text in zip(part.column(0).to_pylist(), part.column(1), strict=True):
                fp, span, first, last = runs(np.frombuffer((text.as_py() or "").encode(), np.uint8))
                for c, x in zip(cols, (fp.view(np.int64), span.view(np.int64), np.full(len(fp), key), first.astype(np.int32), last.astype(np.int32)), strict=True):
                    c.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in cols], ["fp", "span", "key", "first", "last"])


def two_stage_order(text: np.ndarray, depth: int, wanted: np.ndarray | None = None) -> np.ndarray:
    """Positions of ``text`` (bytes; the last one is least and unique) sorted by their next ``depth`` bytes.

    ``wanted`` masks the positions whose order is asked for (all, if None); those that only their
    order depends on, up to the next directly sorted one, are sorted with them.
    """
    n = len(text)
    # smaller than its successor: the first byte that differs from this one is greater
    change = np.append(text[1:] != text[:-1], True)
    where = np.where(change, np.arange(n), n - 1)
    where = np.minimum.accumulate(where[::-1])[::-1]
    follow = np.append(text, 0)[where + 1].astype(np.int16)
    direct = follow > text
    direct[n - 1] = True
    needed = np.ones(n, bool)
    if wanted is not None:
        end = np.where(direct, np.arange(n), n)  # place of the next direct one, at or after each
        end = np.minimum.accumulate(end[::-1])[::-1]
        rise = np.zeros(n + 1, np.int32)
        at = np.flatnonzero(wanted)
        np.add.at(rise, at, 1)
        np.add.at(rise, end[at] + 1, -1)
        needed = np.cumsum(rise[:n]) > 0
    padded = np.concatenate([text, np.zeros(depth + 8, np.uint8)])
    chosen = _sorted_directly(padded, np.flatnonzero(direct & needed), depth)
    induced = needed & ~direct
    first = text[chosen]
    edge = np.searchsorted(first, np.arange(257))
    waiting: list[list[np.ndarray]] = [[] for _ in range(256)]
    out = []

    def induce(found: np.ndarray, c: int) -> np.ndarray:
        """Sends the predecessors of scanned suffixes to their buckets; returns those of this bucket."""
        before = found[found > 0] - 1
        before = before[induced[before]]
        byte = text[before]
        order = np.argsort(byte, kind="stable")
        before, byte = before[order], byte[order]
        own = before[:0]
        if len(byte):
            cuts = np.flatnonzero(byte[1:] != byte[:-1]) + 1
            for part in np.split(before, cuts):
                if (b := int(text[part[0]])) == c:
                    own = part
                else:
                    waiting[b].append(part)
        return own

    for c in range(256):
        wave = np.concatenate(waiting[c]) if waiting[c] else np.empty(0, np.int64)
        waiting[c] = []
        while len(wave):
            out.append(wave)
            wave = induce(wave, c)
        part = chosen[edge[c] : edge[c + 1]]
        if len(part):
            out.append(part)
            induce(part, c)
    return np.concatenate(out)


def _sorted_directly(padded: np.ndarray, at: np.ndarray, depth: int) -> np.ndarray:
    """Positions sorted by ``depth`` bytes: eight bytes at a time, only among positions still tied."""
    eight = np.zeros(len(padded) - 7, _U)
    for b in range(8):
        eight = (eight << _U(8)) | padded[b : len(padded) - 7 + b]
    order = np.argsort(eight[at], kind="stable")
    at = at[order].copy()
    value = eight[at]
    same = np.append(False, value[1:] == value[:-1])
    for step in range(8, depth, 8):
        tied = same | np.append(same[1:], False)
        slots = np.flatnonzero(tied)
        if not len(slots):
            break
        group = np.cumsum(~same[slots])
        part = at[slots]
        value = eight[part + step]
        order = np.lexsort((value, group))
        part, value = part[order], value[order]
        at[slots] = part
        still = np.append(False, (group[1:] == group[:-1]) & (value[1:] == value[:-1]))
        same = np.zeros(len(at), bool)
        same[slots] = still
    return at


def neighbours_share(text: np.ndarray, sa: np.ndarray, depth: int) -> np.ndarray:
    """For each place of ``sa`` but the first: do it and the one before share ``depth`` bytes?"""
    padded = np.concatenate([text, np.zeros(depth + 8, np.uint8)])
    live = np.arange(1, len(sa))
    for step in range(depth):
        if not len(live):
            break
        live = live[padded[sa[live] + step] == padded[sa[live - 1] + step]]
    share = np.zeros(len(sa), bool)
    share[live] = True
    return share


def _repeating(pieces: list[bytes]) -> list[np.ndarray]:
    """For each piece the window starts that occur in another place of the pieces.

    Pieces are joined by a byte that no UTF-8 text holds; a window of a piece doesn't hold it either,
    so whatever equals the window lies within one piece too.
    """
    sizes = np.array([len(p) for p in pieces])
    starts = np.cumsum(sizes + 1) - sizes - 1
    text = np.frombuffer(b"\xff".join(pieces) + b"\xff\x00", np.uint8)
    edge = np.zeros(len(text) + 1, np.int32)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + sizes - WINDOW + 1, -1)
    wanted = np.cumsum(edge[:-1]) > 0
    sa = two_stage_order(text, WINDOW, wanted)
    sa = sa[wanted[sa]]
    share = neighbours_share(text, sa, WINDOW)
    repeat = np.zeros(len(text), bool)
    repeat[sa[share]] = True
    repeat[sa[np.append(share[1:], False)]] = True
    return [np.flatnonzero(repeat[s : s + n - WINDOW + 1]) for s, n in zip(starts.tolist(), sizes.tolist(), strict=True)]


_FOUND = "fp bigint, span bigint, gone array<int>, body binary"
_PARTS = "fp bigint, span bigint, block int, k1 bigint, k2 bigint, n int"
#: Sizes of the blocks of windows that the parts of a crowd compare, coarse to fine.
BLOCKS = (16, 4, 1)


def _anchor(body: np.ndarray) -> int:
    """Place of the anchor that all windows of a run share."""
    up, down = POWERS.to(len(body) + 1)
    prefix = np.concatenate([np.zeros(1, _U), np.cumsum(_BYTE[body] * up[: len(body)])])
    gram = mix((prefix[GRAM:] - prefix[:-GRAM]) * down[: len(body) - GRAM + 1])
    return int(_last_minimum(gram[: WINDOW - GRAM + 1], WINDOW - GRAM + 1)[0])


def _emit_blocks(size: int, parent: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(fp, span, body, gone, wanted parent blocks or null) to the blocks of ``size`` windows by the bytes that all their windows share.

    Blocks are counted backwards from the anchor, so equal windows lie in equally numbered blocks, and
    those have equal common bytes.  A block with windows not found to repeat yet has n 1; of the
    others one of each kind (equal in all their windows, not in the common bytes only) is told, with n 2.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        told: set[bytes] = set()
        for batch in batches:
            out: list[list[int]] = [[] for _ in range(6)]
            for fp, span, body, gone, wanted in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                windows, at = len(body) - WINDOW + 1, _anchor(np.frombuffer(body, np.uint8))
                known = np.zeros(windows, bool)
                known[gone] = True
                chosen = None if wanted is None else set(wanted)
                for block in range((at - windows + 1) // size, at // size + 1):
                    if chosen is not None and block * size // parent not in chosen:
                        continue
                    first, last = max(0, at - block * size - size + 1), min(windows - 1, at - block * size)
                    if first > last:
                        continue
                    shared = body[at - block * size : at - block * size - size + 1 + WINDOW]
                    h = hashlib.blake2b(shared + f"|{fp}|{block}".encode(), digest_size=16).digest()
                    done = bool(known[first : last + 1].all())
                    if done:
                        kind = h if size == 1 else hashlib.blake2b(body[first : last + WINDOW] + f"|{fp}|{block}|{at - first}|{at - last}".encode(), digest_size=16).digest()
                        if kind in told:
                            continue
                        told.add(kind)
                    for c, x in zip(out, (fp, span, block, int.from_bytes(h[:8], "little", signed=True), int.from_bytes(h[8:], "little", signed=True), 2 if done else 1), strict=True):
                        c.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32() if i in (2, 5) else pa.int64()) for i, c in enumerate(out)], ["fp", "span", "block", "k1", "k2", "n"])

    return run


def _across_parts(found: DataFrame) -> DataFrame:
    """(fp, span, gone): windows of crowds that repeat only between their parts."""
    bodies = found.filter("body is not null").select("fp", "span", "body", "gone")
    rows = bodies.withColumn("wanted", F.lit(None).cast("array<int>"))
    for size, parent in zip(BLOCKS, (0, *BLOCKS), strict=False):
        blocks = cut(rows.mapInArrow(_emit_blocks(size, parent), _PARTS))
        twice = cut(blocks.groupBy("k1", "k2").agg(F.sum("n").alias("all")).filter("all > 1").select("k1", "k2"))
        shared = blocks.join(twice, ["k1", "k2"])
        if size > 1:
            rows = bodies.join(shared.groupBy("fp", "span").agg(F.collect_set("block").alias("wanted")), ["fp", "span"])
    again = shared.filter("n = 1").groupBy("fp", "span").agg(F.collect_set("block").alias("back"))
    return bodies.join(again, ["fp", "span"]).select("fp", "span", "body", "back").mapInArrow(_as_places, "fp bigint, span bigint, gone array<int>")


def _as_places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Window numbers counted backwards from the anchor to places in the run."""
    for batch in batches:
        places = [sorted(_anchor(np.frombuffer(body, np.uint8)) - b for b in back) for body, back in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(places, pa.list_(pa.int32()))], ["fp", "span", "gone"])


def _sort_groups(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (fp, span, body, hot) in the order of their groups: suffix-sorts whole groups, as many as fit SORT_BYTES at a time."""
    rows: list[tuple[int, int, bytes, bool, int]] = []
    held = 0

    def flush() -> pa.RecordBatch:
        found = _repeating([r[2] for r in rows])
        out = [(r[0], r[1], f.astype(np.int32), r[2] if r[3] else None) for r, f in zip(rows, found, strict=True) if len(f) or r[3]]
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in out], pa.int64()), pa.array([r[1] for r in out], pa.int64()), pa.array([r[2] for r in out], pa.list_(pa.int32())), pa.array([r[3] for r in out], pa.binary())], ["fp", "span", "gone", "body"])

    for batch in batches:
        cols = batch.to_pydict()
        for row in zip(*(cols[c] for c in ("fp", "span", "body", "hot", "part")), strict=True):
            if held > SORT_BYTES and rows and (rows[-1][0], rows[-1][4]) != (row[0], row[4]):
                yield flush()
                rows, held = [], 0
            rows.append(row)
            held += len(row[2])
    if rows:
        yield flush()


def _fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, key, wanted spans) to (fp, span, body): the bytes of the wanted runs."""
    for batch in batches:
        out: tuple[list, list, list] = ([], [], [])
        for text, wanted in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            raw = (text or "").encode()
            for w in wanted:
                out[0].append(w["fp"])
                out[1].append(w["span"])
                out[2].append(raw[w["first"] : w["last"] + WINDOW])
        yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.binary())], ["fp", "span", "body"])


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, runs of repeating windows) to the digest row and the kept bytes."""
    for batch in batches:
        docs, texts, spans = (batch.column(i).to_pylist() for i in range(3))
        cols: list[list] = [[], [], [], [], []]
        for text, own in zip(texts, spans, strict=True):
            raw = (text or "").encode()
            edge = np.zeros(len(raw) + 1, np.int32)
            for s in own or ():
                if s["gone"] is None:
                    edge[s["first"]] += 1
                    edge[s["last"] + WINDOW] -= 1
                elif s["gone"]:
                    starts = np.array(s["gone"]) + s["first"]
                    np.add.at(edge, starts, 1)
                    np.add.at(edge, starts + WINDOW, -1)
            cover = np.cumsum(edge[:-1]) > 0
            left = np.frombuffer(raw, np.uint8)[~cover].tobytes()
            begun = int(np.count_nonzero(cover & ~np.append(False, cover[:-1]))) if len(raw) else 0
            for c, x in zip(cols, (len(raw), int(cover.sum()), begun, hashlib.sha256(left).hexdigest(), left), strict=True):
                c.append(x)
        yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), *(pa.array(c, pa.int64()) for c in cols[:3]), pa.array(cols[3], pa.string()), pa.array(cols[4], pa.binary())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])


def cut_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept`` (``kept``: the remaining bytes)."""
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    keyed = rows.select(F.xxhash64("doc_id", "text").alias("key"), "doc_id", "text")
    small_batches(docs.sparkSession)
    every = keyed.select("key", "text").mapInArrow(_emit_runs, _RUN)
    anchors = cut(every.groupBy("fp").agg(F.count("*").alias("n"), F.min("span").alias("s0"), F.max("span").alias("s1")).filter("n > 1").select("fp", (F.col("s0") == F.col("s1")).alias("even")))
    shared = cut(every.join(anchors, "fp"))
    mixed = shared.filter("not even")
    spans = cut(mixed.groupBy("fp", "span").agg(F.count("*").alias("n"), F.min(F.struct("key", "first", "last")).alias("at")))
    crowd = cut(spans.groupBy("fp").agg(F.count("*").alias("m")).filter(F.col("m") > HOT))

    wanted = spans.groupBy(F.col("at.key").alias("key")).agg(F.collect_list(F.struct("fp", "span", F.col("at.first").alias("first"), F.col("at.last").alias("last"))).alias("wanted"))
    # rows equal in id and text share a key: the bytes are needed once
    bodies = keyed.join(wanted, "key").select("text", "wanted").mapInArrow(_fetch, "fp bigint, span bigint, body binary").join(crowd, "fp", "left")
    parts = F.when(F.col("m").isNull(), 0).otherwise(F.pmod(F.xxhash64("span"), F.ceil(F.col("m") / HOT))).cast("int")
    bodies = bodies.select("fp", "span", "body", F.col("m").isNotNull().alias("hot"), parts.alias("part")).dropDuplicates(["fp", "part", "span"])
    width = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = cut(bodies.repartition(width, "fp", "part").sortWithinPartitions("fp", "part").mapInArrow(_sort_groups, _FOUND))
    found = found.select("fp", "span", "gone").unionByName(_across_parts(found))

    # runs that occur once lose what was found, runs that occur often (one may hold most rows) are gone as a whole
    once = spans.filter("n = 1").select("fp", "span", "n").join(found, ["fp", "span"])
    nothing = F.lit(None).cast("array<int>").alias("gone")
    told = cut(once.unionByName(spans.filter("n > 1").select("fp", "span", "n", nothing)))
    partly = look_up(mixed, told, ["fp", "span"], "n").select("key", "first", "last", "gone")
    wholly = shared.filter("even").select("key", "first", "last", nothing)
    by_doc = wholly.unionByName(partly).groupBy("key").agg(F.collect_list(F.struct("first", "last", "gone")).alias("runs"))
    return keyed.join(by_doc, "key", "left").select("doc_id", "text", "runs").mapInArrow(_digest, "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string, kept binary")
