"""Harmonic packing of tokenised documents into fixed-capacity sequences.

A document's ids are cut into pieces of the exact class lengths capacity, capacity/2, ...,
capacity/16 and one short tail.  A piece of length in (capacity/(k+1), capacity/k] is of class k
and every bin of class k takes exactly k pieces, so bins are filled without looking at the
lengths and each worker fills its own.  Exact classes leave no padding; a tail's bin leaves at
most 1/(k+1) of it.  Tails below capacity/64 share one class that is filled until full.

The pieces of a class are dealt to as many salted groups as their number asks for; a group's
last, partly filled bins go to a second round: exact lengths are joined into powers of two
(which need no padding), tails are packed best-fit in decreasing order in small groups.

Defined results: a null or empty text is the closing id alone; repeated documents are packed
each; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, small_batches
from .token_counts import ByteAlphabet

#: Exact classes are capacity / 2**j for j up to this; a tail is shorter than the last.
HALVINGS = 4
#: Class of all pieces of at most capacity / SMALL.
SMALL = 64
#: Pieces of one class that one group packs: as even a deal as the shuffle has tasks, within these.
GROUP_LEAST, GROUP_MOST = 1_500, 200_000
#: Pieces that one group of the second round packs.
REST_GROUP = 250

_PIECE = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, class int"
_PLACED = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, class int, salt int, bin bigint, offset bigint"
# The public pattern that byte-level vocabularies of this family split text by (a fixed value).
_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


#: A longer text is looked through for runs that would overflow the fast library's pattern search or merge loop.
LONG_TEXT = 20_000
_LONG_RUN = re.compile(r"\s{10000}|\S{10000}")


class ByteLevelEncoder:
    """Ids that ``tokenizers`` gives for a byte-level vocabulary file.

    They are computed by ``tiktoken`` on the same ranks, four times as fast: the file's merges are in the order of
    its ids, so rank and id agree (checked on loading); special strings inside a text become their ids, as the file's own
    library does by default.  A text with an extremely long run of one kind of character goes to ``tokenizers`` itself.
    """

    def __init__(self, path: str) -> None:
        import tiktoken
        import tokenizers

        self.whole = tokenizers.Tokenizer.from_file(path)
        self.whole.no_truncation()
        self.whole.no_padding()
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        byte_of = {c: b for b, c in enumerate(ByteAlphabet().of)}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(byte_of[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
        merges = ["".join(m) if isinstance(m, list) else m.replace(" ", "") for m in spec["model"]["merges"]]
        order = [spec["model"]["vocab"][m] for m in merges]
        if any(a >= b for a, b in zip(order, order[1:], strict=False)):
            raise ValueError("the vocabulary's ids are not in the order of its merges")
        self.tool = tiktoken.Encoding("byte-level", pat_str=_PATTERN, mergeable_ranks=ranks, special_tokens=special)

    def encode(self, text: str | None) -> np.ndarray:
        if text and len(text) > LONG_TEXT and _LONG_RUN.search(text):
            return np.asarray(self.whole.encode(text, add_special_tokens=False).ids, "<u4")
        return np.asarray(self.tool.encode_to_numpy(text, allowed_special="all"), "<u4") if text else np.empty(0, "<u4")


_ENCODERS: dict[str, ByteLevelEncoder] = {}


def piece_lengths(n: int, capacity: int) -> list[int]:
    """Exact class lengths, longest first, then the tail."""
    out = [capacity] * (n // capacity)
    n %= capacity
    for j in range(1, HALVINGS + 1):
        if n >= capacity >> j:
            out.append(capacity >> j)
            n -= capacity >> j
    return [*out, n] if n else out


def class_of(length: int, capacity: int) -> int:
    return min(capacity // length, SMALL)


def _cutting(path: str, capacity: int, close: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _ENCODERS:
            _ENCODERS[path] = ByteLevelEncoder(path)
        encode = _ENCODERS[path].encode
        closing = np.array([close], "<u4")
        for batch in batches:
            rows: list[tuple] = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.concatenate([encode(text.as_py()), closing])
                at = 0
                for n in piece_lengths(len(ids), capacity):
                    rows.append((doc, at, n, zlib.crc32(ids[at : at + n].tobytes()), len(ids), class_of(n, capacity)))
                    at += n
            columns = list(zip(*rows, strict=True)) or [()] * 6
            yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in columns[:5]), pa.array(columns[5], pa.int32())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "class"])

    return run


def _fill(capacity: int) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """Bins of one group of one class; pieces of partly filled bins get bin -1."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["doc_id", "start"], kind="stable")
        k, length = int(group["class"].iloc[0]), group["length"].to_numpy()
        n = len(length)
        if k < SMALL:
            bins = np.arange(n) // k
            bins[n - n % k :] = -1
        else:
            bins, at, room = np.empty(n, np.int64), 0, capacity
            for i, size in enumerate(length.tolist()):
                if size > room:
                    at, room = at + 1, capacity
                bins[i], room = at, room - size
            bins[bins == at] = -1
        before = np.cumsum(length) - length
        first = np.append(True, bins[1:] != bins[:-1])
        group["bin"], group["offset"] = bins, before - before[np.flatnonzero(first)[np.cumsum(first) - 1]]
        return group

    return run


def _fill_rest(capacity: int) -> Callable[[pd.DataFrame], pd.DataFrame]:
    """Exact lengths into power-of-two totals, tails best-fit in decreasing order."""

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["length", "doc_id", "start"], ascending=[False, True, True], kind="stable")
        length = group["length"].to_numpy()
        bins, offset = np.empty(len(length), np.int64), np.zeros(len(length), np.int64)
        exact = {capacity >> j: [] for j in range(HALVINGS + 1)}
        rooms: dict[int, list[int]] = {}
        made = 0
        for i, size in enumerate(length.tolist()):
            if size in exact:
                exact[size].append(i)
                continue
            room = min((r for r in rooms if r >= size), default=None)
            if room is None:
                room, at, made = capacity, made, made + 1
            else:
                at = rooms[room].pop()
                if not rooms[room]:
                    del rooms[room]
            bins[i], offset[i] = at, capacity - room
            if room > size:
                rooms.setdefault(room - size, []).append(at)
        for size, members in exact.items():
            while members:
                take = min(capacity // size, 1 << (len(members).bit_length() - 1))
                for slot, i in enumerate(members[:take]):
                    bins[i], offset[i] = made, slot * size
                members, made = members[take:], made + 1
        group["bin"], group["offset"] = bins, offset
        return group

    return run


def pack(docs: DataFrame, path: str, capacity: int = 2048, close: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``.  ``capacity`` is a power of two of at least 128."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    small_batches(spark)
    pieces = cut(rows.mapInArrow(_cutting(path, capacity, close), _PIECE))
    held = {r["class"]: r["count"] for r in pieces.groupBy("class").count().collect()}
    width = int(spark.conf.get("spark.sql.shuffle.partitions"))
    target = min(GROUP_MOST, max(GROUP_LEAST, sum(held.values()) // (4 * width)))
    deal = F.lit(1)
    for k, n in held.items():
        deal = F.when(F.col("class") == k, -(-n // target)).otherwise(deal)
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "start"), deal).cast("int"))
    first = cut(salted.groupBy("class", "salt").applyInPandas(_fill(capacity), _PLACED))
    rest = first.filter("bin < 0").drop("bin", "offset")
    groups = max(1, rest.count() // REST_GROUP)
    rest = rest.withColumn("salt", F.pmod(F.xxhash64("doc_id", "start", "class"), F.lit(groups)).cast("int"))
    second = rest.groupBy("salt").applyInPandas(_fill_rest(capacity), _PLACED.replace("class int, salt int", "class int, salt int"))
    number = lambda kind: (F.shiftleft(F.lit(kind).cast("bigint") if isinstance(kind, int) else kind.cast("bigint"), 56) + F.shiftleft(F.col("salt").cast("bigint"), 24) + F.col("bin"))
    out = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
    whole = first.filter("bin >= 0").withColumn("sequence_id", number(F.col("class"))).select(out)
    return whole.unionByName(second.withColumn("sequence_id", number(0)).select(out))
