"""Token counts by heap-and-linked-list byte-pair merging, without emitting identifiers.

A word is a doubly linked list of symbols.  A heap holds every adjacent pair that has a
merge rank; the lowest rank (leftmost on ties) is popped, its two nodes are fused, and the
two new neighbour pairs are pushed.  A popped entry whose nodes have changed since is stale
and skipped.  The count is the number of initial symbols minus the number of merges.

Text is cut at ASCII blanks before anything else.  Neither the normaliser (composition,
white-space folding, per-character lower case) nor the word pattern nor a special string
reaches across such a blank, so counts of the chunks add up to the count of the text, and a
chunk seen before costs one dictionary look-up.  Caches are bounded by ``CACHE_ENTRIES``.

Defined results: null and empty texts have zero bytes and tokens; repeated rows are counted
each; columns other than the id and the text are ignored.
"""

from __future__ import annotations

import heapq
import json
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import small_batches

#: Most chunks and words whose counts one Python worker keeps; both caches restart when full.
CACHE_ENTRIES = 400_000
#: Longest chunk that is kept.
CACHE_CHARS = 48


def merge_count(symbols: list[str], rank: dict[tuple[str, str], int]) -> int:
    """Number of merges that the rank table applies to one word's symbols."""
    n = len(symbols)
    if n < 2:
        return 0
    get = rank.get
    heap = [(r, i) for i in range(n - 1) if (r := get((symbols[i], symbols[i + 1]))) is not None]
    if not heap:
        return 0
    heapq.heapify(heap)
    symbols = list(symbols)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    merges, push, pop = 0, heapq.heappush, heapq.heappop
    while heap:
        r, i = pop(heap)
        left = symbols[i]
        j = after[i]
        if left is None or j >= n or get((left, symbols[j])) != r:
            continue
        symbols[i] = fused = left + symbols[j]
        symbols[j] = None
        after[i] = k = after[j]
        merges += 1
        if k < n:
            before[k] = i
            if (r := get((fused, symbols[k]))) is not None:
                push(heap, (r, i))
        if (h := before[i]) >= 0 and (r := get((symbols[h], fused))) is not None:
            push(heap, (r, h))
    return merges


class ByteAlphabet:
    """The public printable stand-ins of the 256 byte values used by byte-level vocabularies."""

    def __init__(self) -> None:
        printable = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
        shifted = iter(range(256, 512))
        self.of = [chr(b) if b in set(printable) else chr(next(shifted)) for b in range(256)]


class WordTokenCounter:
    """Counts tokens of texts under a word-end byte-pair vocabulary file (``tokenizers`` JSON)."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        model = spec["model"]
        self.rank = {(a, b): i for i, (a, b) in enumerate(m if isinstance(m, list) else m.split(" ") for m in model["merges"])}
        self.vocab = model["vocab"]
        self.word_end = model.get("end_of_word_suffix") or ""
        self.tool = Tokenizer.from_file(path)
        specials = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.special = re.compile("|".join(map(re.escape, specials))) if specials else None
        self.ascii_words = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\sa-z0-9]+", re.ASCII)
        self.words: dict[str, int] = {}
        self.chunks: dict[str, int] = {}

    def _word(self, word: str) -> int:
        """Tokens of one pre-token, already in the byte alphabet."""
        found = self.words.get(word)
        if found is None:
            symbols = [*word[:-1], word[-1] + self.word_end] if word else []
            symbols = [s for s in symbols if s in self.vocab]
            found = len(symbols) - merge_count(symbols, self.rank)
            if len(word) <= CACHE_CHARS:
                if len(self.words) >= CACHE_ENTRIES:
                    self.words.clear()
                self.words[word] = found
        return found

    def _plain(self, text: str) -> int:
        if text.isascii() and text.isprintable():
            return sum(map(self._word, self.ascii_words.findall(text.lower())))
        normal = self.tool.normalizer.normalize_str(text)
        return sum(self._word(w) for w, _ in self.tool.pre_tokenizer.pre_tokenize_str(normal))

    def _chunk(self, chunk: str) -> int:
        parts = self.special.split(chunk) if self.special else [chunk]
        found = len(parts) - 1 + sum(self._plain(p) for p in parts if p)
        if len(chunk) <= CACHE_CHARS:
            if len(self.chunks) >= CACHE_ENTRIES:
                self.chunks.clear()
            self.chunks[chunk] = found
        return found

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        get, miss, total = self.chunks.get, self._chunk, 0
        for chunk in text.replace("\n", " ").split(" "):
            n = get(chunk)
            total += miss(chunk) if n is None else n
        return total


_COUNTERS: dict[str, WordTokenCounter] = {}


def _counter(path: str) -> WordTokenCounter:
    """One counter per Python worker and vocabulary, kept between tasks."""
    if path not in _COUNTERS:
        _COUNTERS[path] = WordTokenCounter(path)
    return _COUNTERS[path]


def _counting(path: str) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _counter(path)
        for batch in batches:
            counts, sizes = [], []
            for scalar in batch.column(1):
                text = scalar.as_py()
                counts.append(counter.count(text))
                sizes.append(len(text.encode()) if text else 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), pa.array(counts, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    return run


def count_tokens(docs: DataFrame, path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id, n_bytes, n_tokens, over_limit``; a single map stage, no shuffle."""
    rows = docs.selectExpr(f"cast(`{id_col}` as bigint) as doc_id", f"cast(`{text_col}` as string) as text")
    small_batches(docs.sparkSession)
    counted = rows.mapInArrow(_counting(path), "doc_id bigint, n_bytes bigint, n_tokens bigint")
    return counted.selectExpr("doc_id", "n_bytes", "n_tokens", f"n_tokens > {int(limit)} as over_limit")
