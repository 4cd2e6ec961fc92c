"""Quality classifier by co-training of two views.

The text view sees a document's content: hashed words and layout statistics of its text.  The page
view sees metadata only: language, source and the given length.  Each view has logistic models
of the labelled rows (of words, of layout, of metadata), joined by what the other view teaches it: in every round both views score
*all* unlabelled documents, each labels those it is sure of, and the counts of words and of
metadata values by these pseudo-labels, over the whole corpus, become log-odds of the other view;
also words that no labelled document holds get a weight so.  A view's parts are mixed and
calibrated on held-out labels, and the views' calibrated logits are combined by weights fitted on
the same labels.  This is done for each target (quality, toxicity); a document is accepted if it is
probably of quality and probably not toxic.

Features are computed once, in one map over the texts, and written; rounds and scores read them.
What reaches the driver is the features of at most ``LABELLED`` labelled documents (the one bounded
sample) and per round one row a hashed word and metadata value, however large the corpus is.

Defined results: a null or empty text has no words and is scored by its page view, the layout of an
empty text and the intercept; null metadata is a value of its own; an id labelled more than once counts
once (the least label), and of rows with one labelled id one text counts (the least by hash); without
labels of both classes a target is not judged (probability 1 of quality, 0 of toxicity); repeated rows
are scored each; extra columns are ignored, missing metadata columns are null.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, small_batches
from .decontamination import _WORD_BYTES
from .shingles import _word_hashes

#: Most labelled documents that are used for fitting: the least by a hash of the id.
LABELLED = 8_000
#: Hashed words; a word counts if so many labelled or pseudo-labelled documents hold it.
BITS, LEAST_DOCS = 18, 6
#: Least chi-square between a word and the label (p about 0.0005).
CHI = 12.0
#: Rounds of exchange, how sure a pseudo-label must be, and its weight.
ROUNDS, SURE, PSEUDO_WEIGHT = 2, 0.97, 0.5
#: Hashed values of language and source, and classes of length: the places of the page view.
CATEGORIES, LENGTHS = 64, 32
PLACES = 2 * CATEGORIES + LENGTHS
#: Size of a metadata value in the labelled model: small, so that a source without labels isn't judged by its intercept alone.
PAGE_SCALE = 0.1
LAYOUT = 10
TARGETS = (("quality", 1.0), ("toxic", 0.0))


def text_features(text: str | None) -> np.ndarray:
    """Distinct hashed words."""
    if not text:
        return np.empty(0, np.int32)
    words = _word_hashes(text.encode().translate(_WORD_BYTES))
    return np.unique(words >> np.uint64(64 - BITS)).astype(np.int32)


def layout_features(text: str | None) -> np.ndarray:
    """Layout statistics of the text, about unit scale."""
    raw = (text or "").encode()
    data = np.frombuffer(raw, np.uint8)
    n = max(1, len(data))
    lines = (text or "").split("\n")
    words = (text or "").split()
    w = max(1, len(words))
    symbol = ((data >= 0x21) & (data <= 0x2F) | (data >= 0x3A) & (data <= 0x40) | (data >= 0x5B) & (data <= 0x60) | (data >= 0x7B) & (data <= 0x7E)).sum()
    digit = ((data >= 0x30) & (data <= 0x39)).sum()
    capital = ((data >= 0x41) & (data <= 0x5A)).sum()
    return np.array((
        np.log1p(len(data)) / 8, np.log1p(len(lines)) / 4, np.log1p(len(data) / len(lines)) / 6, min(1.0, 8 * symbol / n), min(1.0, 8 * digit / n),
        min(1.0, 8 * capital / n), len(set(words)) / w, min(2.0, sum(map(len, words)) / w / 8), len(set(lines)) / len(lines), sum(not any(c.isalnum() for c in x) for x in words) / w * 4,
    ), np.float32)


def page_places(lang: str | None, source: str | None, length: int | None) -> np.ndarray:
    """The places of a document's metadata values."""
    each = [k * CATEGORIES + zlib.crc32(repr(v).encode()) % CATEGORIES for k, v in enumerate((lang, source))]
    return np.array([*each, 2 * CATEGORIES + (0 if length is None else min(LENGTHS - 1, 1 + max(0, int(length)).bit_length()))], np.int32)


@dataclass
class Features:
    """Rows as arrays: hashed words of all rows in a row with their edges, layouts, places of metadata, labels by target (-1: none)."""

    words: np.ndarray
    edges: np.ndarray
    layout: np.ndarray
    places: np.ndarray
    labels: np.ndarray

    def __len__(self) -> int:
        return len(self.layout)

    @property
    def rows(self) -> np.ndarray:
        """The row of each word."""
        return np.repeat(np.arange(len(self)), np.diff(self.edges))

    def take(self, at: np.ndarray) -> Features:
        parts = [self.words[self.edges[i] : self.edges[i + 1]] for i in at.tolist()]
        edges = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
        return Features(np.concatenate([np.empty(0, np.int32), *parts]), edges, self.layout[at], self.places[at], self.labels[at])

    @staticmethod
    def read(batch: pa.RecordBatch | pa.Table) -> Features:
        """From columns ``bag, layout, places`` (little-endian bytes) and ``quality, toxic``."""
        raw = [batch.column(c).to_pylist() for c in ("bag", "layout", "places")]
        joined = [np.frombuffer(b"".join(r), t) for r, t in zip(raw, ("<i4", "<f4", "<i4"), strict=True)]
        edges = np.concatenate([[0], np.cumsum([len(b) // 4 for b in raw[0]])]).astype(np.int64)
        labels = np.stack([np.array(batch.column(t).to_pylist(), np.int64) for t, _ in TARGETS], 1) if batch.num_rows else np.empty((0, len(TARGETS)), np.int64)
        return Features(joined[0], edges, joined[1].reshape(-1, LAYOUT).astype(float), joined[2].reshape(-1, 3), labels)


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _fit(forward: Callable[[np.ndarray], np.ndarray], backward: Callable[[np.ndarray], np.ndarray], size: int, y: np.ndarray, ridge: float, steps: int) -> tuple[np.ndarray, float]:
    """Logistic regression by adaptive gradient steps."""
    w, b = np.zeros(size), 0.0
    seen, seen_b = np.full(size, 1e-8), 1e-8
    for _ in range(steps):
        r = _sigmoid(forward(w) + b) - y
        g, gb = backward(r) / len(y) + ridge * w, r.mean()
        seen, seen_b = seen + g * g, seen_b + gb * gb
        w, b = w - 0.3 * g / np.sqrt(seen), b - 0.3 * gb / np.sqrt(seen_b)
    return w, float(b)


def _newton(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    """A small logistic regression; the last column of ``x`` is 1."""
    w = np.zeros(x.shape[1])
    for _ in range(30):
        p = _sigmoid(x @ w)
        h = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        w = w - np.linalg.solve(h, x.T @ (p - y) + ridge * w)
    return w


def mixed(z: list[np.ndarray], y: np.ndarray) -> np.ndarray:
    """Weights of several logits and a shift; a logit whose weight would be negative is left out and the rest fitted again."""
    use, one = list(range(len(z))), np.ones(len(y))
    while True:
        w = _newton(np.stack([*(z[i] for i in use), one], 1), y)
        if (w[: len(use)] >= 0).all():
            break
        use.remove(use[int(np.argmin(w[: len(use)]))])
    out = np.zeros(len(z) + 1)
    out[[*use, -1]] = w
    return out


@dataclass
class View:
    """Models of words or metadata and (text) of layout, log-odds from the other view's pseudo-labels, and how they are mixed (each, then a shift)."""

    weights: np.ndarray
    shift: float
    layout: tuple[np.ndarray, float] | None = None
    taught: np.ndarray | None = None
    mix: np.ndarray = field(default_factory=lambda: np.array([1.0, 0.0, 0.0, 0.0]))

    def _sums(self, x: Features, w: np.ndarray) -> np.ndarray:
        return np.bincount(x.rows, w[x.words], len(x)) if self.layout is not None else w[x.places].sum(axis=1)

    def parts(self, x: Features) -> list[np.ndarray]:
        none = np.zeros(len(x))
        layout = none if self.layout is None else x.layout @ self.layout[0] + self.layout[1]
        return [self._sums(x, self.weights) + self.shift, layout, none if self.taught is None else self._sums(x, self.taught)]

    def logit(self, x: Features) -> np.ndarray:
        return sum((w * z for w, z in zip(self.mix, self.parts(x), strict=False)), np.full(len(x), self.mix[-1]))


@dataclass
class TargetModel:
    """Both views and their combination (text, page, shift)."""

    text: View
    page: View
    joint: np.ndarray

    def probabilities(self, x: Features) -> list[np.ndarray]:
        z = [self.text.logit(x), self.page.logit(x)]
        return [_sigmoid(v) for v in (*z, self.joint[0] * z[0] + self.joint[1] * z[1] + self.joint[2])]


def _telling(by_class: np.ndarray, n: np.ndarray, least: float) -> np.ndarray:
    """Hashed words of enough documents whose presence depends on the label by a chi-square test."""
    every = by_class.sum(axis=0)
    spread = every * (n.sum() - every) * n[0] * n[1]
    chi = (by_class[1] * n[0] - by_class[0] * n[1]) ** 2 * n.sum() / np.maximum(spread, 1e-9)
    return (every >= least) & (chi >= CHI)


def counted(x: Features, y: np.ndarray, weight: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """Weights of documents by class and value, and by class: of words, and of metadata."""
    out = []
    for values, rows, size in ((x.words, x.rows, 1 << BITS), (x.places.ravel(), np.repeat(np.arange(len(x)), 3), PLACES)):
        tables = [np.bincount(values, weight[rows] * (y[rows] == c), size) for c in (0, 1)]
        out.append((np.stack(tables), np.array([weight[y == c].sum() for c in (0, 1)])))
    return out


def log_odds(by_class: np.ndarray, n: np.ndarray, only_telling: bool) -> np.ndarray:
    """Logarithm of a value's frequency in one class over that in the other; 0 for values that tell nothing."""
    rate = (by_class + 1.0) / (n[:, None] + 2.0)
    odds = np.log(rate[1] / rate[0])
    return np.where(_telling(by_class, n, LEAST_DOCS), odds, 0.0) if only_telling else np.where(by_class.sum(axis=0) > 0, odds, 0.0)


Taught = Callable[[list["TargetModel | None"]], "list[list[tuple[np.ndarray, np.ndarray]]]"]


def pseudo_counts(x: Features, target: int, model: TargetModel) -> list[tuple[np.ndarray, np.ndarray]]:
    """Counts of words by the page view's pseudo-labels, and of metadata by the text view's, of unlabelled rows."""
    free = x.take(np.flatnonzero(x.labels[:, target] < 0))
    out = []
    for k, view in enumerate((model.page, model.text)):
        p = _sigmoid(view.logit(free))
        y = np.where(p >= SURE, 1, np.where(p <= 1 - SURE, 0, -1))
        out.append(counted(free, y, (y >= 0).astype(float))[k])
    return out


def co_train(known: Features, taught_by: Taught) -> list[TargetModel | None]:
    """Models of all targets from the labelled rows and, each round, the counts that ``taught_by`` gathers from all others."""
    state = [_start(known, t) for t in range(len(TARGETS))]
    for r in range(ROUNDS + 1):
        models = [None if s is None else _model(s, known) for s in state]
        if r == ROUNDS or not any(models):
            return models
        for s, tables in zip(state, taught_by(models), strict=True):
            if s is None:
                continue
            for view, own, (by_class, n), telling in zip(s.views, s.counts, tables, (True, False), strict=True):
                if n.min() > 0:
                    view.taught = log_odds(own[0] + PSEUDO_WEIGHT * by_class, own[1] + PSEUDO_WEIGHT * n, telling)


@dataclass
class _State:
    views: tuple[View, View]
    counts: list[tuple[np.ndarray, np.ndarray]]
    check: np.ndarray
    target: int


def _start(known: Features, target: int) -> _State | None:
    """The labelled models of both views; None if a class is missing."""
    at = np.flatnonzero(known.labels[:, target] >= 0)
    y = known.labels[:, target]
    if len(np.unique(y[at])) < 2 or len(at) < 20:
        return None
    held = np.arange(len(at)) % 5 == 0
    train, check = at[~held], at[held]
    if min(len(np.unique(y[train])), len(np.unique(y[check]))) < 2:
        train = check = at
    x, own = known.take(train), y[train]
    counts = counted(x, own, np.ones(len(train)))
    keep = _telling(*counts[0], min(LEAST_DOCS, max(1, len(train) // 50)))
    size, place = int(keep.sum()), np.cumsum(keep) - 1
    some = keep[x.words]
    rows, words = x.rows[some], place[x.words[some]]
    y1 = own.astype(float)
    w, b = _fit(lambda w: np.bincount(rows, w[words], len(train)), lambda r: np.bincount(words, r[rows], size), size, y1, 1e-4, 150)
    layout = _newton(np.concatenate([x.layout, np.ones((len(train), 1))], axis=1), y1)
    wide = np.zeros(1 << BITS)
    wide[keep] = w
    flat, each = x.places.ravel(), np.repeat(np.arange(len(train)), 3)
    p, c = _fit(lambda w: PAGE_SCALE * w[x.places].sum(axis=1), lambda r: PAGE_SCALE * np.bincount(flat, r[each], PLACES), PLACES, y1, 1e-3, 400)
    return _State((View(wide, b, (layout[:-1], float(layout[-1]))), View(PAGE_SCALE * p, c)), counts, check, target)


def _model(s: _State, known: Features) -> TargetModel:
    x, y = known.take(s.check), known.labels[s.check, s.target].astype(float)
    for v in s.views:
        z, use = v.parts(x), [True, v.layout is not None, v.taught is not None, True]
        v.mix = np.zeros(4)
        v.mix[use] = mixed([part for part, some in zip(z, use, strict=False) if some], y)
    z = [v.logit(x) for v in s.views]
    return TargetModel(*s.views, mixed(z, y))


_FEATURES = "doc_id bigint, quality int, toxic int, bag binary, layout binary, places binary"
_NAMES = [c.split()[0] for c in _FEATURES.split(", ")]


def _described(batch: pa.RecordBatch, ids: pa.Array, text: list, lang: list, source: list, length: list, labels: list) -> pa.RecordBatch:
    columns = [
        [text_features(t).tobytes() for t in text], [layout_features(t).tobytes() for t in text],
        [page_places(*m).tobytes() for m in zip(lang, source, length, strict=True)],
    ]
    return pa.RecordBatch.from_arrays([ids, *labels, *(pa.array(c, pa.binary()) for c in columns)], _NAMES)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 512):
            part = batch.slice(at, 512)
            yield _described(part, part.column(0), *(part.column(i).to_pylist() for i in (1, 2, 3, 4)), [part.column(5), part.column(6)])


def _metadata(docs: DataFrame) -> list:
    given = lambda c, kind: (F.col(f"`{c}`").cast(kind) if c in docs.columns else F.lit(None).cast(kind)).alias(f"qc_{c}")
    return [given("lang", "string"), given("source", "string"), given("n_chars", "bigint")]


def featurise(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, Features]:
    """(features of every document, written; features of the labelled ones)."""
    small_batches(docs.sparkSession)
    given = labels.select(F.col("doc_id").cast("bigint").alias("h_id"), F.col("quality").cast("int").alias("quality"), F.col("toxic").cast("int").alias("toxic")).filter("h_id is not null")
    given = given.groupBy("h_id").agg(F.min("quality").alias("quality"), F.min("toxic").alias("toxic")).orderBy(F.xxhash64(F.lit(11), "h_id"), "h_id").limit(LABELLED)
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"), *_metadata(docs))
    label = lambda c: F.coalesce(F.when(F.col(c).isin(0, 1), F.col(c)), F.lit(-1)).alias(c)
    # LABELLED rows of three numbers
    joined = rows.join(F.broadcast(given), F.col("doc_id") == F.col("h_id"), "left").select("doc_id", "text", "qc_lang", "qc_source", "qc_n_chars", label("quality"), label("toxic"))
    every = cut(joined.mapInArrow(_features, _FEATURES))
    known = every.filter("quality >= 0 or toxic >= 0").groupBy("doc_id").agg(F.min_by(F.struct(*_NAMES[1:]), F.xxhash64(*_NAMES[3:])).alias("x")).select("doc_id", "x.*")
    return every, Features.read(known.orderBy(F.xxhash64(F.lit(11), "doc_id"), "doc_id").toArrow())


def _counting(models_of: Callable[[], list[TargetModel | None]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Sums of a task's pseudo-counts as rows (target, view, value or -1 for all documents, n0, n1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models, sums = models_of(), {}
        for batch in batches:
            x = Features.read(batch)
            for t, model in enumerate(models):
                if model is not None and len(x):
                    for v, (by_class, n) in enumerate(pseudo_counts(x, t, model)):
                        old = sums.get((t, v))
                        sums[t, v] = (by_class, n) if old is None else (old[0] + by_class, old[1] + n)
        for (t, v), (by_class, n) in sums.items():
            at = np.flatnonzero(by_class.sum(axis=0))
            value, pair = np.append(at, -1), np.concatenate([by_class[:, at], n[:, None]], axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(value), t, np.int32)), pa.array(np.full(len(value), v, np.int32)), pa.array(value.astype(np.int32)), pa.array(pair[0]), pa.array(pair[1])], ["target", "view", "value", "n0", "n1"])

    return run


def _gathered(every: DataFrame) -> Taught:
    """A round's counts over the whole corpus: sums a task, then a value; at most one row a hashed word or place comes back."""

    def taught_by(models: list[TargetModel | None]) -> list[list[tuple[np.ndarray, np.ndarray]]]:
        sent = every.sparkSession.sparkContext.broadcast(models)
        rows = every.mapInArrow(_counting(lambda: sent.value), "target int, view int, value int, n0 double, n1 double")
        found = rows.groupBy("target", "view", "value").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")).toArrow().to_pydict()
        out = [[(np.zeros((2, size)), np.zeros(2)) for size in (1 << BITS, PLACES)] for _ in models]
        target, view, value = (np.array(found[c], np.int64) for c in ("target", "view", "value"))
        pair = np.array([found["n0"], found["n1"]], float).reshape(2, -1)
        for t in range(len(models)):
            for v in range(2):
                own = (target == t) & (view == v)
                out[t][v][0][:, value[own & (value >= 0)]] = pair[:, own & (value >= 0)]
                out[t][v][1][:] = pair[:, own & (value < 0)].sum(axis=1)
        sent.destroy()
        return out

    return taught_by


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, list[TargetModel | None]]:
    """(features of every document, models of both targets)."""
    every, known = featurise(docs, labels, id_col, text_col)
    return every, co_train(known, _gathered(every))


_SCORES = "doc_id bigint, quality_text double, quality_page double, quality double, toxic_text double, toxic_page double, toxic double"
_SCORE_NAMES = [c.split()[0] for c in _SCORES.split(", ")]


def probabilities(x: Features, models: list[TargetModel | None]) -> list[np.ndarray]:
    """The six probabilities of every row: text view, page view and both, of each target."""
    return [p for (_, prior), m in zip(TARGETS, models, strict=True) for p in ([np.full(len(x), prior)] * 3 if m is None else m.probabilities(x))]


def _scoring(models_of: Callable[[], list[TargetModel | None]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = models_of()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), *map(pa.array, probabilities(Features.read(batch), models))], _SCORE_NAMES)

    return run


def classify(docs: DataFrame, labels: DataFrame, least_quality: float = 0.5, most_toxic: float = 0.4, **names: str) -> DataFrame:
    """One row per document: the six probabilities and ``accepted``."""
    every, models = fit(docs, labels, **names)
    sent = docs.sparkSession.sparkContext.broadcast(models)
    out = every.mapInArrow(_scoring(lambda: sent.value), _SCORES)
    return out.withColumn("accepted", (F.col("quality") >= least_quality) & (F.col("toxic") < most_toxic))


def accepted_only(docs: DataFrame, labels: DataFrame, least_quality: float = 0.5, most_toxic: float = 0.4) -> DataFrame:
    """The documents, all their columns as they were, without those rejected: the map adds its verdict to the row, no join."""
    sent = docs.sparkSession.sparkContext.broadcast(fit(docs, labels)[1])
    names = docs.columns
    given = docs.select(*(F.col(f"`{c}`") for c in names), *_metadata(docs))
    at, n = names.index("text"), len(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = sent.value
        for batch in batches:
            none = pa.array(np.full(batch.num_rows, -1, np.int32))
            x = Features.read(_described(batch, none.cast(pa.int64()), batch.column(at).to_pylist(), *(batch.column(n + i).to_pylist() for i in range(3)), [none, none]))
            p = probabilities(x, models)
            yield batch.select(list(range(n))).filter(pa.array((p[2] >= least_quality) & (p[5] < most_toxic), pa.bool_()))

    return given.mapInArrow(run, docs.schema)
