"""Line dedup on content-defined chunks of lines, with DataFrame functions only.

Lines are hashed, and a rolling hash over the last ``WINDOW`` line hashes is taken after each line;
a chunk ends where its last bits are zero, so a chunk depends on its own lines and not on where it
stands.  Chunks come in two grains: every ``coarse``-th place is an end on the average, and, as a
passage of a few lines seldom holds a whole chunk of that kind, the finest grain, where every line
is an end and a chunk is the shortest run of several lines: two neighbouring lines that are not
blank, with the blank ones between.  Chunks of at least two lines that are not blank are counted
over the whole corpus, and the lines of every occurrence but the first are removed, from the
chunk's first to its last line that is not blank.

A chunk's key is the digest of its line digests.  Equal digests are held to mean equal bytes only
after the bytes of all lines with one digest have been compared; a chunk with a line whose digest
stands for different bytes is left alone.

Shuffles: 64-bit hashes of chunks (pre-aggregated), narrow rows of repeated chunks, distinct lines
for the comparison of bytes, and the documents with their lists of removed lines once.

Defined results: a null text stays null with no lines; an empty text has one empty line; order
of "first" is by id (null first), then key of the row, then place; of rows equal in id and text the
first is judged like any other and the rest lose all their chunks; a document may lose all its lines
and is then returned with an empty text; columns of any name are carried on, and a name of the
report that is taken gets underscores in front.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, look_up

#: Lines under the rolling hash.
WINDOW = 3
#: A coarse chunk ends at one place in so many (a power of two).
COARSE = 4

_SHIFTED = " ^ ".join(f"shiftright(if(i > {k}, ld_hash[i - {k + 1}], 0L), {k})" for k in range(WINDOW))
_FULL = "filter(sequence(c.first, c.end - 1), i -> trim(ld_lines[i]) != '')"
_DIGEST = "unhex(md5(array_join(slice(ld_md5, {0} + 1, {1} - {0}), '')))"


def _fenced(frame: DataFrame, name: str, expression: str) -> DataFrame:
    """Adds a column behind a one-element explosion: a filter or projection above must not copy its expression into a function over lines."""
    return frame.select("*", F.expr(f"explode_outer(array({expression}))").alias(name))


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(ld_c0, ld_c1, ..: all columns under names that meet no other; ld_id, ld_text, and the row's 128-bit key ld_k1, ld_k2)."""
    own = docs.toDF(*(f"ld_c{i}" for i in range(len(docs.columns))))
    at = lambda c: F.col(f"ld_c{docs.columns.index(c)}")
    rows = own.select("*", at(id_col).cast("string").alias("ld_name"), at(id_col).alias("ld_id"), at(text_col).cast("string").alias("ld_text"))
    return rows.withColumns({"ld_k1": F.xxhash64("ld_name", "ld_text"), "ld_k2": F.xxhash64(F.lit(1), "ld_text", "ld_name")}).drop("ld_name")


def _hashed(rows: DataFrame) -> DataFrame:
    """Adds ``ld_lines``, their digests ``ld_md5``, and ``ld_full``: numbers of the lines that are not blank."""
    rows = _fenced(rows, "ld_lines", "split(ld_text, '\n', -1)")
    rows = _fenced(rows, "ld_md5", "transform(ld_lines, x -> md5(x))")
    return _fenced(rows, "ld_full", "filter(sequence(0, size(ld_lines) - 1), i -> trim(ld_lines[i]) != '')")


def _coarse(rows: DataFrame, coarse: int) -> DataFrame:
    """Adds ``ld_chunks``: array of (first line, line after the last) cut where the rolling hash says so."""
    rows = _fenced(rows, "ld_hash", "transform(ld_md5, x -> cast(conv(substr(x, 1, 15), 16, 10) as bigint))")
    rows = _fenced(rows, "ld_ends", f"filter(sequence(1, size(ld_lines)), i -> i = size(ld_lines) or (({_SHIFTED}) & {coarse - 1}L) = 0)").drop("ld_hash")
    return _fenced(rows, "ld_chunks", "zip_with(concat(array(0), slice(ld_ends, 1, size(ld_ends) - 1)), ld_ends, (s, e) -> named_struct('first', s, 'end', e))").drop("ld_ends")


def _units(rows: DataFrame, coarse: int, least_lines: int, finest: bool) -> DataFrame:
    """(ld_k1, ld_k2, ld_id, fine, first, end, digest): a row for each chunk of either grain, spans trimmed to lines that are not blank."""
    cut_up = _coarse(_hashed(rows.select("ld_k1", "ld_k2", "ld_id", "ld_text")), coarse)
    large = f"filter(transform(ld_chunks, c -> named_struct('full', {_FULL}, 'first', c.first, 'end', c.end)), c -> size(c.full) >= {least_lines})"
    large = f"transform({large}, c -> named_struct('fine', false, 'first', c.full[0], 'end', element_at(c.full, -1) + 1, 'digest', {_DIGEST.format('c.first', 'c.end')}))"
    n = "greatest(size(ld_full) - {0}, 0)".format(least_lines - 1)
    small = f"zip_with(slice(ld_full, 1, {n}), slice(ld_full, {least_lines}, {n}), (s, e) -> named_struct('fine', true, 'first', s, 'end', e + 1, 'digest', {_DIGEST.format('s', '(e + 1)')}))"
    return cut_up.select("ld_k1", "ld_k2", "ld_id", F.explode(F.expr(f"concat({large}, {small})" if finest else large)).alias("u")).select("ld_k1", "ld_k2", "ld_id", "u.*")


def repeated_chunks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least_lines: int = 2, coarse: int = COARSE, finest: bool = True) -> DataFrame:
    """``ld_k1, ld_k2, ld_gone, ld_removed``: for every document that loses something, the numbers of its removed lines, and how many coarse chunks go."""
    rows = _keyed(docs, id_col, text_col).filter("ld_text is not null")
    units = _units(rows, coarse, least_lines, finest).withColumn("h", F.xxhash64("fine", "digest"))
    twice = units.groupBy("h").agg(F.count("*").alias("n")).filter("n > 1").select("h")
    again = cut(units.join(twice, "h").drop("h"))
    place = F.struct("ld_id", "ld_k1", "ld_k2", "first")
    # rows equal in id and text are one place: a chunk that only they hold is not repeated here
    first = again.groupBy("fine", "digest").agg(F.min(place).alias("stays"), F.max(place).alias("last"), F.count("*").alias("copies"))
    first = cut(first.filter("not (stays.ld_k1 = last.ld_k1 and stays.ld_k2 = last.ld_k2 and stays.first = last.first)").drop("last"))
    gone = look_up(again, first, ["fine", "digest"]).filter("not (ld_k1 = stays.ld_k1 and ld_k2 = stays.ld_k2 and first = stays.first)")
    spans = gone.groupBy("ld_k1", "ld_k2").agg(F.collect_set(F.struct("first", "end", "fine")).alias("spans"))
    lines = "array_distinct(flatten(transform(spans, s -> sequence(s.first, s.end - 1))))"
    found = spans.select("ld_k1", "ld_k2", F.expr(lines).alias("ld_gone"), F.expr("size(filter(spans, s -> not s.fine))").alias("ld_removed"))
    return cut(_without_clashes(found, rows, _clashes(rows)))


def _clashes(rows: DataFrame) -> DataFrame:
    """Digests that stand for lines of different bytes: none in practice."""
    lines = rows.select(F.explode(F.split("ld_text", "\n", -1)).alias("line")).filter("trim(line) != ''").select(F.unhex(F.md5("line")).alias("digest"), "line")
    return cut(lines.distinct().groupBy("digest").agg(F.count("*").alias("n")).filter("n > 1").select("digest"))


def _without_clashes(found: DataFrame, rows: DataFrame, clashes: DataFrame) -> DataFrame:
    """Leaves the documents alone that hold a line of such a digest."""
    if not clashes.limit(1).count():
        return found
    lines = rows.select("ld_k1", "ld_k2", F.explode(F.split("ld_text", "\n", -1)).alias("line")).select("ld_k1", "ld_k2", F.unhex(F.md5("line")).alias("digest"))
    return found.join(lines.join(clashes, "digest", "left_semi").select("ld_k1", "ld_k2").distinct(), ["ld_k1", "ld_k2"], "left_anti")


def _later_copies(marked: DataFrame, rows: DataFrame) -> DataFrame:
    """Of rows equal in id and text, marks all but one (``ld_later``)."""
    repeated = cut(rows.filter("ld_text is not null").groupBy("ld_k1", "ld_k2").agg(F.count("*").alias("n")).filter("n > 1").select("ld_k1", "ld_k2"))
    if not repeated.limit(1).count():
        return marked.withColumn("ld_later", F.lit(False))
    keys = ["ld_k1", "ld_k2"]
    number = F.row_number().over(Window.partitionBy(*keys).orderBy(*keys))
    return marked.join(repeated, keys, "left_anti").withColumn("ld_later", F.lit(False)).unionByName(marked.join(repeated, keys, "left_semi").withColumn("ld_later", number > 1))


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least_lines: int = 2, coarse: int = COARSE, finest: bool = True) -> DataFrame:
    """The documents with the lines of repeated chunks cut out of ``text_col``, and ``ld_lines, ld_chunks, ld_removed, ld_removed_lines``.

    ``ld_chunks`` and ``ld_removed`` count coarse chunks.  ``finest=False`` compares coarse chunks only: fewer rows, but
    short passages that hold no whole chunk stay.
    """
    rows = _keyed(docs, id_col, text_col)
    marked = rows.drop("ld_text").join(repeated_chunks(docs, id_col, text_col, least_lines, coarse, finest), ["ld_k1", "ld_k2"], "left")
    marked = _later_copies(marked, rows).withColumn("ld_text", F.col(f"ld_c{docs.columns.index(text_col)}").cast("string"))
    whole = _coarse(_hashed(marked), coarse)
    # a later copy loses whatever several lines of it can be in a chunk
    whole = _fenced(whole, "ld_lost", f"if(ld_later, if(size(ld_full) >= {least_lines}, sequence(ld_full[0], element_at(ld_full, -1)), cast(array() as array<int>)), ld_gone)")
    kept = F.expr("array_join(transform(array_except(sequence(0, size(ld_lines) - 1), ld_lost), i -> ld_lines[i]), '\n')")
    full_chunks = F.expr(f"size(filter(ld_chunks, c -> size({_FULL}) >= {least_lines}))")
    out = [F.when(F.col("ld_text").isNotNull() & (F.size("ld_lost") > 0), kept).otherwise(F.col("ld_text")).alias(c) if c == text_col else F.col(f"ld_c{i}").alias(c) for i, c in enumerate(docs.columns)]
    report: dict[str, Column] = {
        "ld_lines": F.coalesce(F.size("ld_lines"), F.lit(0)),
        "ld_chunks": F.coalesce(F.size("ld_chunks"), F.lit(0)),
        "ld_removed": F.when(F.col("ld_later"), full_chunks).otherwise(F.coalesce("ld_removed", F.lit(0))),
        "ld_removed_lines": F.coalesce(F.size("ld_lost"), F.lit(0)),
    }
    for name, value in report.items():
        while name in docs.columns:
            name = f"_{name}"
        out.append(F.when(F.col("ld_text").isNull(), 0).otherwise(value).cast("bigint").alias(name))
    return whole.select(*out)
