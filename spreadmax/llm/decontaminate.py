"""Benchmark decontamination by Wu-Manber multi-pattern search.

Every window of 13 consecutive words of a benchmark item (or the whole item
where it has fewer) is a pattern: a stretch of the item's words with single
spaces. A table of shifts for hashed blocks of bytes says how far the scan may
jump; blocks that end a pattern's head select, by their hash, the few patterns
that are then compared directly. Documents are searched as the same normal
form, so an occurrence means equal consecutive words.

Patterns are places in one string of all items, kept in numpy arrays; shift
tables have a fixed number of one-byte entries (blocks that share an entry only
shorten jumps). So a worker holds about `BYTES_A_WORD` bytes for every word of
the benchmark's block, and a larger benchmark is searched in several passes.

Defined cases: a null text has no words and no hits; items without words have
no windows; an item whose id is null hits words but is not listed; repeated
items count once by id; an empty benchmark hits nothing; an empty table gives
an empty result; columns of the input keep their names and values in
`decontaminate`, and a result column of `find_contamination` whose name is
taken gets an underscore.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spreadmax.llm.common import append_columns, columns, fresh, text_bytes, words_of
from spreadmax.session import written

WINDOW = 13
#: Benchmark text that one set of tables covers (about 60 MB a worker); a larger benchmark is searched in several passes.
PASS_BYTES = 8 << 20
#: Entries of a shift table, one byte each, and buckets of its patterns.
SHIFT_BITS, BUCKET_BITS = 22, 18
#: Text, window and bucket of a word, on average.
BYTES_A_WORD = 40
#: Patterns are searched apart by length, since the shortest one bounds every jump.
LENGTH_CLASSES = (0, 6, 12, 24, 48)


def normal(words: list[bytes]) -> bytes:
    """Words with a space before, between and behind them."""
    return b" " + b" ".join(words) + b" " if words else b""


def windows_of(text: bytes, size: int = WINDOW) -> tuple[bytes, np.ndarray, np.ndarray]:
    """The normal form of a text, and where its windows begin and end there."""
    form = normal(words_of(text))
    spaces = np.flatnonzero(np.frombuffer(form, np.uint8) == 32)
    reach = min(size, len(spaces) - 1)
    if reach < 1:
        return form, np.zeros(0, np.int64), np.zeros(0, np.int64)
    return form, spaces[:-reach], spaces[reach:] + 1


class BlockShiftTable:
    """Shift and suffix tables of patterns of similar length: places in `body`."""

    def __init__(self, body: bytes, begins: np.ndarray, sizes: np.ndarray, owners: np.ndarray):
        self.body = body
        self.head = m = int(sizes.min())
        self.block = b = max(2, min(10, m // 3))
        self.jump = min(m - b + 1, 255)
        wanted = 16 * len(begins) * (m - b + 1)
        self.mask = (1 << max(8, min(SHIFT_BITS, wanted.bit_length()))) - 1
        self.few = (1 << max(4, min(BUCKET_BITS, len(begins).bit_length()))) - 1
        shift = bytearray([self.jump]) * (self.mask + 1)
        suffix = np.empty(len(begins), np.int64)
        for i, at in enumerate(begins.tolist()):
            for end in range(b, m):
                by = m - end
                h = hash(body[at + end - b : at + end]) & self.mask
                if by < shift[h]:
                    shift[h] = by
            last = hash(body[at + m - b : at + m])
            shift[last & self.mask] = 0
            suffix[i] = last & self.few
        order = np.argsort(suffix, kind="stable")
        self.shift = bytes(shift)
        self.begins, self.sizes, self.owners = begins[order], sizes[order].astype(np.int32), owners[order].astype(np.int32)
        self.bucket = np.searchsorted(suffix[order], np.arange(self.few + 2)).astype(np.int32)

    @property
    def nbytes(self) -> int:
        return len(self.shift) + sum(x.nbytes for x in (self.begins, self.sizes, self.owners, self.bucket))

    def find(self, text: bytes) -> Iterator[tuple[int, int, int]]:
        """(offset, size, owner) of all occurrences."""
        at, end, m, b = self.head, len(text), self.head, self.block
        shift, mask, few, body, bucket = self.shift, self.mask, self.few, self.body, self.bucket
        while at <= end:
            h = hash(text[at - b : at])
            by = shift[h & mask]
            if by:
                at += by
                continue
            h &= few
            for k in range(bucket[h], bucket[h + 1]):
                begin, size = int(self.begins[k]), int(self.sizes[k])
                if text.startswith(body[begin : begin + size], at - m):
                    yield at - m, size, int(self.owners[k])
            at += 1


class PatternSet:
    """The tables of all length classes over the items of one block of the benchmark."""

    def __init__(self, items: list[tuple[str | None, bytes]], window: int):
        self.names = [name for name, _ in items]
        forms, begins, sizes, owners, size = [], [], [], [], 0
        for i, (_, text) in enumerate(items):
            form, begin, end = windows_of(text, window)
            forms.append(form)
            begins.append(begin + size)
            sizes.append(end - begin)
            owners.append(np.full(len(begin), i))
            size += len(form)
        self.body = b"".join(forms)
        begins, sizes, owners = (np.concatenate([np.zeros(0, np.int64), *x]) for x in (begins, sizes, owners))
        kind = np.searchsorted(np.array(LENGTH_CLASSES), sizes, "right")
        self.tables = [BlockShiftTable(self.body, begins[own], sizes[own], owners[own]) for k in np.unique(kind) for own in [kind == k]]

    @property
    def nbytes(self) -> int:
        return len(self.body) + sum(t.nbytes for t in self.tables)

    def hits(self, words: list[bytes]) -> tuple[np.ndarray, set[int]]:
        """Which words are hit, and the items that occur."""
        mark, items = np.zeros(len(words), bool), set()
        if not words:
            return mark, items
        text = normal(words)
        spaces = None
        for t in self.tables:
            for at, size, owner in t.find(text):
                if spaces is None:
                    spaces = np.flatnonzero(np.frombuffer(text, np.uint8) == 32)
                first, last = np.searchsorted(spaces, (at, at + size - 1))
                mark[first:last] = True
                items.add(owner)
        return mark, items


_BUILT: dict[str, PatternSet] = {}


def _patterns(key: str, items, window: int) -> PatternSet:
    """One build per Python worker."""
    if key not in _BUILT:
        _BUILT.clear()
        _BUILT[key] = PatternSet(items, window)
    return _BUILT[key]


def _passes(benchmark: DataFrame, limit: int) -> Iterator[list[tuple[str | None, bytes]]]:
    rows = benchmark.select(F.col("item_id").cast("string").alias("item"), F.col("text").cast("binary").alias("text"))
    part: list[tuple[str | None, bytes]] = []
    held = 0
    for row in rows.filter("text is not null").toLocalIterator():
        part.append((row["item"], bytes(row["text"])))
        held += len(part[-1][1])
        if held >= limit:
            yield part
            part, held = [], 0
    if part:
        yield part


RESULT = [
    ("n_words", T.LongType()),
    ("n_hit", T.LongType()),
    ("n_items", T.LongType()),
    ("items_sha256", T.StringType()),
    ("contaminated", T.BooleanType()),
]


def find_contamination(
    docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, pass_bytes: int = PASS_BYTES
) -> DataFrame:
    """`docs` with n_words, n_hit, n_items, items_sha256 and contaminated."""
    return _found(docs, benchmark, fresh(docs.columns, *[n for n, _ in RESULT]), window, pass_bytes)


def _found(docs: DataFrame, benchmark: DataFrame, names: list[str], window: int, pass_bytes: int) -> DataFrame:
    """The same with given names of the result columns.

    The benchmark is the stated query set: it is read in blocks of `pass_bytes`,
    and every block is searched in all documents. One block is a single map over
    the documents. Of several, each hands on the documents that it hits and their
    marked words; these few rows meet by document.
    """
    spark = docs.sparkSession
    fields = [(n, t) for n, (_, t) in zip(names, RESULT, strict=True)]
    parts = _passes(benchmark, pass_bytes)
    block, following = next(parts, []), next(parts, None)
    if following is None:
        return append_columns(docs, ["text"], fields, _searcher(spark, block, window))
    row, marks, items = fresh([*docs.columns, *names], "row_number", "marks", "items")
    base = written(docs.withColumn(row, F.monotonically_increasing_id()), "numbered")
    hits = None
    while block is not None:
        one = base.select(row, F.col("text").cast("binary").alias("text")).mapInArrow(_marker(spark, block, window), _MARKS)
        one = written(one, "marked")
        hits = one if hits is None else hits.unionByName(one)
        block, following = following, next(parts, None)
    whole = hits.groupBy("row").applyInPandas(_joined, _MARKS).select(F.col("row").alias(row), F.col("mark").alias(marks), F.col("items").alias(items))
    return append_columns(base.join(whole, row, "left"), ["text", marks, items], fields, lambda: _summary).drop(row, marks, items)


_MARKS = "row long, mark binary, items array<string>"


def _row(n: int, hit: int, names: set[str]) -> tuple[int, int, int, str, bool]:
    digest = hashlib.sha256(",".join(sorted(names)).encode()).hexdigest()
    return n, hit, len(names), digest, hit > 0 and 20 * hit >= n


def _searcher(spark, items, window: int):
    shared = spark.sparkContext.broadcast(items)
    key = f"{spark.sparkContext.applicationId}-{shared._jbroadcast.id()}"

    def maker():
        found = _patterns(key, shared.value, window)

        def step(texts):
            rows = []
            for text in text_bytes(texts):
                mark, who = found.hits(words_of(text))
                rows.append(_row(len(mark), int(mark.sum()), {found.names[i] for i in who} - {None}))
            return list(zip(*rows, strict=True)) if rows else [[]] * len(RESULT)

        return step

    return maker


def _marker(spark, items, window: int):
    shared = spark.sparkContext.broadcast(items)
    key = f"{spark.sparkContext.applicationId}-{shared._jbroadcast.id()}"

    def run(batches):
        found = _patterns(key, shared.value, window)
        for batch in batches:
            rows, marks, lists = [], [], []
            for row, text in zip(batch.column(0).to_pylist(), text_bytes(batch.column(1)), strict=True):
                mark, who = found.hits(words_of(text))
                if mark.any():
                    rows.append(row)
                    marks.append(np.packbits(mark).tobytes())
                    lists.append(sorted({found.names[k] for k in who} - {None}))
            columns_ = [pa.array(rows, pa.int64()), pa.array(marks, pa.binary()), pa.array(lists, pa.list_(pa.string()))]
            yield pa.RecordBatch.from_arrays(columns_, names=["row", "mark", "items"])

    return run


def _joined(key, group: pd.DataFrame) -> pd.DataFrame:
    """The marks of one document from all passes (one row a pass)."""
    mark = np.bitwise_or.reduce([np.frombuffer(m, np.uint8) for m in group["mark"]])
    return pd.DataFrame({"row": [key[0]], "mark": [mark.tobytes()], "items": [sorted({x for own in group["items"] for x in own})]})


def _summary(texts, marks, lists):
    rows = []
    for text, mark, names in zip(text_bytes(texts), marks.to_pylist(), lists.to_pylist(), strict=True):
        hit = int(np.unpackbits(np.frombuffer(mark, np.uint8)).sum()) if mark else 0
        rows.append(_row(len(words_of(text)), hit, set(names or ())))
    return list(zip(*rows, strict=True)) if rows else [[]] * len(RESULT)


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """`docs` without the contaminated ones, same columns and values."""
    names = fresh(docs.columns, *[f"{n}_found" for n, _ in RESULT])
    return _found(docs, benchmark, names, WINDOW, PASS_BYTES).filter(~F.col(names[-1])).select(*columns(docs))
