"""Benchmark decontamination by Wu-Manber search over words.

Benchmark items are cut into windows of words; the windows are the test
strings. The search reads a document from left to right, one block of two
words at a time. A shift table, keyed by the hash of a block, tells how many
words no occurrence can end in, and the search skips them; a block at which
some window ends leads to the bucket of windows with that suffix and the
text's prefix, and these are compared word by word. Windows of unlike length
(items shorter than a window are one window of their own) have a table for
each length, because the shortest test string bounds the shift.

All tables are sorted arrays, made at once for all windows; the texts of a
chunk are read side by side, in stretches of STRETCH words, so that every step
of the search is one look-up for all stretches that are still being read.

The benchmark travels to the executors in shares of at most SHARE_BYTES of
text, each broadcast once and made into tables once a Python process; a larger
benchmark is searched in several passes, each adding to the hits that ride
along with the rows, so nothing of unknown size is broadcast and no pass
shuffles.

Defined results: null or wordless texts have no words and no hits; null or
wordless items have no windows; a null item_id is left out of the digest.
Columns of docs keep their names; an added column replaces one of its name.
"""

from __future__ import annotations

import uuid
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gradsift.llm.textkit import ALNUM_WORDS, Measure, Words, annotate, per_process, select_rows, text_bytes, words_in_parts, words_of

WINDOW = 10
BLOCK = 2
SHARE_BYTES = 16 << 20
#: Words that one cursor reads.
STRETCH = 512


class Searcher:
    """Shift table and buckets of the test strings of one length, given by
    their first words in w, in order; they are all windows of their items."""

    def __init__(self, w: Words, first: np.ndarray, length: int):
        self.w, self.length, self.block = w, length, min(BLOCK, length)
        self.most = length - self.block + 1
        # a block ends a window, or stands so near the start of an item that
        # only the item's first window, which ends later, can hold it
        tail = self.length - self.block
        lead = first[np.concatenate([[True], np.diff(first) != 1])] if len(first) else first
        early = (lead[:, None] + np.arange(tail)).reshape(-1)
        at = np.concatenate([first + tail, early])
        blocks = w.spans(at, at + self.block)
        steps = np.concatenate([np.zeros(len(first), np.int32), np.tile(np.arange(tail, 0, -1, dtype=np.int32), len(lead))])
        order = np.lexsort((steps, blocks))
        blocks, steps = blocks[order], steps[order]
        least = np.ones(len(blocks), bool)
        least[1:] = blocks[1:] != blocks[:-1]
        self.blocks, self.steps = blocks[least], steps[least]
        ends = self.keys(w, first)
        order = np.argsort(ends, kind="stable")
        self.ends, self.first = ends[order], first[order]

    def keys(self, w: Words, start: np.ndarray) -> np.ndarray:
        """Hash of the suffix and the prefix of the windows that begin there."""
        last = start + self.length - self.block
        return w.spans(last, last + self.block) ^ w.spans(start, start + self.block, 1)

    def shifts(self, keys: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.blocks, keys), len(self.blocks) - 1)
        return np.where(self.blocks[at] == keys, self.steps[at], self.most)

    def occurrences(self, w: Words) -> tuple[np.ndarray, np.ndarray]:
        """(first word in w, first word of the test string) of all matches."""
        n = np.maximum(w.counts - self.length + 1, 0)
        parts = -(-n // STRETCH)
        text = np.repeat(np.arange(len(n)), parts)
        part = np.arange(len(text)) - np.repeat(np.cumsum(parts) - parts, parts)
        # a cursor is the window that would end here
        at = w.first[text] + part * STRETCH
        stop = np.minimum(at + STRETCH, w.first[text] + n[text])
        ends = []
        tail = self.length - self.block
        while len(at):
            step = self.shifts(w.spans(at + tail, at + self.length))
            ends.append(at[step == 0])
            at = at + np.maximum(step, 1)
            left = at < stop
            at, stop = at[left], stop[left]
        start = np.concatenate(ends) if ends else np.zeros(0, np.int64)
        keys = self.keys(w, start)
        low, high = np.searchsorted(self.ends, keys), np.searchsorted(self.ends, keys, "right")
        size = high - low
        start = np.repeat(start, size)
        test = self.first[np.repeat(low - (np.cumsum(size) - size), size) + np.arange(len(start))]
        same = np.ones(len(start), bool)
        for i in range(self.length):
            same[same] = equal_words(w, start[same] + i, self.w, test[same] + i)
        return start[same], test[same]


def equal_words(a: Words, i: np.ndarray, b: Words, j: np.ndarray) -> np.ndarray:
    """Whether words i of a are words j of b, byte by byte."""
    size = a.ends[i] - a.starts[i]
    same = size == b.ends[j] - b.starts[j]
    size = np.where(same, size, 0)
    pair = np.repeat(np.arange(len(i)), size)
    inside = np.arange(len(pair)) - np.repeat(np.cumsum(size) - size, size)
    unlike = a.data[a.starts[i][pair] + inside] != b.data[b.starts[j][pair] + inside]
    same[pair[unlike]] = False
    return same


class Tables:
    """Searchers of all lengths, and the item of every word."""

    def __init__(self, items: pa.Table, size: int):
        data, offsets = text_bytes(items.column("text"))
        w = words_in_parts(data, offsets, ALNUM_WORDS, lower=True)
        self.names = items.column("item").to_pylist()
        self.item = w.doc
        self.searchers = []
        full = w.counts >= size
        if full.any():
            at, _ = w.windows(size)
            self.searchers.append(Searcher(w, at, size))
        for n in np.unique(w.counts[~full & (w.counts > 0)]).tolist():
            self.searchers.append(Searcher(w, w.first[w.counts == n], n))

    def search(self, w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(text, word) of every hit word, and (text, item) of every item,
        each pair once."""
        hit, of, item = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for s in self.searchers:
            start, test = s.occurrences(w)
            hit.append((np.unique(start)[:, None] + np.arange(s.length)).reshape(-1))
            of.append(w.doc[start])
            item.append(self.item[test])
        words = np.unique(np.concatenate(hit))
        pairs = np.unique(np.stack([np.concatenate(of), np.concatenate(item)]), axis=1)
        return w.doc[words], words - w.first[w.doc[words]] if len(words) else words, pairs[0], pairs[1]


def shares_of(benchmark: DataFrame, item: str, text: str) -> list[DataFrame]:
    """The benchmark in parts of bounded size."""
    size = benchmark.agg(F.sum(F.octet_length(text) + 64).alias("b")).first()["b"] or 0
    parts = max(1, ceil(size / SHARE_BYTES))
    rows = benchmark.select(F.col(item).cast("string").alias("item"), F.col(text).alias("text"))
    return [rows.where(F.pmod(F.xxhash64("item", "text"), F.lit(parts)) == p) for p in range(parts)] if parts > 1 else [rows]


def sent(share: DataFrame) -> tuple[str, Broadcast]:
    """A share, broadcast, and a name for it."""
    return uuid.uuid4().hex, share.sparkSession.sparkContext.broadcast(share.toArrow())


def tables_of(share: tuple[str, Broadcast], size: int) -> Tables:
    """The tables of a share, made once a process."""
    name, items = share
    return per_process("wumanber", lambda: Tables(items.value, size), f"{name}-{size}")


def _free(names: list[str], wanted: str) -> str:
    """A column name that no column has."""
    while wanted.lower() in (n.lower() for n in names):
        wanted += "_"
    return wanted


def search(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", size: int = WINDOW, keep: list[str] | None = None) -> DataFrame:
    """Add n_words, n_hit, n_items, items_sha256 and contaminated to each row."""
    added = ("n_words", "n_hit", "n_items", "items_sha256", "contaminated")
    own = [c for c in (docs.columns if keep is None else keep) if c not in added]
    names = [_free(docs.columns, c) for c in ("words_found", "hit_words", "hit_items")]
    kinds = [T.LongType(), T.ArrayType(T.IntegerType()), T.ArrayType(T.StringType())]
    hits = T.StructType([T.StructField(n, k) for n, k in zip(names, kinds, strict=True)])
    out = docs
    for n, share in enumerate(map(sent, shares_of(benchmark, item, item_text))):
        out = annotate(out, text, hits, lambda share=share, more=n > 0: _measure(share, size, names, more), [*dict.fromkeys([*own, text])], reads=names if n else None)
    words, hit, items = (F.col(n) for n in names)
    digest = F.sha2(F.array_join(F.array_sort(items), ","), 256)
    values = (words, F.size(hit).cast("long"), F.size(items).cast("long"), digest, F.size(hit) > 0)
    return out.select(*own, *[v.alias(c) for c, v in zip(added, values, strict=True)])


def clean(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", size: int = WINDOW) -> DataFrame:
    """The rows of docs without a hit, unchanged."""
    for share in map(sent, shares_of(benchmark, item, item_text)):

        def start(share=share):
            tables = tables_of(share, size)

            def decide(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
                free = np.ones(len(offsets) - 1, bool)
                free[tables.search(words_of(data, offsets, ALNUM_WORDS, lower=True))[0]] = False
                return free

            return decide

        docs = select_rows(docs, text, start)
    return docs


def _lists(of: np.ndarray, values: np.ndarray, n: int) -> list[list]:
    """values by text, of which `of` is in order."""
    at = np.searchsorted(of, np.arange(n + 1)).tolist()
    values = values.tolist()
    return [values[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]


def _measure(share: tuple[str, Broadcast], size: int, names: list[str], more: bool) -> Measure:
    tables = tables_of(share, size)

    def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
        w = words_of(data, offsets, ALNUM_WORDS, lower=True)
        n = len(w.counts)
        of, word, text, item = tables.search(w)
        hit = _lists(of, word, n)
        items = [sorted({tables.names[i] for i in found} - {None}) for found in _lists(text, item, n)]
        if more:
            before = [part.column(part.schema.get_field_index(c)).to_pylist() for c in names[1:]]
            hit = [sorted({*a, *b}) for a, b in zip(hit, before[0], strict=True)]
            items = [sorted({*a, *b}) for a, b in zip(items, before[1], strict=True)]
        return {names[0]: w.counts, names[1]: hit, names[2]: items}

    return measure
