"""Vectorised text kernels shared by the corpus operators.

All kernels work on the UTF-8 bytes of a batch of texts, as Arrow hands them
over: one byte buffer and the offsets of the texts in it. Every word class
used here is a set of bytes (all its non-members are ASCII), so cutting the
bytes cuts the code points as well. Hashes are 64-bit polynomials over bytes
or words, normalised by the start position and then mixed, so that equal
content gives an equal hash wherever it stands.
"""

from __future__ import annotations

import sys
import types
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

CHUNK_BYTES = 2 << 20
#: Where many steps follow each other in one Python process, or features are
#: sorted: scratch of a chunk is some sixty times its text.
SMALL_CHUNK_BYTES = 1 << 19


def _class(excluded: list[int]) -> np.ndarray:
    table = np.ones(256, bool)
    table[excluded] = False
    return table


#: The word classes of the contracts, as byte tables.
BLANK_WORDS = _class([0x20, *range(0x09, 0x0E)])
ALNUM_WORDS = _class([*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)])
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

_BYTE_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_WORD_BASE = np.uint64(0xD6E8FEB86659FD93 | 1)


def mix(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply); bijective for a fixed seed."""
    with np.errstate(over="ignore"):
        x = x + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) & 0xFFFFFFFFFFFFFFFF)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n."""
    got = _POWERS.get(int(base))
    if got is None or len(got[0]) < n:
        size = max(1 << 16, 1 << (n - 1).bit_length())
        inverse = np.uint64(pow(int(base), -1, 1 << 64))
        with np.errstate(over="ignore"):
            up = np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, base, np.uint64)]))
            down = np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, inverse, np.uint64)]))
        got = _POWERS[int(base)] = (up, down)
    return got


_BYTES = mix(np.arange(256, dtype=np.uint64), 77)


def _prefix(values: np.ndarray, base: np.uint64) -> np.ndarray:
    up, _ = _powers(base, len(values) + 1)
    out = np.zeros(len(values) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum(values * up[: len(values)], out=out[1:])
    return out


def _ranges(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray, base: np.uint64, seed: int) -> np.ndarray:
    _, down = _powers(base, len(prefix))
    with np.errstate(over="ignore"):
        raw = (prefix[ends] - prefix[starts]) * down[starts]
        return mix(raw + (ends - starts).astype(np.uint64) * np.uint64(0xA24BAED4963EE407), seed)


@dataclass
class Words:
    """Words of a chunk: byte range, text number and hash of each, and for
    each text the number of its words and the number of its first word."""

    data: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    doc: np.ndarray
    counts: np.ndarray
    first: np.ndarray
    hashes: np.ndarray

    def windows(self, k: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
        """First word and hash of every run of k words inside one text."""
        n = len(self.starts)
        if n < k:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        at = np.flatnonzero(self.doc[: n - k + 1] == self.doc[k - 1 :])
        return at, self.spans(at, at + k, seed)

    def spans(self, starts: np.ndarray, ends: np.ndarray, seed: int = 0) -> np.ndarray:
        """Hash of the words from start to end, end exclusive."""
        return _ranges(self.prefix(seed), starts, ends, _WORD_BASE, seed)

    def prefix(self, seed: int = 0) -> np.ndarray:
        return _prefix(self.hashes if not seed else mix(self.hashes, seed), _WORD_BASE)


def words_of(data: np.ndarray, offsets: np.ndarray, is_word: np.ndarray, lower: bool = False) -> Words:
    """Cut a chunk of texts into words. offsets: n+1 byte positions."""
    offsets = offsets.astype(np.int64)
    if lower:
        data = LOWER[data]
    mask = np.zeros(len(data) + 2, np.int8)
    mask[1:-1] = is_word[data]
    begins, stops = (mask[1:-1] > mask[:-2]), (mask[1:-1] > mask[2:])
    full = offsets[:-1] < offsets[1:]
    edge = offsets[:-1][full]
    begins[edge] |= mask[1:-1][edge] > 0
    edge = offsets[1:][full] - 1
    stops[edge] |= mask[1:-1][edge] > 0
    starts, ends = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    first = np.searchsorted(starts, offsets[:-1])
    counts = np.searchsorted(starts, offsets[1:]) - first
    doc = np.repeat(np.arange(len(counts)), counts)
    hashes = _ranges(_prefix(_BYTES[data], _BYTE_BASE), starts, ends, _BYTE_BASE, 3)
    return Words(data, starts, ends, doc, counts, first, hashes)


def words_in_parts(data: np.ndarray, offsets: np.ndarray, is_word: np.ndarray, lower: bool = False, limit: int = 1 << 19) -> Words:
    """words_of, but with the byte-wide scratch of a part of the texts only."""
    offsets, n = offsets.astype(np.int64), len(offsets) - 1
    parts, lo = [], 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        w = words_of(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo], is_word, lower)
        parts.append((w.starts + offsets[lo], w.ends + offsets[lo], w.counts, w.hashes, w.data if lower else None))
        lo = hi
    if not parts:
        return words_of(data, offsets, is_word, lower)
    starts, ends, counts, hashes = (np.concatenate([p[i] for p in parts]) for i in range(4))
    first = np.cumsum(counts) - counts
    return Words(np.concatenate([p[4] for p in parts]) if lower else data, starts, ends, np.repeat(np.arange(n), counts), counts, first, hashes)


def byte_ranges(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of any byte ranges of a chunk, such as lines."""
    return _ranges(_prefix(_BYTES[data], _BYTE_BASE), starts, ends, _BYTE_BASE, 5)


def per_doc(values: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    """Sum of values by text number."""
    return np.bincount(doc, weights=values, minlength=n).astype(np.int64) if len(doc) else np.zeros(n, np.int64)


def covered(starts: np.ndarray, length: np.ndarray | int, n: int) -> np.ndarray:
    """Which of n positions lie in any of the runs."""
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + length, -1)
    return np.cumsum(edge[:-1]) > 0


def text_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The byte buffer and the offsets of a string column; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1] if offsets else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def chunks(batch: pa.RecordBatch, text: str, limit: int = CHUNK_BYTES) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices of a batch with up to limit bytes of text, or one longer text."""
    data, offsets = text_bytes(batch.column(batch.schema.get_field_index(text)))
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1)
        yield batch.slice(lo, hi - lo), data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi


def slices(data: np.ndarray, offsets: np.ndarray) -> list[bytes]:
    raw = data.tobytes()
    at = offsets.tolist()
    return [raw[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]


def per_process(key: str, make: Callable, version: str = ""):
    """An object that a Python worker makes once and keeps for later tasks;
    of one key, only the last version is kept."""
    store = vars(sys.modules.setdefault("_gradsift_process", types.ModuleType("_gradsift_process")))
    if key not in store or store[key][0] != version:
        store.pop(key, None)
        store[key] = (version, make())
    return store[key][1]


Measure = Callable[[pa.RecordBatch, np.ndarray, np.ndarray], dict]


def annotate(docs: DataFrame, text: str, added: T.StructType, start: Callable[[], Measure], keep: list[str] | None = None, reads: list[str] | None = None, limit: int = CHUNK_BYTES) -> DataFrame:
    """Add columns measured on every text, in one pass without a shuffle.

    start() is called once per task and returns the measure of a chunk, a
    dict of column name to values. keep: the columns of docs to keep, all by
    default. An added column replaces one of docs that has its name. reads:
    further columns that the measure looks at. limit: bytes of a chunk.
    """
    names = [f.name for f in added]
    kept = [c for c in (keep if keep is not None else docs.columns) if c not in names]
    taken = docs.select(*dict.fromkeys([*kept, text, *(reads or [])]))
    out = T.StructType([f for f in taken.schema if f.name in kept] + list(added))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_type

        kinds = [(f.name, to_arrow_type(f.dataType)) for f in added]
        measure = start()
        for batch in batches:
            for part, data, offsets in chunks(batch, text, limit):
                got = measure(part, data, offsets)
                yield pa.RecordBatch.from_arrays(
                    [part.column(part.schema.get_field_index(c)) for c in kept] + [got[c] if isinstance(got[c], pa.Array) else pa.array(got[c], k) for c, k in kinds],
                    names=[*kept, *names],
                )

    return taken.mapInArrow(run, out)


def select_rows(docs: DataFrame, text: str, start: Callable[[], Callable[[pa.RecordBatch, np.ndarray, np.ndarray], np.ndarray]]) -> DataFrame:
    """Keep the rows for which the measure is true, all columns unchanged."""
    limit = SMALL_CHUNK_BYTES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decide = start()
        for batch in batches:
            for part, data, offsets in chunks(batch, text, limit):
                yield part.filter(pa.array(np.asarray(decide(part, data, offsets), bool)))

    return docs.mapInArrow(run, docs.schema)
