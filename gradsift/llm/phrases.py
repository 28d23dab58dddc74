"""Removal of passages that recur, by automata of repeated phrases.

A window of WINDOW words is removed where its words also start anywhere else.
Two windows that are equal hold equal phrases, so it is enough to look where
phrases of PHRASE words repeat, and of these only at the smallest hash of each
window (winnowing), which equal windows have in common.

Texts are dealt into blocks of about BLOCK_BYTES, once; all steps read that
one exchange:

    suspect  each block's smallest phrase hashes, once a block with the number
             of their places; summed over blocks, the repeated ones go back to
             the blocks that hold them
    confirm  blocks answer with the words of the suspected phrases; a phrase
             recurs if two places have the same words, one by one. Confirmed
             phrases go, as text, to the blocks that hold them
    locate   a block compiles its phrases into Aho-Corasick automata, sharded
             at SHARD phrases each, and streams all its texts through every
             shard. Nothing else tells where a phrase stands. Every window
             around an occurrence is a candidate, and the block's distinct
             candidates are counted
    judge    candidates are summed over blocks; those with two places or more
             go back, as one place each, to the blocks that hold them; a place
             counts the words of the block's texts, sorted
    cut      each block drops the words that such a window covers

A block gets only the phrases that occur in it: all texts through all phrases
would be work that grows with the square of the corpus. A block, its phrases
and one automaton are all that a task holds. A phrase or window of a third of
all texts is one row a block: at 100 TB 17 million rows, about 1.5 GB for a
phrase, that pass one task, sorted outside memory. Windows are compared by 96
bits of hash. In the automata a word is its number in the block's vocabulary,
spelled in letters of an alphabet of 32, which keeps nodes narrow at any size.

Defined results: null and wordless texts have no words and keep none; texts
shorter than a window lose nothing; equal rows of a window or more lose all
their words, as each is the other's recurrence. Equal rows are spread over
blocks by the partition that they are read in.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from gradsift.llm.textkit import BLANK_WORDS, Words, covered, mix, per_doc, text_bytes, words_in_parts, words_of

WINDOW = 35
PHRASE = 12
BLOCK_BYTES = 6 << 20
#: Phrases of one automaton.
SHARD = 8192

LETTERS = np.frombuffer(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdef", np.uint8)


def in_order(table: pa.Table) -> pa.Table:
    """The rows of a block by their texts. A shuffle hands them over in the
    order in which its pieces arrive, another one each time that it is read;
    rows of one text have the same words, so the place of a word is fixed."""
    return table.take(pc.sort_indices(table, sort_keys=[("text", "ascending")]))


def block_words(table: pa.Table) -> tuple[Words, np.ndarray]:
    data, offsets = text_bytes(table.column("text"))
    return words_in_parts(data, offsets, BLANK_WORDS), offsets


def phrase_hashes(w: Words, window: int, phrase: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Phrase hash by first word (of texts with a window), whether a phrase
    starts there, and for every window its smallest phrase hash."""
    n = len(w.starts)
    h = np.full(n, np.iinfo(np.uint64).max, np.uint64)
    at, got = w.windows(phrase, 31)
    h[at] = got
    begins = np.zeros(n, bool)
    begins[at] = True
    begins &= (w.counts >= window)[w.doc] if n else begins
    starts = np.flatnonzero(w.doc[: n - window + 1] == w.doc[window - 1 :]) if n >= window else np.zeros(0, np.int64)
    low, width, span = h, 1, window - phrase + 1
    while 2 * width <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    if width < span:
        low = np.minimum(low[: len(low) - (span - width)], low[span - width :])
    return h, begins, low[starts] if len(starts) else np.zeros(0, np.uint64)


def spelled(numbers: np.ndarray, letters: int) -> np.ndarray:
    """Numbers as rows of so many letters."""
    out = np.empty((len(numbers), letters), np.uint8)
    for i in range(letters):
        out[:, i] = LETTERS[(numbers >> 5 * i) & 31]
    return out


def joined(w: Words) -> tuple[bytes, np.ndarray]:
    """All words of a block, each with one space behind, and their starts."""
    size = w.ends - w.starts + 1
    at = np.cumsum(size) - size
    total = int(size.sum())
    place = np.arange(total) - np.repeat(at - w.starts, size)
    out = w.data[np.minimum(place, len(w.data) - 1)] if total else np.zeros(0, np.uint8)
    out[at + size - 1] = 0x20
    return out.tobytes(), at


def _phrases(window: int, phrase: int):
    def run(key: tuple, table: pa.Table) -> pa.Table:
        w, _ = block_words(table)
        h, begins, low = phrase_hashes(w, window, phrase)
        chosen = np.unique(low)
        values, times = np.unique(h[begins], return_counts=True)
        times = times[np.searchsorted(values, chosen)]
        return pa.table({"h": chosen.view(np.int64), "block": np.full(len(chosen), key[0].as_py(), np.int32), "n": np.minimum(times, 2).astype(np.int32)})

    return run


def _texts(window: int, phrase: int):
    """The words of a block's suspected phrases, with 1 or 2 for the places
    that have them."""
    empty = pa.table({"phrase": pa.array([], pa.string()), "block": pa.array([], pa.int32()), "n": pa.array([], pa.int32())})

    def run(key: tuple, table: pa.Table, suspected: pa.Table) -> pa.Table:
        if not table.num_rows or not suspected.num_rows:
            return empty
        w, _ = block_words(table)
        h, begins, _ = phrase_hashes(w, window, phrase)
        here = np.flatnonzero(begins & np.isin(h, suspected.column("h").to_numpy().view(np.uint64)))
        here = here[np.argsort(h[here], kind="stable")]
        first = np.flatnonzero(np.concatenate([[True], h[here[1:]] != h[here[:-1]]])) if len(here) else here
        raw, at = joined(w)
        ends = np.concatenate([at[1:], [len(raw)]]) - 1
        words = lambda places: [raw[x:y] for x, y in zip(at[places].tolist(), ends[places + phrase - 1].tolist(), strict=True)]
        times = np.diff(np.concatenate([first, [len(here)]]))
        found, second = words(here[first]), words(here[np.minimum(first + 1, len(here) - 1)] if len(here) else here)
        out = []
        for i, (a, b, n) in enumerate(zip(found, second, times.tolist(), strict=True)):
            if n == 1 or a == b:
                out.append((a, min(n, 2)))
            else:  # one hash, unlike words
                out += [(t, min(m, 2)) for t, m in Counter(words(here[first[i] : first[i] + n])).items()]
        return pa.table({"phrase": pa.array([t.decode() for t, _ in out], pa.string()), "block": np.full(len(out), key[0].as_py(), np.int32), "n": np.array([n for _, n in out], np.int32)})

    return run


def streamed(code: str, patterns: list[str], letters: int) -> np.ndarray:
    """Numbers of the words at which a pattern ends in the code of a block,
    by one automaton of these patterns."""
    import ahocorasick

    automaton = ahocorasick.Automaton(ahocorasick.STORE_LENGTH)
    for p in patterns:
        automaton.add_word(p)
    automaton.make_automaton()
    ends = np.fromiter((e for e, _ in automaton.iter(code)), np.int64)
    return ends[ends % letters == letters - 1] // letters


def located(w: Words, phrases: pa.ChunkedArray, window: int, phrase: int) -> np.ndarray:
    """First words of the windows around any occurrence of the phrases, found
    by automata of SHARD phrases each."""
    known, number = np.unique(w.hashes, return_inverse=True)
    letters = max(1, ceil(np.log2(max(len(known), 2)) / 5))
    code = spelled(number, letters).tobytes().decode("ascii")
    p = words_of(*text_bytes(phrases), BLANK_WORDS)
    patterns = spelled(np.searchsorted(known, p.hashes), letters).reshape(-1, phrase * letters)
    near = np.zeros(len(w.starts) + 1, np.int64)
    for lo in range(0, len(patterns), SHARD):
        last = streamed(code, [x.tobytes().decode("ascii") for x in patterns[lo : lo + SHARD]], letters)
        start = last - phrase + 1
        d = w.doc[last]
        first, n = w.first[d], w.counts[d]
        low, high = np.maximum(start - (window - phrase), first), np.minimum(start, first + n - window)
        inside = (start >= first) & (n >= window) & (low <= high)
        np.add.at(near, low[inside], 1)
        np.add.at(near, high[inside] + 1, -1)
    return np.flatnonzero(np.cumsum(near[:-1]) > 0)


def window_keys(w: Words, at: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """96 bits of hash of the windows that begin at the given words."""
    return w.spans(at, at + window, 51).view(np.int64), (w.spans(at, at + window, 52) >> np.uint64(32)).astype(np.uint32).view(np.int32)


CANDIDATES = "w1 long, w2 int, block int, place int, n int"


def _candidates(window: int, phrase: int):
    empty = pa.table({"w1": pa.array([], pa.int64())} | {c: pa.array([], pa.int32()) for c in ("w2", "block", "place", "n")})

    def run(key: tuple, table: pa.Table, phrases: pa.Table) -> pa.Table:
        if not table.num_rows or not phrases.num_rows:
            return empty
        w, _ = block_words(in_order(table))
        at = located(w, phrases.column("phrase"), window, phrase)
        w1, w2 = window_keys(w, at, window)
        order = np.lexsort((w2, w1))
        new = np.ones(len(order), bool)
        new[1:] = (w1[order[1:]] != w1[order[:-1]]) | (w2[order[1:]] != w2[order[:-1]])
        index, first = order[new], np.flatnonzero(new)
        times = np.diff(np.concatenate([first, [len(order)]]))
        return pa.table({"w1": w1[index], "w2": w2[index], "block": np.full(len(index), key[0].as_py(), np.int32), "place": at[index].astype(np.int32), "n": np.minimum(times, 2).astype(np.int32)})

    return run


def kept_text(w: Words, offsets: np.ndarray, removed: np.ndarray) -> tuple[bytes, np.ndarray]:
    """Kept words joined by one space, text after text, and the offsets."""
    n = len(w.counts)
    keep = ~removed
    data = w.data.copy()
    edge = np.zeros(len(data) + 1, np.int8)
    edge[w.starts[keep]] = 1
    edge[w.ends[keep]] -= 1
    mask = np.cumsum(edge[:-1], dtype=np.int8).view(bool)
    doc, ends = w.doc[keep], w.ends[keep]
    inner = ends[:-1][doc[:-1] == doc[1:]] if len(doc) else ends
    mask[inner] = True
    data[inner] = 0x20
    total = np.zeros(len(data) + 1, np.int64)
    np.cumsum(mask, out=total[1:])
    return data[mask].tobytes(), total[offsets] if n else np.zeros(1, np.int64)


def _cut(window: int, names: list[str], with_text: bool):
    def run(key: tuple, table: pa.Table, confirmed: pa.Table) -> pa.Table:
        table = in_order(table)
        w, offsets = block_words(table)
        removed = np.zeros(len(w.starts), bool)
        at = np.flatnonzero(w.doc[: len(w.starts) - window + 1] == w.doc[window - 1 :]) if len(w.starts) >= window else np.zeros(0, np.int64)
        if confirmed.num_rows and len(at):
            w1, w2 = window_keys(w, at, window)
            index = np.searchsorted(at, confirmed.column("place").to_numpy())
            known = np.unique(w1[index])
            check = np.unique(mix(w1[index].view(np.uint64), 1) ^ w2[index].view(np.uint32))
            hit = np.isin(w1, known)
            hit[hit] = np.isin(mix(w1[hit].view(np.uint64), 1) ^ w2[hit].view(np.uint32), check)
            removed = covered(at[hit], window, len(w.starts))
        raw, ends = kept_text(w, offsets, removed)
        parts = [raw[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
        out = {c: table.column(c) for c in names}
        out |= {"n_words": pa.array(w.counts, pa.int64()), "n_removed": pa.array(per_doc(removed, w.doc, len(w.counts)), pa.int64())}
        out |= {"kept_sha256": pa.array([hashlib.sha256(p).hexdigest() for p in parts], pa.string())}
        if with_text:
            out |= {"kept_text": pa.array([p.decode() for p in parts], pa.string())}
        return pa.table(out)

    return run


def cut_repeats(docs: DataFrame, text: str = "text", window: int = WINDOW, phrase: int = PHRASE, block_bytes: int = BLOCK_BYTES, keep: list[str] | None = None, with_text: bool = False) -> DataFrame:
    """Add n_words, n_removed and kept_sha256, and on request kept_text, to
    each row of docs. An added column replaces one of docs that has its name."""
    added = ["n_words", "n_removed", "kept_sha256", *(["kept_text"] if with_text else [])]
    names = [c for c in (docs.columns if keep is None else keep) if c not in added]
    size = docs.agg(F.sum(F.octet_length(text)).alias("b")).first()["b"] or 0
    blocks = max(1, ceil(size / block_bytes))
    # columns ride along under numbers, so that no name can clash
    inner = [f"c{i}" for i in range(len(names))]
    row = F.xxhash64(F.col(text), F.spark_partition_id(), *[F.col(c) for c in names if dict(docs.dtypes)[c].split("<")[0] not in ("map", "variant")])
    rows = docs.select(*[F.col(c).alias(i) for c, i in zip(names, inner, strict=True)], F.col(text).alias("text"), F.pmod(row, F.lit(blocks)).cast("int").alias("block"))
    by_block = rows.groupBy("block")

    total = lambda *keys: F.sum("n").over(Window.partitionBy(*keys))
    suspected = by_block.applyInArrow(_phrases(window, phrase), "h long, block int, n int")
    suspected = suspected.withColumn("n", total("h")).where("n > 1").select("h", "block")
    recurring = by_block.cogroup(suspected.groupBy("block")).applyInArrow(_texts(window, phrase), "phrase string, block int, n int")
    recurring = recurring.withColumn("n", total("phrase")).where("n > 1").select("phrase", "block")
    candidates = by_block.cogroup(recurring.groupBy("block")).applyInArrow(_candidates(window, phrase), CANDIDATES)
    confirmed = candidates.withColumn("n", total("w1", "w2")).where("n > 1").select("place", "block")
    out = T.StructType([f for f in rows.schema if f.name in inner] + [T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_sha256", T.StringType())] + ([T.StructField("kept_text", T.StringType())] if with_text else []))
    result = by_block.cogroup(confirmed.groupBy("block")).applyInArrow(_cut(window, inner, with_text), out)
    return result.select(*[F.col(i).alias(c) for c, i in zip(names, inner, strict=True)], *added)
