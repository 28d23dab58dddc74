"""Near-duplicate groups by SuperMinHash, banding, verification, union-find.

SuperMinHash gives every element one random permutation of the signature's
places and, at the j-th of them, a value in [j, j+1). Ranks of one element are
thus correlated, which lowers the variance, and once every place holds a
value below j + 1 no later step can change one: it stops early, for large
sets after the first step. Here the j-th step is taken for all elements of a
chunk at once; the permutation is unrolled from the swaps alone.

    sets    one scan: set size, 128-bit set fingerprint, band keys
    classes equal sets become one class, a vertex with a number of its own;
            its smallest id is only its name
    pairs   classes that share a band key are paired with the smallest
            class there, one pair a member and key, never all with all
    verify  pairs are confirmed on the full sets, then united
    rest    band keys whose classes are still apart: pairs across components
            are compared inside tasks, so that a link whose ends both differ
            from the smallest class is found too. Classes stand in cells of
            bounded size, a large component in cells of its own, and cells of
            one component are never compared: where one component has nearly
            all classes of a key, each of its sets is sent once for every
            cell of the others, not for every cell
    unite   components of all links; the class names map back to rows

With 32 bands of 4 places a pair at the threshold of 0.85 shares no band key
with probability (1 - 0.85**4)**32 < 1e-10.

Defined results: null and wordless texts have an empty set and are alone;
texts shorter than a shingle have their words as the only one. An id is an
integer, and may be null or repeated: rows are grouped by their texts alone, null is the smallest
id, and groups whose smallest ids are equal share that name but stay apart.
A row is found again by its id and a 64-bit hash of its text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gradsift.llm.groups import components
from gradsift.llm.shared import written
from gradsift.llm.textkit import BLANK_WORDS, annotate, mix, words_of

SHINGLE = 5
BANDS = 32
ROWS = 4
#: Link at 100 * intersection >= LINK * union.
LINK = 85
#: A comparison holds two parts of at most so many sets and bytes on average.
PART_SETS = 512
PART_BYTES = 16 << 20
#: Sets up to which a shingle's pairs are counted one by one.
FEW = 24
#: Pairs that are counted at once.
PAIRS = 1 << 20

NULL_ID = -(1 << 63)
TOP = np.uint64((1 << 56) - 1)


def shingle_sets(data: np.ndarray, offsets: np.ndarray, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of a chunk, text after text, and the
    first position of each text's set (n+1 numbers)."""
    w = words_of(data, offsets, BLANK_WORDS, lower=True)
    at, h = w.windows(size)
    doc = w.doc[at]
    short = np.flatnonzero((w.counts > 0) & (w.counts < size))
    if len(short):
        h = np.concatenate([h, w.spans(w.first[short], w.first[short] + w.counts[short])])
        doc = np.concatenate([doc, short])
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    h, doc = h[new], doc[new]
    return h, np.searchsorted(doc, np.arange(len(w.counts) + 1))


def signatures(h: np.ndarray, first: np.ndarray, m: int) -> np.ndarray:
    """SuperMinHash of every set, m places: step in the top byte, then a
    56-bit fraction. Empty sets keep the largest value everywhere."""
    n = len(first) - 1
    sign = np.full(n * m, np.iinfo(np.uint64).max, np.uint64)
    doc = np.repeat(np.arange(n), np.diff(first))
    swaps: list[np.ndarray] = []
    for j in range(m):
        if not len(h):
            break
        r = mix(h, 100 + j)
        place = j + ((mix(h, 300 + j) >> np.uint64(32)) * np.uint64(m - j) >> np.uint64(32)).astype(np.int64)
        swaps.append(place)
        for i in range(j - 1, -1, -1):
            place = np.where(swaps[i] == place, i, place)
        np.minimum.at(sign, doc * m + place, np.uint64(j) << np.uint64(56) | r & TOP)
        done = (sign.reshape(n, m).max(axis=1) >> np.uint64(56)) <= np.uint64(j)
        left = ~done[doc]
        h, doc, swaps = h[left], doc[left], [s[left] for s in swaps]
    return sign.reshape(n, m)


def band_keys(sign: np.ndarray, bands: int, rows: int) -> np.ndarray:
    key = np.zeros((len(sign), bands), np.uint64)
    cells = sign.reshape(len(sign), bands, rows)
    for r in range(rows):
        key = mix(key ^ cells[:, :, r], 7 + r)
    return mix(key ^ np.arange(bands, dtype=np.uint64)).view(np.int64)


FOUND = T.StructType([T.StructField(n, T.LongType()) for n in ("n_shingles", "f1", "f2")] + [T.StructField("bands", T.ArrayType(T.LongType()))])


def _sums(h: np.ndarray, first: np.ndarray, seed: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        total = np.concatenate([[np.uint64(0)], np.cumsum(mix(h, seed))])
        return (total[first[1:]] - total[first[:-1]]).view(np.int64)


def sets_of(docs: DataFrame, key: str, text: str, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
        h, first = shingle_sets(data, offsets)
        keys = band_keys(signatures(h, first, bands * rows), bands, rows)
        sizes = np.diff(first)
        ends = np.concatenate([[0], np.cumsum(np.where(sizes > 0, bands, 0))]).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(keys[sizes > 0].reshape(-1)))
        return {"n_shingles": sizes, "f1": _sums(h, first, 21), "f2": _sums(h, first, 22), "bands": lists}

    return annotate(docs.select(*_named(key, text), F.col(text).alias("text")), "text", FOUND, lambda: measure, ["id", "hash"])


def _named(key: str, text: str) -> list[Column]:
    """id and hash, by which a row is found again."""
    return [F.coalesce(F.col(key).cast("long"), F.lit(NULL_ID)).alias("id"), F.xxhash64(text).alias("hash")]


def full_sets(docs: DataFrame) -> DataFrame:
    """(id, set) with the sorted shingle hashes as bytes."""

    def measure(part: pa.RecordBatch, data: np.ndarray, offsets: np.ndarray) -> dict:
        h, first = shingle_sets(data, offsets)
        raw = h.tobytes()
        return {"set": [raw[8 * a : 8 * b] for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True)]}

    return annotate(docs, "text", T.StructType([T.StructField("set", T.BinaryType())]), lambda: measure, ["id"])


def linked(a: np.ndarray, b: np.ndarray, link: int) -> bool:
    n, m = len(a), len(b)
    if 100 * min(n, m) < link * max(n, m):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= link * (n + m - both)


def _verify(pairs: DataFrame, sets: DataFrame, link: int) -> DataFrame:
    """The pairs (u, v) that are linked."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            view = lambda x: np.frombuffer(x.as_buffer(), np.uint64)
            good = [linked(view(a), view(b), link) for a, b in zip(batch.column("a"), batch.column("b"), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("u").filter(pa.array(good, pa.bool_())), batch.column("v").filter(pa.array(good, pa.bool_()))], names=["u", "v"])

    with_a = pairs.join(sets.select(F.col("id").alias("u"), F.col("set").alias("a")), "u")
    with_b = with_a.join(sets.select(F.col("id").alias("v"), F.col("set").alias("b")), "v")
    return with_b.select("u", "v", "a", "b").mapInArrow(run, "u long, v long")


def overlaps(sets: list[np.ndarray]) -> np.ndarray:
    """Intersection sizes of all pairs of a block. Shingles of few sets add
    their pairs one by one, those of many are columns of a matrix product."""
    n = len(sets)
    values = np.concatenate(sets) if n else np.zeros(0, np.uint64)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    order = np.argsort(values, kind="stable")
    values, owner = values[order], owner[order]
    first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]])) if len(values) else np.zeros(0, np.int64)
    times = np.diff(np.concatenate([first, [len(values)]]))
    out = np.zeros(n * n, np.int64)
    for size in range(2, FEW + 1):
        at = first[times == size]
        step = max(1, PAIRS // (size * size))
        for lo in range(0, len(at), step):
            who = owner[at[lo : lo + step, None] + np.arange(size)]
            out += np.bincount((who[:, :, None] * n + who[:, None, :]).reshape(-1), minlength=n * n)
    out = out.reshape(n, n)
    many = np.flatnonzero(times > FEW)
    for lo in range(0, len(many), 4096):
        part = many[lo : lo + 4096]
        column = np.repeat(np.arange(len(part)), times[part])
        place = np.arange(len(column)) - np.repeat(np.cumsum(times[part]) - times[part], times[part]) + np.repeat(first[part], times[part])
        grid = np.zeros((n, len(part)), np.float32)
        grid[owner[place], column] = 1
        out += (grid @ grid.T).astype(np.int64)
    return out


def _compare_block(link: int):
    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("id")
        ids, comp = part["id"].to_numpy(), part["comp"].to_numpy()
        sets = [np.frombuffer(s, np.uint64) for s in part["set"]]
        size = np.array([len(s) for s in sets])
        both = overlaps(sets)
        ok = (100 * both >= link * (size[:, None] + size[None, :] - both)) & (comp[:, None] < comp[None, :])
        i, j = np.nonzero(ok)
        found = pd.DataFrame({"u": ids[i], "v": ids[j], "cu": comp[i], "cv": comp[j]})
        return found.drop_duplicates(["cu", "cv"])[["u", "v"]]

    return run


def _in_cells(rest: DataFrame) -> DataFrame:
    """(pair, id, comp) of band keys whose classes are apart: every class once
    for each pair of cells that its own cell is part of."""
    parts = lambda m, s: F.greatest(F.ceil(m / F.lit(PART_SETS)), F.ceil(s / F.lit(PART_BYTES // 8)))
    each = rest.groupBy("band", "comp").agg(F.count("*").alias("m"), F.sum("n_shingles").alias("s"))
    # a component of half a cell or more has cells of its own, named by it
    each = each.select("*", (parts(F.col("m") * 2, F.col("s") * 2) > 1).alias("own"))
    small = each.where("not own").groupBy("band").agg(parts(F.sum("m"), F.sum("s")).alias("shared"))
    each = each.join(small, "band", "left")
    each = each.select("band", "comp", F.when(F.col("own"), F.col("comp")).otherwise(-1).alias("of"), F.when(F.col("own"), parts(F.col("m"), F.col("s"))).otherwise(F.col("shared")).alias("cells"))
    place = F.pmod(F.when(F.col("of") >= 0, F.xxhash64("id")).otherwise(F.xxhash64("comp")), F.col("cells"))
    members = written(rest.join(each, ["band", "comp"]).select("band", "id", "comp", F.struct("of", place.alias("number")).alias("cell")), "cells")

    cells = members.select("band", "cell").distinct()
    x, y = cells.select("band", F.col("cell").alias("x")), cells.select("band", F.col("cell").alias("y"))
    pairs = x.join(y, "band").where((F.col("x") <= F.col("y")) & ((F.col("x.of") != F.col("y.of")) | (F.col("x.of") < 0)))
    pairs = pairs.select("band", "x", "y", F.xxhash64("band", "x", "y").alias("pair"))
    sides = pairs.select("band", F.col("x").alias("cell"), "pair").unionByName(pairs.where(F.col("x") != F.col("y")).select("band", F.col("y").alias("cell"), "pair"))
    return members.join(sides, ["band", "cell"]).select("pair", "id", "comp")


def links(docs: DataFrame, key: str = "doc_id", text: str = "text", link: int = LINK, bands: int = BANDS, rows: int = ROWS) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(found, classes, roots): found has id, hash, n_shingles and the set's
    fingerprint of every row of docs; classes has the fingerprint, rep, the
    vertex, and id and hash of the first row of every class; roots has vertex
    and root of every linked class."""
    found = written(sets_of(docs, key, text, bands, rows), "sets")
    full = found.where("n_shingles > 0")
    classes = full.groupBy("f1", "f2", "n_shingles").agg(F.min(F.struct("id", "hash")).alias("least"), F.min_by("bands", "id").alias("bands"))
    classes = written(classes.select("f1", "f2", "n_shingles", "least.*", "bands", F.monotonically_increasing_id().alias("rep")), "classes")
    keys = classes.select("rep", "n_shingles", F.explode("bands").alias("band"))
    least = keys.groupBy("band").agg(F.min("rep").alias("low"), F.max("rep").alias("high")).where("low < high").select("band", "low")
    shared = written(keys.join(least, "band"), "buckets")

    wanted = shared.select(F.explode(F.array("rep", "low")).alias("id")).distinct()
    wanted = wanted.join(classes.select(F.col("rep").alias("vertex"), F.col("id").alias("row"), "hash"), F.col("id") == F.col("vertex")).select("vertex", F.col("row").alias("id"), "hash")
    texts = docs.select(*_named(key, text), F.col(text).alias("text")).join(wanted, ["id", "hash"]).select(F.col("vertex").alias("id"), "text")
    sets = written(full_sets(texts.dropDuplicates(["id"])), "full-sets")
    pairs = shared.where("rep <> low").select(F.col("rep").alias("u"), F.col("low").alias("v")).distinct()
    edges = written(_verify(pairs, sets, link), "links")

    first = components(edges)
    placed = shared.join(first, F.col("rep") == F.col("vertex"), "left").select("band", F.col("rep").alias("id"), "n_shingles", F.coalesce("root", "rep").alias("comp"))
    apart = placed.groupBy("band").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("m"), F.sum("n_shingles").alias("s"), F.sum(F.xxhash64("id").cast("decimal(38,0)")).alias("who")).where("lo < hi")
    # keys with the same members need one look
    apart = apart.groupBy("who", "m", "s").agg(F.min("band").alias("band"))
    rest = _in_cells(placed.join(apart.select("band"), "band"))
    more = rest.join(sets, "id").groupBy("pair").applyInPandas(_compare_block(link), "u long, v long")
    return found, classes, components(first.select(F.col("vertex").alias("u"), F.col("root").alias("v")).unionByName(more))


def _placed(docs: DataFrame, key: str, text: str, link: int) -> tuple[DataFrame, DataFrame]:
    """(found, placed): placed has the fingerprint of every class, and id and
    hash of the first row of its component."""
    found, classes, roots = links(docs, key, text, link)
    rooted = written(classes.drop("bands").join(roots, F.col("rep") == F.col("vertex"), "left").select("f1", "f2", "n_shingles", "id", "hash", F.coalesce("root", "rep").alias("root")), "rooted")
    names = written(rooted.groupBy("root").agg(F.min(F.struct("id", "hash")).alias("least")).select("root", F.col("least.id").alias("comp"), F.col("least.hash").alias("comp_hash")), "names")
    return found, rooted.drop("id", "hash").join(names, "root").drop("root")


def groups(docs: DataFrame, key: str = "doc_id", text: str = "text", link: int = LINK) -> DataFrame:
    """Set size, component and whether it is kept (the smallest id of its
    component), for every row of docs."""
    found, placed = _placed(docs, key, text, link)
    name = lambda c: F.when(c != NULL_ID, c)
    comp = F.coalesce("comp", "id")
    rows = found.select("id", "n_shingles", "f1", "f2").join(placed, ["f1", "f2", "n_shingles"], "left")
    return rows.select(name(F.col("id")).alias(key), F.col("n_shingles"), name(comp).alias("component_id"), (F.col("id") == comp).alias("kept"))


def one_of_each(docs: DataFrame, key: str = "doc_id", text: str = "text", link: int = LINK) -> DataFrame:
    """One row of docs for each component, unchanged, and every row without
    words."""
    found, placed = _placed(docs.select(key, text), key, text, link)
    mark = "_"
    while any(c.startswith(mark) for c in docs.columns):
        mark += "_"
    own = [c.alias(mark + n) for c, n in zip(_named(key, text), ("id", "hash"), strict=True)]
    same = [mark + n for n in ("id", "hash")]
    first = placed.select(F.col("comp").alias(same[0]), F.col("comp_hash").alias(same[1]), F.lit(False).alias(mark + "alone"))
    alone = found.where("n_shingles = 0").select(F.col("id").alias(same[0]), F.col("hash").alias(same[1]), F.lit(True).alias(mark + "alone"))
    chosen = first.unionByName(alone).distinct()
    # rows of one id and text are told apart only where all of them stay; the
    # join has already dealt the rows by id and text
    rows = docs.select("*", *own).join(chosen, same).withColumn(mark + "row", F.when(F.col(mark + "alone"), F.monotonically_increasing_id()))
    return rows.dropDuplicates([*same, mark + "row"]).select(*docs.columns)
