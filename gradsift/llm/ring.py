"""Sharding on a consistent-hash ring with virtual nodes and bounded loads.

The ring has SLOTS positions. Every shard stands on it at `vnodes` of them
(hashed), and a key belongs to the first node clockwise of its own slot.
Shards have a bounded load; keys that overflow a full shard go on clockwise
to the next shard with room. With no slack the bounds add up to the number of
rows, so that row counts differ by one at most: law `rows`.

Three relations, all of DataFrame expressions:

1. one scan of the input gives key, size and checksum, with equal rows
   counted before they are shuffled; it is written once, without the texts;
2. slots are split into cells of about CELL_ROWS rows by a hash of the row;
   counts by cell (SLOTS cells and one for CELL_ROWS rows at most: 30 MB for
   10**12 rows) give each cell its first rank on its arc, the stretch before
   one node. The driver sees one count for each arc, SHARDS * vnodes numbers
   whatever the input, and plans from these which ranks of an arc go to which
   shard;
3. a row's rank on its arc is its cell's first rank plus its rank there; the
   plan, a bounded table, turns it into shard and slot number.

One key with a third of all rows falls into one slot, which is split into as
many cells as its rows need. Equal rows are one counted row until the end;
where they are more than PIECE, their ranks are dealt out in pieces of that
many before they become rows again, so that no task makes them all.

Defined results: null ids are a key like any other, null texts have size 1
and checksum 0; repeated rows each get a slot; an empty input gives no rows.
"""

from __future__ import annotations

from bisect import bisect_left

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from gradsift.llm.shared import written

SHARDS = 16
VNODES = 64
SLOTS = 4096
CELL_ROWS = 1 << 20
PIECE = 1 << 16


def slot_of(*columns: Column) -> Column:
    return F.pmod(F.xxhash64(F.lit("slot"), *columns), F.lit(SLOTS)).cast("int")


def nodes_of(spark: SparkSession, shards: int, vnodes: int) -> list[tuple[int, int]]:
    """(slot, shard) of all virtual nodes in ring order; on one slot, the
    lower shard comes first."""
    n = spark.range(shards * vnodes).select((F.col("id") % shards).cast("int").alias("shard"), F.floor(F.col("id") / shards).alias("copy"))
    return sorted((r["slot"], r["shard"]) for r in n.select("shard", slot_of(F.lit("node"), "shard", "copy").alias("slot")).collect())


def preferences(nodes: list[tuple[int, int]], shards: int) -> list[list[int]]:
    """For each arc, the shards in the order in which its keys meet them."""
    out = []
    for at in range(len(nodes)):
        seen = dict.fromkeys(nodes[(at + i) % len(nodes)][1] for i in range(len(nodes)))
        out.append(list(seen))
    assert all(len(p) == shards for p in out)
    return out


def bounds(rows: int, shards: int, slack: float) -> list[int]:
    """Most rows of each shard. Without slack the first ones take the odd rows."""
    if slack:
        return [int(-(-(rows * (1 + slack)) // shards))] * shards
    return [rows // shards + (s < rows % shards) for s in range(shards)]


def plan(counts: list[int], prefer: list[list[int]], room: list[int]) -> list[tuple[int, int, int, int, int]]:
    """(arc, first rank, end rank, shard, first slot number) of every stretch.

    In round r the keys still without a place knock at the r-th shard of
    their arc; first choices of all arcs go before any second choice, which
    keeps the number of moved keys low.
    """
    room, used, done, out = list(room), [0] * len(room), [0] * len(counts), []
    for r in range(len(room)):
        for arc, total in enumerate(counts):
            shard = prefer[arc][r]
            n = min(total - done[arc], room[shard])
            if n > 0:
                out.append((arc, done[arc], done[arc] + n, shard, used[shard]))
                done[arc] += n
                used[shard] += n
                room[shard] -= n
    return out


def _in_pieces(ranked: DataFrame) -> DataFrame:
    """Counted rows in parts of at most PIECE ranks, dealt over all tasks."""
    cut = ranked.select("key", "size", "crc", "arc", "from", "n", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1, F.lit(PIECE).cast("long"))).alias("skip"))
    cut = cut.select("key", "size", "crc", "arc", (F.col("from") + F.col("skip")).alias("from"), F.least(F.lit(PIECE).cast("long"), F.col("n") - F.col("skip")).alias("n"))
    return cut.repartition("arc", "from")


def assign(docs: DataFrame, key: str = "doc_id", text: str = "text", shards: int = SHARDS, vnodes: int = VNODES, slack: float = 0.0) -> DataFrame:
    """Shard, slot number and home shard of every row of docs, with key,
    size and checksum. grown_shard is null: the law is `rows`."""
    spark = docs.sparkSession
    rows = docs.select(
        F.col(key).alias("key"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + F.lit(1)).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col(text), F.lit("")).cast("binary")).alias("crc"),
    )
    rows = rows.groupBy("key", "size", "crc").agg(F.count("*").alias("n"))
    rows = written(rows.select("*", slot_of("key").alias("slot")), "ring-rows")
    cells_of = rows.groupBy("slot").agg(F.ceil(F.sum("n") / F.lit(CELL_ROWS)).alias("cells"))
    rows = rows.join(F.broadcast(cells_of), "slot").withColumn("cell", F.pmod(F.xxhash64("key", "size", "crc"), F.col("cells"))).drop("cells")

    nodes = nodes_of(spark, shards, vnodes)
    places = [s for s, _ in nodes]
    arcs = F.array(*[F.lit(bisect_left(places, s) % len(nodes)) for s in range(SLOTS)])
    cells = rows.groupBy("slot", "cell").agg(F.sum("n").alias("n"), F.max("n").alias("most")).select("*", F.element_at(arcs, F.col("slot") + 1).alias("arc"))
    by_arc = {r["arc"]: (r["n"], r["most"]) for r in cells.groupBy("arc").agg(F.sum("n").alias("n"), F.max("most").alias("most")).collect()}
    counts = [by_arc.get(a, (0, 0))[0] for a in range(len(nodes))]
    pieces = plan(counts, preferences(nodes, shards), bounds(sum(counts), shards, slack))
    before = Window.partitionBy("arc").orderBy("slot", "cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = cells.select("slot", "cell", "arc", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))

    text_plan = ";".join(",".join(map(str, p)) for p in pieces)
    field = lambda i: F.element_at(F.split("p", ","), i + 1).cast("long")
    stretch = spark.range(1 if pieces else 0).select(F.explode(F.split(F.lit(text_plan), ";")).alias("p"))
    stretch = stretch.select(field(0).cast("int").alias("arc"), field(1).alias("lo"), field(2).alias("hi"), field(3).cast("int").alias("shard"), field(4).alias("at"))

    inside = Window.partitionBy("slot", "cell").orderBy("key", "size", "crc").rowsBetween(Window.unboundedPreceding, -1)
    ranked = rows.withColumn("first", F.coalesce(F.sum("n").over(inside), F.lit(0)))
    ranked = ranked.join(F.broadcast(cells), ["slot", "cell"]).select("key", "size", "crc", "arc", (F.col("base") + F.col("first")).alias("from"), "n")
    if max((most for _, most in by_arc.values()), default=0) > PIECE:
        ranked = ranked.where(F.col("n") <= PIECE).unionByName(_in_pieces(ranked.where(F.col("n") > PIECE)))
    ranked = ranked.select("key", "size", "crc", "arc", F.explode(F.sequence(F.col("from"), F.col("from") + F.col("n") - 1)).alias("rank"))
    placed = ranked.join(F.broadcast(stretch), "arc").where((F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    home = F.array(*[F.lit(s) for _, s in nodes])
    return placed.select(
        F.col("key").alias(key),
        "size",
        F.col("crc").alias("text_crc32"),
        F.lit("rows").alias("law"),
        "shard",
        (F.col("at") + F.col("rank") - F.col("lo")).alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
        F.element_at(home, F.col("arc") + 1).alias("home_shard"),
    )
