"""Secret scan with corpus-wide ownership frequency, of SQL expressions only.

Base kinds are patterns: assignments, access keys, hex runs. Beside them
stands a broad kind, `run`: 20 or more characters of the base64 or identifier
alphabets, with letters and digits. Every found value is hashed, and the
hashes are counted over all texts by distinct repository and owner. A value
of many owners or repositories is an example that people copy; a value of one
owner, with enough different characters, looks live. Live-looking runs that
touch no base span are added to the spans as kind `owned`.

Spark gives no positions of pattern matches, but their lengths and those of
the text between them (split by the same pattern) add up to them. Runs are
looked for in a copy of the text in which base assignments are blotted out;
the other base kinds lie inside one run, so every test for a touch is a pattern
and the work on a text grows with its length, not with pairs of matches.

The tables have no column of repositories: unless one is named, every document
is its own, and a value that one source repeats in more than a few documents
counts as copied. Ownership decides n_live and n_copied for values of all
kinds, and the spans of kind `owned`.

Skew: owners are counted on (value, owner, repository) sets that are made
unique before they meet by value, so a value of a third of all texts is
counted from partial sums; the join of spans and verdicts is an ordinary
sort-merge join, whose hot side Spark splits.

Defined results: null and empty texts have no spans; a null owner or
repository counts as one of its own; equal rows get equal results.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gradsift.llm.shared import written

#: Fixed values of the contract, as Java patterns. Runs of a minimum length
#: are the maximal runs that reach it.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}"
#: A run is taken whole or not at all: not from its middle, and not if a
#: blotted-out assignment stands beside what is left of it.
RUN = r"(?<![A-Za-z0-9+/_=\x01-])[A-Za-z0-9+/_=-]{20,}+(?!\x01)"
#: What blots out an assignment, and what stands for it where a text has it
#: already; no other pattern matches either.
BLOT, CLEAR = "\x01", "\x02"
LEAST_ASSIGNED = 12

#: The order of kinds that start together.
KINDS = ("assign", "access", "hex", "owned")

#: Values of more owners, or more repositories of one owner, are examples.
MOST_OWNERS = 1
MOST_REPOSITORIES = 3
LEAST_DISTINCT = 8


def _hits(text: Column, pattern: str) -> Column:
    """array<struct<gap, value>> of all matches, in order: the length of the
    text since the match before, and the match."""
    parts = F.zip_with(F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda b, h: F.struct(F.length(b).alias("gap"), h.alias("value")))
    found = F.filter(parts, lambda x: x["value"].isNotNull())
    return F.when(text.rlike(pattern), found).otherwise(F.expr("cast(array() as array<struct<gap:int,value:string>>)"))


def _running(steps: str) -> Column:
    """Sums of the elements before each one, of an array column of int. The
    array is cut into about sqrt(n) blocks of sqrt(n), each folded by itself
    and then moved by the sum of the blocks before it, so that no fold has to
    copy a list that grows to n."""
    empty = F.expr("cast(array() as array<int>)")
    width = F.greatest(F.ceil(F.sqrt(F.size(steps))), F.lit(1)).cast("int")
    starts = F.sequence(F.lit(1), F.greatest(F.size(steps), F.lit(1)), width)
    fold = lambda block: F.aggregate(
        block,
        F.struct(F.lit(0).alias("at"), empty.alias("out")),
        lambda s, x: F.struct((s["at"] + x).alias("at"), F.concat(s["out"], F.array(s["at"])).alias("out")),
    )
    blocks = F.transform(starts, lambda i: fold(F.slice(steps, i, width)))
    moved = F.aggregate(
        blocks,
        F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<array<int>>)").alias("out")),
        lambda s, b: F.struct((s["at"] + b["at"]).alias("at"), F.concat(s["out"], F.array(F.transform(b["out"], lambda x: x + s["at"]))).alias("out")),
    )
    return F.flatten(moved["out"])


def _spans(hits: str, before: str, kind: int) -> Column:
    """array<struct<start, kind, end, value>> from the hits and what stands
    before each of them."""

    def span(x: Column, at: Column) -> Column:
        start = at + x["gap"]
        return F.struct(start.alias("start"), F.lit(kind).alias("kind"), (start + F.length(x["value"])).alias("end"), x["value"].alias("value"))

    return F.zip_with(hits, before, span)


def _assigned(hit: Column) -> Column:
    """The value of an assignment."""
    return F.regexp_extract(hit, ASSIGN, 2)


def _masked(text: Column) -> Column:
    """The text, of the same length, with every base assignment blotted out."""
    blot = lambda h: F.when(F.length(_assigned(h)) >= LEAST_ASSIGNED, F.repeat(F.lit(BLOT), F.length(h))).otherwise(h)
    clear = F.translate(text, BLOT, CLEAR)
    parts = F.zip_with(F.split(clear, ASSIGN, -1), F.regexp_extract_all(clear, F.lit(ASSIGN), F.lit(0)), lambda b, h: F.concat(b, F.coalesce(blot(h), F.lit(""))))
    return F.when(text.rlike(ASSIGN), F.array_join(parts, "")).otherwise(clear)


def _shown(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def _sorted(spans: Column) -> Column:
    return F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end"))))


def candidates(docs: DataFrame, key: str, text: str, owner: str, repository: str) -> DataFrame:
    """One row per row of docs: base spans, and the live-looking runs that
    touch none of them."""
    t = F.coalesce(F.col(text), F.lit(""))
    out = docs.select(F.col(key).alias("key"), F.xxhash64(t).alias("body"), F.col(owner).cast("string").alias("owner"), F.col(repository).cast("string").alias("repository"), t.alias("t"))
    kinds = {"a": F.col("t"), "b": F.col("t"), "c": F.col("t"), "r": F.col("m")}
    out = out.withColumn("m", _masked(F.col("t")))
    out = out.select("key", "body", "owner", "repository", *[_hits(source, p).alias(k) for (k, source), p in zip(kinds.items(), (ASSIGN, ACCESS, HEX, RUN), strict=True)])
    out = out.select("*", *[F.transform(k, lambda x: x["gap"] + F.length(x["value"])).alias(f"{k}_steps") for k in kinds])
    out = out.select("*", *[_running(f"{k}_steps").alias(f"{k}_before") for k in kinds])
    out = out.select("key", "body", "owner", "repository", *[_spans(k, f"{k}_before", i).alias(k) for i, k in enumerate(kinds)])
    out = out.withColumn("a", F.transform("a", lambda s: s.withField("value", _assigned(s["value"]))))
    out = out.withColumn("a", F.filter("a", lambda s: F.length(s["value"]) >= LEAST_ASSIGNED))
    out = out.withColumn("base", F.concat("a", "b", "c"))
    # a run that holds an access key or a hex run touches a base span
    free = lambda v: ~v.rlike(ACCESS) & ~v.rlike(HEX)
    mixed = lambda v: v.rlike("[0-9]") & v.rlike("[A-Za-z]") & (F.size(F.array_distinct(F.split(v, ""))) >= LEAST_DISTINCT)
    out = out.withColumn("r", F.filter("r", lambda s: free(s["value"]) & mixed(s["value"])))
    hashed = lambda spans: F.transform(spans, lambda s: F.struct(s["start"], s["kind"], s["end"], F.md5(s["value"]).alias("value")))
    return out.select("key", "body", "owner", "repository", F.size("a").cast("long").alias("n_assign"), F.size("b").cast("long").alias("n_access"), F.size("c").cast("long").alias("n_hex"), _sorted(F.col("base")).alias("base"), hashed(F.concat("base", "r")).alias("found"))


def ownership(found: DataFrame) -> DataFrame:
    """Distinct owners and repositories of every value."""
    each = found.select("owner", "repository", F.explode("found").alias("f")).select(F.col("f.value").alias("value"), "owner", "repository").distinct()
    by_owner = each.groupBy("value", "owner").agg(F.count("*").alias("n"))
    return by_owner.groupBy("value").agg(F.count("*").alias("owners"), F.sum("n").alias("repositories"))


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", owner: str = "source", repository: str = "doc_id", most_owners: int = MOST_OWNERS, most_repositories: int = MOST_REPOSITORIES) -> DataFrame:
    """Spans of every row, and how many of its values look live or copied."""
    rows = written(candidates(docs, key, text, owner, repository), "secret-candidates")
    some = rows.where(F.size("found") > 0)
    verdict = ownership(some).select("value", ((F.col("owners") <= most_owners) & (F.col("repositories") <= most_repositories)).alias("live"))
    each = some.select("key", "body", F.explode("found").alias("f")).select("key", "body", "f.start", "f.kind", "f.end", "f.value").distinct()
    owned = F.when(F.col("live") & (F.col("kind") == 3), F.struct("start", "kind", "end"))
    by_row = each.join(verdict, "value").groupBy("key", "body").agg(F.collect_list(owned).alias("added"), F.count_if("live").alias("n_live"), F.count_if(~F.col("live")).alias("n_copied"))
    by_row = by_row.select(F.col("key").alias("k"), F.col("body").alias("t"), "added", "n_live", "n_copied")
    joined = rows.join(by_row, F.col("key").eqNullSafe(F.col("k")) & (F.col("body") == F.col("t")), "left")
    spans = _sorted(F.concat("base", F.coalesce("added", F.expr("cast(array() as array<struct<start:int,kind:int,end:int>>)"))))
    return joined.select(
        F.col("key").alias(key),
        "n_assign",
        "n_access",
        "n_hex",
        F.sha2(_shown(F.col("base")), 256).alias("base_sha256"),
        _shown(spans).alias("spans"),
        F.coalesce("n_live", F.lit(0)).alias("n_live"),
        F.coalesce("n_copied", F.lit(0)).alias("n_copied"),
    )
