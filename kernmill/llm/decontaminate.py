"""Benchmark decontamination by winnowed fingerprints, DataFrame functions only.

Words of documents and items are cut into runs of GRAM words, each hashed, and
of every WINDOW - GRAM + 1 neighbouring hashes the smallest is kept. Any shared
run of WINDOW words then shares a kept fingerprint, so joining fingerprints
misses none. Documents with a fingerprint in common are compared window by
window as text, which extends hits to whole spans. Items of fewer than WINDOW
words are one window each and are looked up at their own length.

Null or wordless texts have no words and no hits; items without words never
occur; repeated documents each get their row. The benchmark side is broadcast
only below ``BROADCAST_ROWS`` counted rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, bounded_broadcast, let, stage

WINDOW, GRAM = 10, 5
BROADCAST_ROWS = 500_000
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words(text: Column) -> Column:
    return F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), SEPARATORS), lambda w: w != "")


def _empty(kind: str) -> Column:
    return F.expr(f"cast(array() as array<{kind}>)")


def _winnowed(w: Column) -> Column:
    """Distinct winnowed hashes of at least WINDOW words; else empty."""
    span = WINDOW - GRAM + 1

    def least(g):
        return F.transform(F.sequence(F.lit(1), F.size(g) - (span - 1)), lambda i: F.array_min(F.slice(g, i, span)))

    grams = F.transform(F.sequence(F.lit(1), F.size(w) - (GRAM - 1)), lambda i: F.xxhash64(F.slice(w, i, GRAM)))
    return F.when(F.size(w) >= WINDOW, F.array_distinct(let(grams, least))).otherwise(_empty("bigint"))


def _cut(w: Column, length: int) -> Column:
    """All runs of ``length`` words, in order."""
    cut = F.transform(F.sequence(F.lit(1), F.size(w) - (length - 1)), lambda i: F.array_join(F.slice(w, i, length), " "))
    return F.when(F.size(w) >= length, cut).otherwise(_empty("string"))


def prints_of(text: Column, lengths: list[int]) -> Column:
    """Distinct (length, print) of a text in one pass over its words: winnowed hashes under WINDOW, and hashes of all runs of each shorter length."""

    def hashed(w, n):
        return F.transform(F.array_distinct(_cut(w, n)), lambda r: F.struct(F.lit(n).alias("length"), F.xxhash64(r).alias("print")))

    def all_of(w):
        long = F.transform(_winnowed(w), lambda p: F.struct(F.lit(WINDOW).alias("length"), p.alias("print")))
        return F.concat(long, *[hashed(w, n) for n in lengths])

    return let(words(text), all_of)


def fingerprints(text: Column) -> Column:
    """Distinct winnowed hashes of a text of at least WINDOW words; else empty."""
    return let(words(text), _winnowed)


def runs(text: Column, length: int) -> Column:
    """All runs of ``length`` words of a text, in order."""
    return let(words(text), lambda w: _cut(w, length))


def placed_runs(text: Column, lengths: list[int]) -> Column:
    """(length, pos, run) of all runs of all ``lengths``, pos from 0."""

    def at(w, n):
        return F.transform(_cut(w, n), lambda r, i: F.struct(F.lit(n).alias("length"), i.alias("pos"), r.alias("run")))

    return let(words(text), lambda w: F.concat(*[at(w, n) for n in lengths]))


def _windows(benchmark: DataFrame) -> DataFrame:
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text", words(F.col("text")).alias("w")).where("item_id IS NOT NULL AND size(w) > 0")
    long = items.where(F.size("w") >= WINDOW).select("item_id", F.lit(WINDOW).alias("length"), F.explode(runs(F.col("text"), WINDOW)).alias("run"))
    short = items.where(F.size("w") < WINDOW).select("item_id", F.size("w").alias("length"), F.array_join("w", " ").alias("run"))
    return long.union(short).distinct()


def hits(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, mark, pos, length, item_id): every occurrence of an item's window, pos from 0; mark tells texts with one doc_id apart.

    One pass over the texts finds those with a print in common, another compares them as text.
    """
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"), F.col("text").cast("string").alias("text"))
    windows = stage(_windows(benchmark))
    short = sorted(r[0] for r in windows.where(F.col("length") < WINDOW).select("length").distinct().collect())  # nine values at most
    long_prints = benchmark.select(F.lit(WINDOW).alias("length"), F.explode(fingerprints(F.col("text"))).alias("print"))
    prints = long_prints.union(windows.where(F.col("length") < WINDOW).select("length", F.xxhash64("run"))).distinct()
    prints = bounded_broadcast(stage(prints), BROADCAST_ROWS)
    shared = source.select("doc_id", "mark", F.inline(prints_of(F.col("text"), short))).join(prints, ["length", "print"], "left_semi").select("doc_id", "mark")
    marked = bounded_broadcast(stage(shared.distinct()), BROADCAST_ROWS)
    near = source.join(marked, [source.doc_id.eqNullSafe(marked.doc_id), source.mark == marked.mark], "left_semi").dropDuplicates(["doc_id", "mark"])
    at = near.select("doc_id", "mark", F.inline(placed_runs(F.col("text"), [WINDOW, *short])))
    return at.join(bounded_broadcast(windows, BROADCAST_ROWS), ["length", "run"]).select("doc_id", "mark", "pos", "length", "item_id")


def covered(spans: Column) -> Column:
    """Positions covered by an array of (pos, length) structs."""
    start = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))

    def step(acc, x):
        end = x["pos"] + x["length"]
        fresh = F.greatest(end - F.greatest(acc["end"], x["pos"]), F.lit(0))
        return F.struct(F.greatest(acc["end"], end).alias("end"), (acc["n"] + fresh).alias("n"))

    return F.aggregate(F.array_sort(spans), start, step, lambda acc: acc["n"])


def contamination(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, n_words, n_hit, n_items, items_sha256, contaminated) per row of ``docs``."""
    found = hits(docs, benchmark)
    per = found.groupBy("doc_id", "mark").agg(F.collect_set(F.struct("pos", "length")).alias("spans"), F.array_sort(F.collect_set("item_id")).alias("items"))
    per = stage(per.select(F.col("doc_id").alias("d"), F.col("mark").alias("m"), covered(F.col("spans")).alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256")))
    per = bounded_broadcast(per, BROADCAST_ROWS)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"), F.size(words(F.col("text"))).cast("long").alias("n_words"))
    return rows.join(per, [F.col("doc_id").eqNullSafe(F.col("d")), F.col("mark") == F.col("m")], "left").select(
        "doc_id",
        "n_words",
        F.coalesce("n_hit", F.lit(0).cast("long")).alias("n_hit"),
        F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"),
        F.coalesce("items_sha256", F.sha2(F.lit(""), 256)).alias("items_sha256"),
        (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
    )


def remove_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Rows of ``docs`` in which no item's window occurs."""
    found = hits(docs, benchmark).select(F.col("doc_id").alias("d"), F.col("mark").alias("m")).distinct()
    found = bounded_broadcast(stage(found), BROADCAST_ROWS)
    return docs.join(found, [docs["doc_id"].cast("long").eqNullSafe(found["d"]), F.xxhash64(docs["text"]) == found["m"]], "left_anti")
