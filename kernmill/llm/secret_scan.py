"""Secret scan with corpus-wide ownership, DataFrame functions only.

Three base patterns give spans in code points. A fourth kind, ``opaque``, adds
long tokens of mixed letters and digits outside base spans, but only where the
corpus shows few owners. Every candidate value is hashed and counted over the
corpus by distinct owners and repositories: values many owners hold are copied
examples, values of one or few owners look live. Counting goes by (value,
owner, repository) first, so a value that a third of all rows hold is summed
before it meets other rows.

Null text counts as empty, a null owner as one owner of its own; null doc_id and
repeated rows keep their rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bounded_broadcast, let, salted_join, small_enough, stage

#: The base patterns; quantifiers of access and hex hold the least length.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
OPAQUE = r"[A-Za-z0-9+/_-]{32,}"
KINDS = ("assign", "access", "hex", "opaque")
LIVE_OWNERS, LIVE_REPOSITORIES = 2, 4
BROADCAST_ROWS = 500_000
_NONE = "cast(array() as array<struct<kind:int,start:bigint,end:bigint,value:string>>)"


def spans(text: Column, pattern: str, kind: int, group: int = 0) -> Column:
    """Structs (kind, start, end, value) of all matches: the pieces between matches give the offsets."""

    def found(matches, pieces, values):
        start = F.struct(F.lit(0).cast("long").alias("at"), F.expr(_NONE).alias("out"))

        def step(acc, i):
            begin = acc["at"] + F.length(F.element_at(pieces, i))
            end = begin + F.length(F.element_at(matches, i))
            one = F.struct(F.lit(kind).alias("kind"), begin.alias("start"), end.alias("end"), F.element_at(values, i).alias("value"))
            return F.struct(end.alias("at"), F.concat(acc["out"], F.array(one)).alias("out"))

        return F.aggregate(F.sequence(F.lit(1), F.size(matches)), start, step, lambda acc: acc["out"])

    def all_of(n):
        return F.regexp_extract_all(text, F.lit(pattern), n)

    def one_row(m):
        split = let(F.split(text, pattern, -1), lambda p: found(m, p, m) if group == 0 else let(all_of(group), lambda v: found(m, p, v)))
        return F.when(F.size(m) > 0, split).otherwise(F.expr(_NONE))

    return let(all_of(0), one_row)


def located(docs: DataFrame, owner: str = "source", repository: str | None = None) -> DataFrame:
    """Columns of ``docs`` under ``row``, its text, owner, repository and ``found``, all spans of all kinds that may be secrets."""
    whole = docs.select(
        F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
        F.coalesce(F.col(owner).cast("string"), F.lit("")).alias("owner") if owner in docs.columns else F.lit("").alias("owner"),
        F.coalesce(F.col(repository or owner).cast("string"), F.lit("")).alias("repository") if (repository or owner) in docs.columns else F.lit("").alias("repository"),
    )
    text = F.col("text")
    base = F.concat(F.filter(spans(text, ASSIGN, 0, 2), lambda s: F.length(s["value"]) >= 6), spans(text, ACCESS, 1), spans(text, HEX, 2))
    mixed = F.filter(spans(text, OPAQUE, 3), lambda s: s["value"].rlike("[0-9]") & s["value"].rlike("[A-Za-z]"))

    def both(pair):
        apart = F.filter(pair["mixed"], lambda m: ~F.exists(pair["base"], lambda b: (b["start"] < m["end"]) & (m["start"] < b["end"])))
        return F.concat(pair["base"], apart)

    return whole.withColumn("found", let(F.struct(base.alias("base"), mixed.alias("mixed")), both))


def ownership(found: DataFrame) -> DataFrame:
    """(value_id, owners, repositories) of every candidate value."""
    each = found.select("owner", "repository", F.explode("found").alias("s")).select("owner", "repository", F.sha2("s.value", 256).alias("value_id"))
    pairs = each.groupBy("value_id", "owner", "repository").agg(F.lit(1).alias("one"))
    owners = pairs.groupBy("value_id", "owner").agg(F.count("*").alias("r"))
    return owners.groupBy("value_id").agg(F.count("*").alias("owners"), F.sum("r").alias("repositories"))


def _key() -> list[Column]:
    return [F.xxhash64("row").alias("k1"), F.hash("row").alias("k2")]


def scan(docs: DataFrame, owner: str = "source", repository: str | None = None, live_owners: int = LIVE_OWNERS, live_repositories: int = LIVE_REPOSITORIES) -> DataFrame:
    """row (all of docs), text and ``spans``: array of (start, kind, end, owners, live), in order of start, then kind.

    A value is live if at most ``live_owners`` owners and ``live_repositories`` of
    their repositories hold it. The patterns run over the texts once: rows with
    candidates are staged, judged, and met by the hashes of whole rows.
    """
    whole = located(docs, owner, repository)
    found = stage(whole.where(F.size("found") > 0).select(*_key(), "owner", "repository", "found"))
    held = stage(ownership(found))
    each = found.dropDuplicates(["k1", "k2"]).select("k1", "k2", F.explode("found").alias("s")).withColumn("value_id", F.sha2("s.value", 256))
    judged = each.join(F.broadcast(held), "value_id") if small_enough(held, BROADCAST_ROWS) else salted_join(each, held, "value_id", "k1")
    live = (F.col("owners") <= live_owners) & (F.col("repositories") <= live_repositories)
    span = F.struct(F.col("s.start").alias("start"), F.col("s.kind").alias("kind"), F.col("s.end").alias("end"), "owners", live.alias("live"))
    known = judged.where((F.col("s.kind") < 3) | live).groupBy("k1", "k2").agg(F.array_sort(F.collect_list(span)).alias("spans"))
    known = bounded_broadcast(stage(known), BROADCAST_ROWS)
    none = F.expr("cast(array() as array<struct<start:bigint,kind:int,end:bigint,owners:bigint,live:boolean>>)")
    rows = whole.select("row", "text", *_key())
    return rows.join(known, ["k1", "k2"], "left").select("row", "text", F.coalesce("spans", none).alias("spans"))


def _listed(of: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(of, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def report(docs: DataFrame, **options) -> DataFrame:
    """Per row: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_copied."""
    got = scan(docs, **options)
    base = F.filter("spans", lambda s: s["kind"] < 3)

    def n(kind: int) -> Column:
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")

    return got.select(
        F.col("row.doc_id").cast("long").alias("doc_id"),
        n(0).alias("n_assign"),
        n(1).alias("n_access"),
        n(2).alias("n_hex"),
        F.sha2(_listed(base), 256).alias("base_sha256"),
        _listed(F.col("spans")).alias("spans"),
        F.size(F.filter("spans", lambda s: s["live"])).cast("long").alias("n_live"),
        F.size(F.filter("spans", lambda s: ~s["live"])).cast("long").alias("n_copied"),
    )


def redact(docs: DataFrame, placeholder: str = "[SECRET]", **options) -> DataFrame:
    """``docs`` with every span replaced; overlapping spans become one placeholder. Other columns stay as they are."""
    got = scan(docs, **options)
    start = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out"))

    def step(acc, s):
        gap = F.when(s["start"] >= acc["at"], F.concat(F.substring(F.col("text"), acc["at"].cast("int") + 1, (s["start"] - acc["at"]).cast("int")), F.lit(placeholder))).otherwise("")
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.concat(acc["out"], gap).alias("out"))

    rest = F.aggregate("spans", start, step, lambda acc: F.concat(acc["out"], F.substring(F.col("text"), acc["at"].cast("int") + 1, F.length("text"))))
    clean = F.when(F.size("spans") > 0, rest).otherwise(F.col("row.text"))
    return got.select(*[clean.alias(c) if c == "text" else F.col(f"row.`{c}`").alias(c) for c in docs.columns])
