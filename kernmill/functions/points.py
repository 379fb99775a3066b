"""From tables to points (idx, key, x): feature builders and the point sets of the workloads."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.store import materialize, table


def dense_index(df: DataFrame, keys: list[str], partitions: int | None = None) -> DataFrame:
    """Adds idx, the rank by ``keys`` from 0; the keys must be unique together.

    With several partitions (by default the session's shuffle partitions) the rows are dealt by ranges of the keys and staged,
    each range is numbered by itself, and the counts of the ranges before give
    the offset: no single task sees all rows.
    """
    partitions = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    if partitions <= 1:
        return df.withColumn("idx", (F.row_number().over(Window.orderBy(*keys)) - 1).cast("long"))
    dealt = materialize(df.repartitionByRange(partitions, *keys).withColumn("part", F.spark_partition_id()))
    counts = {r.part: r["count"] for r in dealt.groupBy("part").count().collect()}
    before, total = {}, 0
    for p in sorted(counts):
        before[p] = total
        total += counts[p]
    offsets = F.create_map(*[F.lit(v) for p in before for v in (p, before[p])]) if before else F.create_map(F.lit(0), F.lit(0))
    rank = F.row_number().over(Window.partitionBy("part").orderBy(*keys)) - 1
    return dealt.withColumn("idx", (rank + offsets[F.col("part")]).cast("long")).drop("part")


def assemble(*cols) -> Column:
    return F.array(*[F.col(c).cast("double") if isinstance(c, str) else c.cast("double") for c in cols])


def standardize(df: DataFrame, cols: list[str]) -> DataFrame:
    """z-scores over all rows of ``df``; a column without spread becomes 0."""
    stats = df.agg(*[f(c).alias(f"{c}_{name}") for c in cols for name, f in (("m", F.avg), ("s", F.stddev_pop))])
    out = df.crossJoin(F.broadcast(stats))
    for c in cols:
        out = out.withColumn(c, F.when(F.col(f"{c}_s") > 0, (F.col(c) - F.col(f"{c}_m")) / F.col(f"{c}_s")).otherwise(F.lit(0.0)))
    return out.drop(*stats.columns)


def minmax(df: DataFrame, cols: list[str]) -> DataFrame:
    stats = df.agg(*[f(c).alias(f"{c}_{name}") for c in cols for name, f in (("lo", F.min), ("hi", F.max))])
    out = df.crossJoin(F.broadcast(stats))
    for c in cols:
        out = out.withColumn(c, F.when(F.col(f"{c}_hi") > F.col(f"{c}_lo"), (F.col(c) - F.col(f"{c}_lo")) / (F.col(f"{c}_hi") - F.col(f"{c}_lo"))).otherwise(F.lit(0.0)))
    return out.drop(*stats.columns)


def l2_normalize(x: Column) -> Column:
    """Unit vectors; a zero vector stays."""
    norm = F.sqrt(F.aggregate(x, F.lit(0.0), lambda a, v: a + v * v))
    return F.transform(x, lambda v: F.when(norm > 0, v / norm).otherwise(v))


def one_hot(col: str, values: list) -> list[Column]:
    return [F.when(F.col(col) == v, 1.0).otherwise(0.0) for v in values]


def cyclic(value: Column, period: float) -> list[Column]:
    turn = value * F.lit(2 * math.pi / period)
    return [F.sin(turn), F.cos(turn)]


def token_bucket(token: Column, m: int) -> Column:
    """Bucket of a token from the first eight hex digits of its md5: the same in any engine."""
    return (F.conv(F.substring(F.md5(token.cast("binary")), 1, 8), 16, 10).cast("long") % m).cast("int")


def filter_valid(points: DataFrame, on_invalid: str = "error") -> DataFrame:
    """Points whose vector is whole and finite; ``drop`` leaves the others out, ``error`` raises on them."""
    good = F.col("x").isNotNull() & (F.size("x") > 0) & F.forall("x", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) != float("inf")))
    if on_invalid == "drop":
        return points.where(good)
    if points.where(~good | good.isNull()).limit(1).count():
        raise ValueError("a vector is null, empty or not finite")
    return points


def sample_n(df: DataFrame, n: int, keys: list[str], seed: int = 0) -> DataFrame:
    """Exactly n rows (or all), by md5 order of the keys and the seed."""
    mark = F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.col(k).cast("string") for k in keys]).cast("binary"))
    return df.orderBy(mark, *keys).limit(n)


def sampled(points: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """n of the points, drawn by md5 order of their keys and numbered anew; ``points`` has idx, key, x."""
    return dense_index(sample_n(points.select("key", "x"), n, ["key"], seed), ["key"], 1).select("idx", "key", "x")


def sample_features(points: DataFrame, m: int, dim: int, seed: int = 0) -> DataFrame:
    """Keeps m of ``dim`` features, drawn by the seed, in their order."""
    import numpy as np

    kept = np.sort(np.random.Generator(np.random.PCG64(seed)).choice(dim, size=min(m, dim), replace=False))
    return points.withColumn("x", F.array(*[F.col("x")[int(i)] for i in kept]))


def project(points: DataFrame, m: int, dim: int, seed: int = 0) -> DataFrame:
    """Gaussian projection to m dimensions (approximate distances)."""
    import numpy as np

    r = np.random.Generator(np.random.PCG64(seed)).normal(0, 1 / math.sqrt(m), (m, dim))
    rows = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in r])
    return points.withColumn("x", F.transform(rows, lambda w: F.aggregate(F.zip_with("x", w, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)))


# --- point sets ---------------------------------------------------------------

LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
LINE4 = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def mini(spark: SparkSession, sf_dir: str = "") -> DataFrame:
    return spark.createDataFrame([(0, 0, [1.0], 0), (1, 1, [2.0], 1), (2, 2, [-1.0], 0), (3, 3, [-2.0], 1)], "idx long, key long, x array<double>, truth int")


def emb(spark: SparkSession, sf_dir: str, n: int | None = None) -> DataFrame:
    rows = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("key"), F.col("embedding").cast("array<double>").alias("x"))
    rows = rows.orderBy("key").limit(n) if n else rows
    return dense_index(rows, ["key"]).select("idx", "key", "x")


def _first(rows: DataFrame, keys: list[str], n: int | None) -> DataFrame:
    """The first n rows by ``keys``, or all of them."""
    return rows.orderBy(*keys).limit(n) if n else rows


def line4(spark: SparkSession, sf_dir: str, n: int | None = None) -> DataFrame:
    rows = _first(table(spark, sf_dir, "lineitem").select(*LINE_KEY, *LINE4), LINE_KEY, n)
    keyed = dense_index(rows, LINE_KEY)
    return standardize(keyed, LINE4).select("idx", F.col("l_orderkey").alias("key"), assemble(*LINE4).alias("x"))


WIDE28 = [f"f{i:02d}" for i in range(28)]


def wide28(spark: SparkSession, sf_dir: str, n: int | None = None) -> DataFrame:
    def t(name):
        return table(spark, sf_dir, name)

    line = _first(t("lineitem"), LINE_KEY, n)
    rows = (
        line.join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
        .join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
        .join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    )
    ship = F.col("l_shipdate")
    priorities = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
    features = [
        *[F.col(c) for c in LINE4],
        *cyclic(F.month(ship), 12),
        *cyclic(F.dayofweek(ship), 7),
        F.year(ship),
        *one_hot("l_returnflag", ["A", "N", "R"]),
        *one_hot("l_linestatus", ["F", "O"]),
        F.col("o_totalprice"),
        *one_hot("o_orderstatus", ["F", "O", "P"]),
        *[F.when(F.substring("o_orderpriority", 1, 1) == p[0], 1.0).otherwise(0.0) for p in priorities],
        F.col("p_size"),
        F.col("p_retailprice"),
        F.col("s_acctbal"),
        F.col("c_acctbal"),
        F.datediff(ship, F.col("o_orderdate")),
    ]
    keyed = dense_index(rows.select(*LINE_KEY, *[f.cast("double").alias(name) for f, name in zip(features, WIDE28)]), LINE_KEY)
    return standardize(keyed, WIDE28).select("idx", F.col("l_orderkey").alias("key"), assemble(*WIDE28).alias("x"))


def tokens(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(r"(\p{L}+)"), 1)


def docbag(spark: SparkSession, sf_dir: str, m: int = 1024, n: int | None = None, drawn: int | None = None) -> DataFrame:
    """Unit vectors of token counts in m md5 buckets; truth is the rank of the language. ``drawn``: of so many documents, those that ``sampled`` would draw, chosen before any vector is made."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    if drawn:
        docs = docs.join(F.broadcast(sample_n(docs.select("doc_id"), drawn, ["doc_id"])), "doc_id")
    docs = docs.orderBy("doc_id").limit(n) if n else docs
    truth = F.array_position(F.array(*[F.lit(v) for v in ("de", "en", "es", "fr")]), F.col("lang")).cast("int") - 1
    found = F.transform(tokens(F.coalesce("text", F.lit(""))), lambda t: token_bucket(t, m))
    bags = docs.select(F.col("doc_id").alias("key"), truth.alias("truth"), found.alias("found"))
    kind = next(f.dataType.simpleString() for f in bags.schema.fields if f.name == "key")
    counted = materialize(bags.mapInArrow(_counted(m), f"key {kind}, truth int, b array<int>, c array<int>, norm double"))  # else the bags are made again to find the ranges of their keys

    def filled(b, i):
        """Zeros since the bucket before, then this bucket's share."""
        since = F.when(i > 0, F.col("b")[i - 1] + 1).otherwise(0)
        return F.concat(F.array_repeat(F.lit(0.0), b - since), F.array(F.col("c")[i] / F.col("norm")))

    rest = F.when(F.size("b") > 0, m - 1 - F.col("b")[F.size("b") - 1]).otherwise(m)
    x = F.concat(F.flatten(F.transform("b", filled)), F.array_repeat(F.lit(0.0), rest))
    return dense_index(counted, ["key"]).select("key", x.alias("x"), "truth", "idx")


def _counted(m: int):
    """Batches of (key, truth, found) with their buckets as sorted lists of those that occur and how often, and the norm of the latter."""
    import numpy as np
    import pyarrow as pa

    def lists(values, sizes):
        return pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]), pa.int32()), pa.array(values, pa.int32()))

    def run(batches):
        for batch in batches:
            found = batch.column("found")
            rows = np.repeat(np.arange(batch.num_rows), np.diff(found.offsets.to_numpy()))
            cells, times = np.unique(rows * m + found.flatten().to_numpy(), return_counts=True)
            sizes, norms = (np.bincount(cells // m, w, batch.num_rows) for w in (None, times.astype("f8") ** 2))
            norms = np.sqrt(norms)
            yield pa.RecordBatch.from_arrays([batch.column("key"), batch.column("truth"), lists(cells % m, sizes), lists(times, sizes), pa.array(norms)], ["key", "truth", "b", "c", "norm"])

    return run


def docvocab(spark: SparkSession, sf_dir: str, m: int = 10_000) -> DataFrame:
    """Token counts over m words of the vocabulary, drawn by md5 order: sampled columns of the wide matrix. Sparse: (idx, doc_id, col, c)."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.explode(tokens(F.col("text"))).alias("t"))
    chosen = docs.select("t").distinct().orderBy(F.md5(F.col("t").cast("binary")), "t").limit(m)
    columns = dense_index(chosen, ["t"]).select("t", F.col("idx").alias("col"))
    return docs.join(columns, "t").groupBy("doc_id", "col").agg(F.count("*").alias("c"))


def eventday(spark: SparkSession, sf_dir: str, n: int | None = None) -> DataFrame:
    rows = _first(table(spark, sf_dir, "events"), ["event_id"], n)
    hour = F.hour("ts") + F.minute("ts") / 60.0 + F.second("ts") / 3600.0
    kept = rows.select("event_id", *[c.alias(f"h{i}") for i, c in enumerate(cyclic(hour, 24))], F.log1p("value").alias("v"), F.get_json_object("props", "$.k").cast("double").alias("k"))
    return standardize(dense_index(kept, ["event_id"]), ["v", "k"]).select("idx", F.col("event_id").alias("key"), assemble("h0", "h1", "v", "k").alias("x"))


USER = ["n_click", "n_error", "n_purchase", "n_signup", "n_view", "total", "mean", "recency"]


def userfeat(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events")
    last = events.agg(F.max("ts").alias("now"))
    kinds = [F.sum(F.when(F.col("event_type") == c[2:], 1.0).otherwise(0.0)).alias(c) for c in USER[:5]]
    users = events.groupBy("user_id").agg(*kinds, F.sum("value").alias("total"), F.avg("value").alias("mean"), F.max("ts").alias("latest"))
    gone = (F.col("now").cast("timestamp").cast("double") - F.col("latest").cast("timestamp").cast("double")) / 3600.0
    rows = users.crossJoin(F.broadcast(last)).withColumn("recency", gone)
    return standardize(dense_index(rows, ["user_id"]), USER).select("idx", F.col("user_id").alias("key"), assemble(*USER).alias("x"))


def part2(spark: SparkSession, sf_dir: str, n: int | None = None) -> DataFrame:
    rows = table(spark, sf_dir, "part").select("p_partkey", F.col("p_size").cast("double").alias("s"), F.col("p_retailprice").alias("r"))
    rows = rows.orderBy("p_partkey").limit(n) if n else rows
    return standardize(dense_index(rows, ["p_partkey"]), ["s", "r"]).select("idx", F.col("p_partkey").alias("key"), assemble("s", "r").alias("x"))


def lobes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two crossed pairs of lobes: no line parts the classes."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("key"), F.col("c_acctbal").alias("bal"))
    y = (F.col("bal") > 4500).cast("int")
    s = F.when(F.floor(F.col("key") / 2) % 2 == 0, 1.0).otherwise(-1.0)
    a = 2 + F.pmod(F.col("bal"), F.lit(100.0)) / 100
    b = F.pmod(7 * F.col("bal"), F.lit(100.0)) / 100 - 0.5
    x = F.when(y == 0, F.array(s * a, b)).otherwise(F.array(b, s * a))
    return dense_index(c.select("key", x.alias("x"), y.alias("truth")), ["key"])


def rings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two concentric rings."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("key"), F.col("c_acctbal").alias("bal"))
    y = (F.col("bal") > 4500).cast("int")
    turn = 0.6180339887 * F.col("key")
    angle = 2 * math.pi * (turn - F.floor(turn))
    r = F.when(y == 1, 1.0).otherwise(3.0) + 0.2 * F.pmod(F.col("bal"), F.lit(100.0)) / 100
    return dense_index(c.select("key", F.array(r * F.cos(angle), r * F.sin(angle)).alias("x"), y.alias("truth")), ["key"])
