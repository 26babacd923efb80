"""Sharding by sampled splitters.

Records are ordered by a key (a hash of the text, then doc_id), so equal texts stand together. Keys
are drawn with chances in proportion to their sizes; quantiles of the sample are the boundaries of
ranges, and records are dealt to the ranges. A range that holds more than `overfull` times its share
is divided again, by boundaries drawn in it alone, until none is or its keys are all alike. Sizes in a
range are then added up in key order and offset by the exact sums of the ranges before it, and the
shard is where the middle of the record falls among equal parts of the total. So the sample decides
only how the work is spread; the shards are the same for any sample.

Laws: `bytes` makes the sums of sizes near equal (each is off by less than the largest record);
`rows` makes the counts differ by one at most. Slots number a shard's records in key order, from 0.

Only key, size and checksum are shuffled. What the driver holds is the sample and a row for each
range and shard, bounded by `sample_keys`, the number of ranges and of shards.

Defined results: a null text counts like the empty one; a null doc_id sorts first, whole numbers by their
value and ids of other types by a hash; rows that are alike in text and doc_id may change places; an
empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, table

SHARDS, OVERHEAD = 40, 16
SAMPLE_KEYS = 20_000
#: A range is divided when it has more than so many times its share.
OVERFULL = 2.0
LEAST_ID = -(1 << 63)


def keyed(df: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32 and the key (h, id) of each row."""
    text = F.coalesce(F.col("text"), F.lit(""))
    whole = isinstance(df.schema["doc_id"].dataType, T.IntegralType)
    number = F.col("doc_id").cast("bigint") if whole else F.when(F.col("doc_id").isNotNull(), F.xxhash64("doc_id"))
    return df.select(
        "doc_id",
        (F.octet_length(text) + OVERHEAD).cast("bigint").alias("size"),
        F.crc32(text).alias("text_crc32"),
        F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint").alias("h"),
        F.coalesce(number, F.lit(LEAST_ID)).alias("id"),
    )


def draw(rows: DataFrame, weight: Column, total: int, n: int) -> list[tuple[int, int, float]]:
    """About n keys (h, id), each drawn with a chance in proportion to its weight, and what each stands for."""
    chance = F.least(F.lit(1.0), weight * n / max(1, total))
    u = F.pmod(F.xxhash64("h", "id"), F.lit(1 << 40)) / F.lit(float(1 << 40))
    got = rows.filter(u < chance).groupBy("h", "id").agg(F.sum(weight / chance).alias("w")).collect()
    return sorted((r["h"], r["id"], float(r["w"])) for r in got)


def splitters(sample: list[tuple[int, int, float]], ranges: int) -> list[tuple[int, int]]:
    """Boundaries at the weighted quantiles; a range holds keys from its lower boundary on."""
    if not sample:
        return []
    upto = np.cumsum([w for _, _, w in sample])
    at = np.searchsorted(upto, upto[-1] * np.arange(1, ranges) / ranges)
    return sorted({sample[i][:2] for i in at})


def deal(rows: DataFrame, bounds: list[tuple[int, int]]) -> DataFrame:
    """rows with `part`: the number of boundaries at or below the key."""
    high, low = np.array([b[0] for b in bounds], np.int64), np.array([b[1] for b in bounds], np.int64)

    @F.pandas_udf("int")
    def place(h: pd.Series, i: pd.Series) -> pd.Series:
        first = np.searchsorted(high, h.to_numpy(), "left")
        last = np.searchsorted(high, h.to_numpy(), "right")
        tied = np.flatnonzero(last > first)
        part, own = first.astype(np.int32), i.to_numpy()
        for a in np.unique(first[tied]):  # boundaries of one text: at most as many as there are boundaries
            rows = tied[first[tied] == a]
            part[rows] += np.searchsorted(low[a : last[rows[0]]], own[rows], "right").astype(np.int32)
        return pd.Series(part)

    return rows.withColumn("part", place("h", "id"))


def shard(df: DataFrame, shards: int = SHARDS, law: str = "bytes", sample_keys: int = SAMPLE_KEYS, ranges: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of each row of (doc_id, text)."""
    if law not in ("bytes", "rows"):
        raise ValueError(f"no such law: {law}")
    weight = F.col("size") if law == "bytes" else F.lit(1).cast("bigint")
    rows = cut(keyed(df))
    n, total = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(weight), F.lit(0))).first()
    ranges = ranges or int(min(sample_keys // 20, max(shards, n // 50_000)))
    bounds = splitters(draw(rows, weight, total, sample_keys), ranges)
    while True:
        sums = deal(rows, bounds).groupBy("part").agg(F.sum(weight).alias("w"), F.min(F.struct("h", "id")).alias("a"), F.max(F.struct("h", "id")).alias("z")).collect()
        full = [r for r in sums if r["w"] > OVERFULL * total / ranges and r["a"] != r["z"]]
        new = set(bounds)
        for r in full:
            inside = rows.filter(F.struct("h", "id").between(F.struct(F.lit(r["a"]["h"]).alias("h"), F.lit(r["a"]["id"]).alias("id")), F.struct(F.lit(r["z"]["h"]).alias("h"), F.lit(r["z"]["id"]).alias("id"))))
            parts = int(np.ceil(r["w"] * ranges / total)) + 1
            new |= set(splitters(draw(inside, weight, r["w"], 200 * parts), parts)) - {(r["a"]["h"], r["a"]["id"])}
        if len(new) == len(bounds):  # no range is overfull, or none has a key to be divided at
            break
        bounds = sorted(new)
    dealt = cut(deal(rows, bounds).withColumn("w", weight).repartition(len(bounds) + 1, "part"))
    own = dealt.groupBy("part").agg(F.sum("w").alias("w")).collect()
    before, at = {}, 0
    for r in sorted(own, key=lambda r: r["part"]):
        before[r["part"]] = at
        at += r["w"]
    spark = df.sparkSession
    offsets = spark.createDataFrame(list(before.items()), "part int, offset bigint")  # a row for each range
    order = Window.partitionBy("part").orderBy("h", "id", "size", "text_crc32")
    summed = dealt.join(F.broadcast(offsets), "part").withColumn("end", F.col("offset") + F.sum("w").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    middle = 2 * F.col("end") - F.col("w") if law == "bytes" else 2 * (F.col("end") - F.col("w"))
    spot = F.expr(f"cast(2 * {max(1, total)} as bigint)")
    placed = summed.withColumn("shard", F.least(F.lit(shards - 1), F.floor(middle.cast("decimal(38,0)") * shards / spot)).cast("int"))
    placed = placed.withColumn("at", F.row_number().over(Window.partitionBy("part", "shard").orderBy("h", "id", "size", "text_crc32")) - 1)
    placed = cut(placed.select("doc_id", "size", "text_crc32", "part", "shard", "at"))
    counts = sorted((r["shard"], r["part"], r["n"]) for r in placed.groupBy("shard", "part").agg(F.count(F.lit(1)).alias("n")).collect())
    first, seen = [], {}
    for s, p, k in counts:
        first.append((s, p, seen.get(s, 0)))
        seen[s] = seen.get(s, 0) + k
    starts = spark.createDataFrame(first, "shard int, part int, start bigint")  # ranges and shards together
    return placed.join(F.broadcast(starts), ["shard", "part"]).select("doc_id", "size", "text_crc32", F.lit(law).alias("law"), "shard", (F.col("start") + F.col("at")).cast("bigint").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def torn_groups(placed: DataFrame) -> DataFrame:
    """groups, torn: groups of equal texts (told by checksum and size) of two rows or more, and how many of them are in more than one shard."""
    per = placed.groupBy("text_crc32", "size").agg(F.count(F.lit(1)).alias("n"), F.min("shard").alias("a"), F.max("shard").alias("z")).filter("n > 1")
    return per.agg(F.count(F.lit(1)).alias("groups"), F.count_if(F.col("a") < F.col("z")).alias("torn"))


def op8_splitter_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard(table(spark, sf_dir, "documents"))


ORACLE_SQL = """
WITH codes AS (
  SELECT list_transform(range(256), lambda i: list_reduce(list_prepend(i, range(8)),
           lambda c, k: CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END)) AS crc),
base AS (
  SELECT doc_id, coalesce(text, '') AS t, octet_length(encode(coalesce(text, ''))) + 16 AS size FROM documents),
sums AS (
  SELECT doc_id, size, CAST('0x' || substr(md5(t), 1, 15) AS BIGINT) AS h,
         xor(4294967295, list_reduce(
           list_prepend(CAST(4294967295 AS BIGINT),
             list_transform(regexp_extract_all(hex(encode(t)), '..'), lambda x: CAST('0x' || x AS BIGINT))),
           lambda c, b: xor(c // 256, crc[CAST(xor(c % 256, b) AS INT) + 1]))) AS text_crc32
  FROM base, codes),
placed AS (
  SELECT *, sum(size) OVER (ORDER BY h, doc_id NULLS FIRST ROWS UNBOUNDED PRECEDING) AS upto, sum(size) OVER () AS total
  FROM sums),
cut AS (SELECT *, least(39, CAST(((2 * upto - size) * 40) // (2 * total) AS INT)) AS shard FROM placed)
SELECT doc_id, CAST(size AS BIGINT) AS size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'bytes' AS law, shard,
       row_number() OVER (PARTITION BY shard ORDER BY h, doc_id NULLS FIRST) - 1 AS slot, CAST(NULL AS INT) AS grown_shard
FROM cut
"""
