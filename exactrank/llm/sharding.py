"""Sharding by rendezvous hashing of stable record keys over weighted shards.

Every (key, shard) pair gets a number from MD5; a record goes to the shard of the highest
score ``-weight / ln(u)``. A shard that joins can only take records for itself: all other
scores stay as they are. Everything is DataFrame expressions; the plan has one exchange of
narrow rows (for the slots) and none of texts.

Defined results: a null key is the key ``""`` prefixed by ``n``, all others are prefixed by
``v``; a null text has size 1 and the checksum of no bytes; repeated rows share a shard and
get slots of their own; an empty table gives no rows; columns besides key and text are ignored.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from exactrank.llm.common import documents, own_name

SHARDS = 16
#: Slot numbering counts rows in this many fixed groups of every shard.
SLOT_GROUPS = 4096


def stable_key(key: Column) -> Column:
    return F.coalesce(F.concat(F.lit("v"), key.cast("string")), F.lit("n"))


def _digest(key: Column, shard: int) -> Column:
    return F.md5(F.concat(key, F.lit(f":{shard}")))


def rendezvous(key: Column, weights: Sequence[float]) -> Column:
    """The shard (from 0) with the highest weighted score for a string key.

    Equal weights compare the digests themselves, which order as the scores do. Ties go to the
    higher shard number; a weight of 0 takes nothing.
    """
    if not weights or min(weights) < 0 or max(weights) <= 0:
        raise ValueError("weights must be non-negative, one of them positive")
    live = [(s, w) for s, w in enumerate(weights) if w > 0]
    if len({w for _, w in live}) == 1:
        ranked = [F.struct(_digest(key, s).alias("score"), F.lit(s).alias("shard")) for s, _ in live]
    else:
        def score(s: int, w: float) -> Column:
            u = (F.conv(F.substring(_digest(key, s), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)
            return -F.lit(float(w)) / F.log(u)

        ranked = [F.struct(score(s, w).alias("score"), F.lit(s).alias("shard")) for s, w in live]
    return (F.greatest(*ranked) if len(ranked) > 1 else ranked[0])["shard"].cast("int")


def assign_shards(df: DataFrame, key: str, weights: Sequence[float], out: str = "shard") -> DataFrame:
    """``df`` with the column ``out``; no exchange at all."""
    return df.withColumn(out, rendezvous(stable_key(F.col(key)), weights))


def with_slots(df: DataFrame, shard: str, key: str, order: Sequence[str], out: str = "slot") -> DataFrame:
    """Gapless numbers from 0 within each shard, without one task per shard.

    Rows are numbered within (shard, group), the group being a hash of the key; groups start
    where the counts before them end. There are at most shards x SLOT_GROUPS counts, whatever
    the input, so they are safe to broadcast.
    """
    group = F.conv(F.substring(F.md5(stable_key(F.col(key))), 1, 3), 16, 10).cast("int")
    own, nth, s, g, start = (own_name(df, f"slot {x}") for x in ("group", "place", "shard", "number", "start"))
    rows = df.withColumn(own, group)
    counts = rows.groupBy(F.col(shard).alias(s), F.col(own).alias(g)).agg(F.count("*").alias("n"))
    before = Window.partitionBy(s).orderBy(g).rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select(s, g, F.coalesce(F.sum("n").over(before), F.lit(0)).alias(start))
    within = Window.partitionBy(shard, own).orderBy(*order)
    numbered = rows.withColumn(nth, F.row_number().over(within) - 1)
    return (
        numbered.join(F.broadcast(starts), (F.col(shard) == F.col(s)) & (F.col(own) == F.col(g)))
        .withColumn(out, (F.col(start) + F.col(nth)).cast("long"))
        .drop(s, g, start, nth, own)
    )


def op3_rendezvous_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents into SHARDS equal shards by key; ``grown_shard`` is with one shard more."""
    docs = documents(spark, sf_dir, "doc_id", "text")
    rows = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"),
        F.lit("key").alias("law"),
    )
    rows = assign_shards(rows, "doc_id", [1.0] * SHARDS)
    rows = assign_shards(rows, "doc_id", [1.0] * (SHARDS + 1), "grown_shard")
    out = with_slots(rows, "shard", "doc_id", ["doc_id", "size", "text_crc32"])
    return out.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")


_CRC_TABLE = "list_transform(range(256), lambda x: list_reduce([x::BIGINT, 1, 1, 1, 1, 1, 1, 1, 1], lambda c, i: CASE WHEN c % 2 = 1 THEN xor(3988292384::BIGINT, c // 2) ELSE c // 2 END))"

OP3_SQL = f"""
WITH crc AS (SELECT {_CRC_TABLE} AS t),
keyed AS (
  SELECT doc_id, coalesce(strlen(text), 0) + 1 AS size, coalesce(text, '') AS body,
         coalesce('v' || doc_id, 'n') AS k
  FROM documents),
scored AS (
  SELECT *,
    list_reduce(range(1, {SHARDS}), lambda b, s: CASE WHEN md5(k || ':' || s) >= md5(k || ':' || b) THEN s ELSE b END, 0::BIGINT) AS shard,
    list_reduce(range(1, {SHARDS + 1}), lambda b, s: CASE WHEN md5(k || ':' || s) >= md5(k || ':' || b) THEN s ELSE b END, 0::BIGINT) AS grown,
    xor(4294967295::BIGINT, list_reduce(
      list_transform(regexp_extract_all(hex(encode(body)), '..'), lambda h: ('0x' || h)::BIGINT),
      lambda c, b: xor(c // 256, t[xor(c % 256, b) + 1]), 4294967295::BIGINT)) AS text_crc32
  FROM keyed, crc)
SELECT doc_id, size::BIGINT AS size, text_crc32, 'key' AS law, shard::INTEGER AS shard,
  row_number() OVER (PARTITION BY shard ORDER BY substr(md5(k), 1, 3), doc_id, size, text_crc32) - 1 AS slot,
  grown::INTEGER AS grown_shard
FROM scored
"""
