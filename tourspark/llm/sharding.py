"""Rendezvous hashing of stable record keys over weighted shards.

Every (key, shard) pair has a digest; the shard with the best digest wins the key. A new
shard can only take keys for itself, and a removed shard gives up only its own keys.
Built from SQL functions alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tourspark.functions.numbering import dense_number
from tourspark.session import stage


def key_text(key: Column) -> Column:
    """A key as text; null is a key of its own."""
    return F.coalesce(key.cast("string"), F.lit("null"))


def _pair_digest(key: Column, shard: int) -> Column:
    return F.md5(F.concat(key_text(key), F.lit(f":{shard}")))


def _race(key: Column, shard: int, weight: float) -> Column:
    """Negated arrival time of a shard in an exponential race at rate ``weight``."""
    bits = F.conv(F.substring(_pair_digest(key, shard), 1, 13), 16, 10).cast("double")
    return F.log((bits + 0.5) / F.lit(float(1 << 52))) / F.lit(float(weight))


def rendezvous(key: Column, n_shards: int, weights: list[float] | None = None) -> Column:
    """struct(best, shard): the winning score and its shard; ties go to the smaller shard.

    Equal weights compare whole 128-bit digests; other weights race at those rates, and a
    shard of weight 0 gets nothing.
    """
    if n_shards < 1 or weights is not None and (len(weights) != n_shards or min(weights) < 0 or max(weights) == 0):
        raise ValueError("at least one shard, and one weight of 0 or more for each")
    rate = weights or [1.0] * n_shards
    same = len(set(rate)) == 1
    runs = [
        F.struct((_pair_digest(key, s) if same else _race(key, s, rate[s])).alias("best"), F.lit(-s).alias("minus"))
        for s in range(n_shards)
        if rate[s] > 0
    ]
    top = F.array_max(F.array(*runs))
    return F.struct(top["best"].alias("best"), (-top["minus"]).cast("int").alias("shard"))


def shard_documents(
    docs: DataFrame, n_shards: int = 40, key: str = "doc_id", text: str = "text",
    weights: list[float] | None = None,
) -> DataFrame:
    """Shard, slot within the shard, and the shard after one more shard of equal weight joins.

    ``slot`` is the rank of a row in its shard by the digest of its key, then by the key, the
    size and the checksum. All rows are numbered through by ranges, so that no task sorts a
    whole shard nor all rows of one key; a shard's first number, one row a shard, is taken off.

    Null text counts as no bytes; a null key is a key like any other; repeated rows go to one
    shard with slots of their own; an empty table gives an empty table. Other columns of
    ``docs`` are ignored. With weights that differ, ``grown_shard`` is null.
    """
    equal = weights is None or len(set(weights)) == 1
    win = rendezvous(F.col("k"), n_shards, weights)
    rows = docs.select(
        F.col(key).alias("k"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + 16).cast("long").alias("size"),
        F.coalesce(F.crc32(F.col(text).cast("binary")), F.lit(0)).cast("long").alias("text_crc32"),
    )
    grown = F.when(_pair_digest(F.col("k"), n_shards) > F.col("win.best"), F.lit(n_shards)).otherwise(F.col("win.shard")) if equal else F.lit(None)
    placed = rows.withColumns({"win": win, "place": F.md5(key_text(F.col("k")))}).select(
        "k", "size", "text_crc32", "place", F.col("win.shard").alias("shard"), grown.cast("int").alias("grown_shard"),
    )
    numbered = dense_number(stage(placed, "shards"), ["shard", "place", "k", "size", "text_crc32"], "n", 0)
    first = F.broadcast(numbered.groupBy("shard").agg(F.min("n").alias("first")))  # a row a shard
    return numbered.join(first, "shard").select(
        F.col("k").alias(key), "size", "text_crc32", F.lit("key").alias("law"), "shard",
        (F.col("n") - F.col("first")).cast("long").alias("slot"), "grown_shard",
    )


#: CRC-32 is folded over the bytes with a table that the reflected polynomial gives.
ORACLE = """
WITH RECURSIVE step(i, n, c) AS (
  SELECT i, 0, i FROM range(256) r(i)
  UNION ALL
  SELECT i, n + 1, CASE WHEN c & 1 = 1 THEN xor(c >> 1, 3988292384) ELSE c >> 1 END FROM step WHERE n < 8
), crc AS (SELECT list(c ORDER BY i) AS tab FROM step WHERE n = 8),
rows AS (
  SELECT doc_id, coalesce(CAST(doc_id AS VARCHAR), 'null') AS k, coalesce(strlen(text), 0) + 16 AS size,
         list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda p: CAST('0x' || p AS BIGINT)) AS bytes
  FROM documents
), summed AS (
  SELECT doc_id, k, size,
         xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), bytes), lambda c, b: xor(c >> 8, tab[xor(c & 255, b) + 1])), 4294967295) AS text_crc32
  FROM rows, crc
), raced AS (
  SELECT k, arg_max(s, (h, -s)) FILTER (WHERE s < 40) AS shard, arg_max(s, (h, -s)) AS grown_shard
  FROM (SELECT k, s, md5(k || ':' || s) AS h FROM (SELECT DISTINCT k FROM rows), range(41) r(s)) GROUP BY k
)
SELECT doc_id, CAST(size AS BIGINT) AS size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'key' AS law, CAST(shard AS INTEGER) AS shard,
       CAST(row_number() OVER (PARTITION BY shard ORDER BY md5(k), doc_id, size, text_crc32) - 1 AS BIGINT) AS slot,
       CAST(grown_shard AS INTEGER) AS grown_shard
FROM summed JOIN raced USING (k)
"""
