"""Proportional stratified interleaving into shards (operator 8).

Rows of each source are put into a seeded random order and ranked; the row of rank
r among n has the fractional rank (r - 1/2) / n. Ordered by it, all sources advance
together, so any run of consecutive rows holds the mixture, and cutting the order
into equal runs gives shards that match it with row counts at most one apart.

Ranks come from two range sorts. Within a sorted partition the rank is a running
number; what comes before a partition is a sum over partitions. So a source with a
third of all rows is spread over as many partitions as its size asks for, and no
window holds a source. Only keys, sizes and checksums move; texts stay where they
are. Null sources are a source of their own; null ids and repeated rows are ranked
like any other (ties are broken by text checksum and size, rows alike in all of
them are interchangeable); an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tallgram.llm.common import stored

#: Rows of (source, partition) sums up to which they are broadcast; beyond it they are joined by shuffle.
BROADCAST_ROWS = 200_000


def _numbered(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """df sorted by order over range partitions, with part and its place there from 0; stored, so both stay fixed."""
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = df.repartitionByRange(n, *order).sortWithinPartitions(*order).withColumn("_n", F.monotonically_increasing_id())
    part = F.shiftright("_n", 33)
    return stored(ordered.select(*df.columns, part.cast("int").alias("_part"), (F.col("_n") - F.shiftleft(part, 33)).alias("_at")), name)


def _before(numbered: DataFrame, keys: list[str]) -> DataFrame:
    """For each (keys, part): rows of keys in earlier parts, the first place in the part, and rows of keys in all."""
    sums = numbered.groupBy(*keys, "_part").agg(F.count("*").alias("_rows"), F.min("_at").alias("_first"))
    over = Window.partitionBy(*keys).orderBy("_part")
    return sums.select(*keys, "_part", "_first", (F.sum("_rows").over(over) - F.col("_rows")).alias("_earlier"), F.sum("_rows").over(Window.partitionBy(*keys)).alias("_total"))


def interleave(rows: DataFrame, strata: str, n_shards: int, ties: list[str], seed: int = 17) -> DataFrame:
    """rows with shard (int) and slot (long, gapless from 0 in its shard). ties: columns that order rows of equal draw."""
    columns = rows.columns
    drawn = rows.withColumn("_draw", F.xxhash64(F.lit(seed), *ties)).withColumn("_s", F.coalesce(F.concat(F.lit("="), F.col(strata).cast("string")), F.lit("")))
    ranked = _numbered(drawn, ["_s", "_draw", *ties], "strata")
    sums = _before(ranked, ["_s"]).withColumnsRenamed({"_s": "_s2", "_part": "_p2"})
    # there is one row of sums for each partition and source that meet: partitions plus sources at most
    small = F.broadcast(sums) if sums.count() <= BROADCAST_ROWS else sums
    placed = ranked.join(small, (ranked["_s"] == sums["_s2"]) & (ranked["_part"] == sums["_p2"]))
    fraction: Column = (F.col("_earlier") + F.col("_at") - F.col("_first") + F.lit(0.5)) / F.col("_total")
    mixed = _numbered(placed.select(*columns, "_s", "_draw", fraction.alias("_fraction")), ["_fraction", "_draw", "_s", *ties], "mixed")
    sums = _before(mixed.withColumn("_k", F.lit(1)), ["_k"]).withColumnsRenamed({"_part": "_p2"}).drop("_k", "_first")
    # one row a partition, so its size is bounded by the number of partitions
    out = mixed.join(F.broadcast(sums), F.col("_part") == F.col("_p2")).withColumn("_position", F.col("_earlier") + F.col("_at"))
    out = out.withColumn("shard", F.expr(f"cast((_position * {n_shards}) div _total as int)"))
    slot = F.expr(f"_position - (shard * _total + {n_shards - 1}) div {n_shards}").cast("long")
    return out.select(*columns, "shard", slot.alias("slot"))


def shard_documents(docs: DataFrame, n_shards: int = 8, seed: int = 17) -> DataFrame:
    """Every row of docs (doc_id, text, source) under the law ``rows``: doc_id, source, size, text_crc32, law, shard, slot, grown_shard."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", "source", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"))
    out = interleave(rows, "source", n_shards, ["doc_id", "text_crc32", "size"], seed)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "source")
