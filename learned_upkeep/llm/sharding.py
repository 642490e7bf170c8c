"""Operator 10, sharding by balanced label propagation (DataFrame functions only).

Linked documents are the members of a group (for the query: equal texts).  Group vertices relay
labels between their members, so a round costs one partial aggregation over (group, shard) and one
salted join back, however large a group is, and no pair of members is ever formed:

1. every linked document starts in the shard its hash names, and sends that label to its group;
2. a group favours the shard that holds most of its bytes; its other members ask to move there;
3. each shard admits requests up to its quota of bytes, whole groups in the order of a hash as long
   as their running total fits, then single members of the groups that are larger than the room;
4. after the last round, documents without links (and linked ones beyond a shard's quota) fill the
   shards up to equal size.

The law kept is ``bytes``: shard sizes differ by about one of the smaller documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise, replicated, salted, whole_text, with_running_total

SHARDS = 8
ROUNDS = 3
#: A document of more than 1/LARGE of all bytes is dealt by rank; there are fewer than LARGE of them.
LARGE = 512


def vertices(docs: DataFrame) -> DataFrame:
    """(doc_id, size, text_crc32, group, h): size in UTF-8 bytes plus 1; group is the text's SHA-256."""
    text = whole_text()
    return docs.select("doc_id", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.unhex(F.sha2(text, 256)).alias("group")).withColumn("h", F.xxhash64("doc_id", "size", "text_crc32"))


def vertices_with_ties(docs: DataFrame) -> DataFrame:
    """The vertices, with ``tied`` for those whose group has another member."""
    nodes = materialise(vertices(docs), "vertices")
    groups = nodes.groupBy("group").agg(F.count("*").alias("__n")).where("__n > 1").select("group", F.lit(True).alias("__tied"))
    joined = salted(nodes, "doc_id", "h").join(replicated(groups), ["group", "__salt"], "left")
    return materialise(joined.select(*nodes.columns, F.coalesce("__tied", F.lit(False)).alias("tied")), "tied")


def _shard_table(spark, shards: int) -> DataFrame:
    return spark.range(shards).select(F.col("id").cast("int").alias("shard"))


def _round(linked: DataFrame, quota: Column, shards: int, name: str) -> DataFrame:
    """One round: linked (doc_id, size, group, h, shard) with some members moved to their group's favourite shard."""
    votes = linked.groupBy("group", "shard").agg(F.sum("size").alias("__bytes"))
    per_group = votes.groupBy("group").agg(F.max_by("shard", F.struct("__bytes", -F.col("shard"))).alias("to"), F.sum("__bytes").alias("__all"), F.max("__bytes").alias("__there"))
    asking = per_group.where("__all > __there").withColumn("ask", F.col("__all") - F.col("__there")).withColumn("h", F.xxhash64("group", F.lit(name)))
    load = linked.groupBy("shard").agg(F.sum("size").alias("__load"))
    room = _shard_table(linked.sparkSession, shards).join(load, "shard", "left").select(F.col("shard").alias("to"), F.greatest(quota - F.coalesce("__load", F.lit(0)), F.lit(0)).alias("room"))
    # prefix sums of the requests in the order of a hash; the table of rooms has one row for each shard
    queued = with_running_total(asking.withColumnRenamed("group", "doc_id"), "h", "ask", "ahead", ["to"]).join(F.broadcast(room), "to")
    share = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (F.col("room") - F.col("ahead")) / F.col("ask")))
    admitted = queued.select(F.col("doc_id").alias("group"), "to", share.alias("share")).where("share > 0")
    coin = F.shiftrightunsigned(F.xxhash64("h", F.lit(name)), 11) / F.lit(float(1 << 53))
    moved = salted(linked, "doc_id", "h").join(replicated(admitted), ["group", "__salt"], "left").withColumn("shard", F.when(coin < F.col("share"), F.col("to")).otherwise(F.col("shard")))
    return materialise(moved.select(*linked.columns), name)


def propagate(nodes: DataFrame, total: int, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """(doc_id, size, text_crc32, group, h, shard) of the tied documents after the last round."""
    linked = nodes.where("tied").drop("tied").withColumn("shard", F.pmod("h", F.lit(shards)).cast("int"))
    for r in range(rounds):
        linked = _round(linked, F.lit(total // shards), shards, f"round{r}")
    return linked


def assign(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """One row per input row: doc_id, size, text_crc32, law, shard, slot, grown_shard.

    A null text has no bytes and size 1; empty texts are linked with one another.  Repeated rows are
    linked (their texts are equal) and may be parted only by the quota.  An empty table gives an
    empty result; further columns are ignored.  Slots count from 0 in every shard without gaps.
    """
    nodes = vertices_with_ties(docs)
    total = nodes.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0]
    linked = propagate(nodes, total, shards, rounds)
    even = -(-total // shards)
    # linked documents beyond an even share leave their shard; they and the unlinked ones are dealt anew
    placed = with_running_total(linked, "h", "size", "ahead", ["shard"])
    fits = F.col("ahead") + F.col("size") <= F.lit(even)
    columns = ["doc_id", "size", "text_crc32", "h"]
    kept = materialise(placed.where(fits).select(*columns, "shard"), "kept")
    single = nodes.where("not tied").select(*columns)
    pool = materialise(single.unionByName(placed.where(~fits).select(*columns)), "pool")
    out = kept.unionByName(_fill(pool, kept, total, even, shards))
    return _with_slots(materialise(out, "placed")).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def _free(kept: DataFrame, even: int, shards: int) -> DataFrame:
    """(shard, free): what each shard lacks to an even share."""
    load = kept.groupBy("shard").agg(F.sum("size").alias("__load"))
    return _shard_table(kept.sparkSession, shards).join(load, "shard", "left").select("shard", F.greatest(F.lit(even) - F.coalesce("__load", F.lit(0)), F.lit(0)).alias("free"))


def _fill(pool: DataFrame, kept: DataFrame, total: int, even: int, shards: int) -> DataFrame:
    """Deals the pool: fewer than LARGE large documents by rank, the rest along running totals of bytes."""
    large = pool.where(F.col("size") > F.lit(total // LARGE))
    small = pool.where(F.col("size") <= F.lit(total // LARGE))
    # the largest document to the freest shard, then back and forth
    by_free = _free(kept, even, shards).select("shard", (F.row_number().over(W.partitionBy(F.lit(0)).orderBy(F.desc("free"), "shard")) - 1).alias("__turn"))
    rank = F.row_number().over(W.partitionBy(F.lit(0)).orderBy(F.desc("size"), "h", "doc_id")) - 1
    turn = F.when(F.floor(rank / F.lit(shards)) % 2 == 0, rank % shards).otherwise(shards - 1 - rank % shards)
    dealt = materialise(large.withColumn("__turn", turn).join(F.broadcast(by_free), "__turn").drop("__turn"), "large")
    free = _free(kept.unionByName(dealt), even, shards)
    upto = F.sum("free").over(W.partitionBy(F.lit(0)).orderBy("shard").rowsBetween(W.unboundedPreceding, 0))
    bounds = free.withColumn("__to", upto)
    # as many rows as there are shards: the ends of their intervals of free bytes, which become literals
    ends = bounds.where("free > 0").orderBy("shard").collect()
    if not ends:
        return dealt
    middle = F.least(F.col("__ahead") + F.col("size") / 2, F.lit(ends[-1]["__to"] - 0.5))
    shard = F.lit(ends[-1]["shard"])
    for e in reversed(ends[:-1]):
        shard = F.when(middle < F.lit(e["__to"]), F.lit(e["shard"])).otherwise(shard)
    run = with_running_total(small, "h", "size", "__ahead", [])
    return dealt.unionByName(run.select(*pool.columns, shard.cast("int").alias("shard")))


def _with_slots(placed: DataFrame) -> DataFrame:
    one = placed.withColumn("__one", F.lit(1).cast("long"))
    return with_running_total(one, "h", "__one", "slot", ["shard"]).drop("__one")

