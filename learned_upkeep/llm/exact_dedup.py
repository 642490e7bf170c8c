"""Operator 1, exact deduplication by content-defined chunk recipes (DataFrame functions only).

A text is cut where its own content says so, so a document becomes a recipe: the ordered list of
its chunks' short identifiers.  Identifiers are verified: the dictionary keeps one entry for each
(identifier, SHA-256 of the chunk) and an identifier that stands for two chunks gets a rank, which
then joins the list.  Documents are equal when their ordered lists of verified identifiers are.
The text is read once; only recipes (about 40 bytes per chunk) are moved afterwards.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise, replicated, salted, scratch_scope, whole_text, without_ids

#: Least and most characters of a chunk, and the content before a cut: a vowel, white space, a letter of the first third of the alphabet.
CHUNK = r"(?s).{512,4096}?(?<=[aeioué]\s[A-Ha-h])|(?s).{1,4096}"


def recipes(docs: DataFrame, fingerprint_bits: int = 64) -> DataFrame:
    """(doc_id, text_sha256, recipe array<long>, digests array<binary>, recipe_key) of every row."""
    short = lambda c: F.xxhash64(c, F.octet_length(c)) if fingerprint_bits == 64 else F.pmod(F.xxhash64(c), F.lit(1 << fingerprint_bits))
    return (
        docs.select(F.col("doc_id"), whole_text().alias("__text"))
        .select("doc_id", F.sha2("__text", 256).alias("text_sha256"), F.regexp_extract_all("__text", F.lit(CHUNK), F.lit(0)).alias("__chunks"))
        .select(
            "doc_id", "text_sha256",
            F.transform("__chunks", short).alias("recipe"),
            F.transform("__chunks", lambda c: F.unhex(F.sha2(c, 256))).alias("digests"),
        )
        .withColumn("recipe_key", F.xxhash64("recipe"))
    )


def exact_duplicates(docs: DataFrame, fingerprint_bits: int = 64) -> DataFrame:
    """One row per input row: doc_id, keep_id, group_size, kept, text_sha256.

    Of equal texts the largest doc_id stays.  A null text counts as empty, and empty texts equal one
    another.  A null doc_id ranks below all others.  Repeated rows of one doc_id share their decision
    (:func:`drop_duplicates` then leaves one of them).  An empty table gives an empty result; further
    columns of the input are ignored.
    """
    table = materialise(recipes(docs, fingerprint_bits), "recipes")
    shared = table.groupBy("recipe_key").count().where("count > 1").select("recipe_key")
    alike = salted(table, "doc_id").join(replicated(shared), ["recipe_key", "__salt"]).drop("__salt")
    dictionary = (
        alike.select(F.explode(F.arrays_zip("recipe", "digests")).alias("__c"))
        .groupBy(F.col("__c.recipe").alias("__short"), F.col("__c.digests").alias("__digest"))
        .agg(F.lit(1).alias("__one"))
    )
    ranked = dictionary.withColumn("__rank", F.row_number().over(W.partitionBy("__short").orderBy("__digest")))
    second = ranked.where("__rank > 1").drop("__one")
    listed = ["recipe_key", "recipe"]
    if not second.isEmpty():  # some short identifiers stand for several chunks: their ranks become part of the lists
        table = _with_ranks(table, second)
        listed.append("ranks")
    groups = (alike if len(listed) == 2 else table).groupBy(*listed).agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size")).where("group_size > 1")
    out = salted(table, "doc_id").join(replicated(groups), [*listed, "__salt"], "left")
    keep = F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id"))
    return out.select(
        "doc_id", keep.alias("keep_id"), F.coalesce("group_size", F.lit(1)).alias("group_size"), F.col("doc_id").eqNullSafe(keep).alias("kept"), "text_sha256"
    )


def _with_ranks(table: DataFrame, second: DataFrame) -> DataFrame:
    """Adds ranks: for each chunk its rank among the chunks of the same short identifier."""
    entries = table.select("doc_id", "text_sha256", "recipe", F.posexplode(F.arrays_zip("recipe", "digests")).alias("__pos", "__c"))
    entries = entries.withColumns({"__short": F.col("__c.recipe"), "__digest": F.col("__c.digests")})
    found = entries.join(second, ["__short", "__digest"])
    ranks = found.groupBy("text_sha256", "recipe").agg(F.sort_array(F.collect_set(F.struct("__pos", "__rank"))).alias("ranks"))
    none = F.array().cast("array<struct<__pos:int,__rank:int>>")
    return table.join(ranks, ["text_sha256", "recipe"], "left").withColumn("ranks", F.coalesce("ranks", none))


def drop_duplicates(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that stay, one for each text, with their own columns."""
    with scratch_scope(docs.sparkSession):
        decided = materialise(exact_duplicates(docs).select("doc_id", "kept"), "decided")
        by_id = materialise(decided.groupBy("doc_id").agg(F.count("*").alias("__rows"), F.bool_or("kept").alias("__kept")).where("__rows > 1 or not __kept"), "by-id")
        dropped = materialise(by_id.where("__rows = 1").select(F.col("doc_id").alias("__id")), "dropped", keep=True)
        repeated = materialise(by_id.where("__rows > 1").select(F.col("doc_id").alias("__id"), "__kept"), "repeated", keep=True)
        several_rows = not repeated.isEmpty()
        if several_rows:
            winners = materialise(exact_duplicates(docs).where("kept").select(F.col("doc_id").alias("__id"), F.col("text_sha256").alias("__sha2")).distinct(), "winners", keep=True)
    left = without_ids(docs, dropped)
    if not several_rows:
        return left
    # rows that share a doc_id: the first of each (doc_id, text), and only where no other doc_id keeps that text
    single = left.join(repeated, F.col("doc_id").eqNullSafe(F.col("__id")), "left_anti")
    several = left.join(repeated.select("__id"), F.col("doc_id").eqNullSafe(F.col("__id")), "left_semi").withColumn("__sha", F.sha2(whole_text(), 256))
    several = several.join(winners, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__sha") == F.col("__sha2")), "left_semi")
    return single.unionByName(several.dropDuplicates(["doc_id", "__sha"]).drop("__sha"))
