"""The operators as stages of the corpus pipeline: (spark, docs, sf_dir) to a DataFrame."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hybridsort.ship import ship
from hybridsort.sources.tables import fresh

from . import decontam, neardup, packing, quality, suffix_tree
from .common import old_names, plain_names, staged, table

SALTS = 8


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules and perplexity bands keep.

    A verdict belongs to a text and its language, so only rejected digests come back from the judging, and
    no text passes through Python twice. Rows of one text are spread over SALTS tasks.
    """
    ship(spark)
    docs, old = plain_names(docs)
    judged = quality.judge(docs.select("text", "lang"), keep=[])
    gone = staged(judged.where("not kept").select("lang_group", "text_digest").distinct(), "rejected")
    gone = gone.withColumn("salt", F.explode(F.array(*[F.lit(k) for k in range(SALTS)])))
    keyed = docs.withColumns({"lang_group": F.coalesce("lang", F.lit("")), "text_digest": quality.text_digest(), "salt": F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int")})
    # the rejected digests grow with the input, so they are never broadcast
    return old_names(keyed.join(gone.hint("merge"), ["lang_group", "text_digest", "salt"], "left_anti").select(*docs.columns), old)


def minhash_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group, the one with the smallest id.

    Rows that share an id are one document: if it stays, each of its different texts does, once.
    Rows without an id stay.
    """
    ship(spark)
    linked = neardup.link(docs)
    kept = linked.where("kept and doc_id is not null").select("doc_id").distinct()
    names = [f"`{c}`" for c in docs.columns]
    out = docs.join(kept, "doc_id", "left_semi").select(*names)
    if linked.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count():
        digest = fresh(out, "digest")
        out = out.withColumn(digest, quality.text_digest()).dropDuplicates(["doc_id", digest]).select(*names)
    return out.unionByName(docs.where("doc_id is null"))


def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the passages that stand more than once in the corpus."""
    ship(spark)
    return suffix_tree.clean(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without benchmark passages; documents that are mostly benchmark go."""
    ship(spark)
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of training sequences with their token ids."""
    ship(spark)
    return packing.pack(docs)
