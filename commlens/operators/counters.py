"""Assignments, counters and estimates. Counters are sparse long tables: rows of zero are absent."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens.functions.expressions import hashed


def first_assignment(docs: DataFrame, communities: int, topics: int, seed: int = 0) -> DataFrame:
    """(doc_id, user_id, c, z) by a hash of the document; narrow."""
    c = F.pmod(hashed(F.col("doc_id"), 101 + seed), F.lit(communities))
    z = F.pmod(F.floor(hashed(F.col("doc_id"), 202 + seed) / F.lit(64)), F.lit(topics))
    return docs.select("doc_id", "user_id", c.cast("int").alias("c"), z.cast("int").alias("z"))


def user_community(assign: DataFrame) -> DataFrame:
    return assign.groupBy("user_id", "c").agg(F.count("*").alias("n"))


def community_topic(assign: DataFrame) -> DataFrame:
    return assign.groupBy("c", "z").agg(F.count("*").alias("n"))


def topic_word(assign: DataFrame, tokens: DataFrame) -> DataFrame:
    return tokens.join(assign.select("doc_id", "z"), "doc_id").groupBy("z", "word").agg(F.sum("cnt").alias("n"))


def topic_time(assign: DataFrame, docs: DataFrame) -> DataFrame:
    return assign.select("doc_id", "z").join(docs.select("doc_id", "tbin"), "doc_id").groupBy("z", "tbin").agg(F.count("*").alias("n"))


def popularity(counts: DataFrame, scale: str = "raw") -> DataFrame:
    """(z, tbin, pop) from ``topic_time`` counts."""
    n = F.col("n").cast("double")
    value = {"raw": n, "log1p": F.log1p(n), "share": n / F.sum("n").over(W.partitionBy("tbin"))}[scale]
    return counts.select("z", "tbin", value.alias("pop"))


def _share(counts: DataFrame, of: str, kind: str) -> DataFrame:
    return counts.select(of, kind, (F.col("n") / F.sum("n").over(W.partitionBy(of))).alias("p"))


def empirical_membership(assign: DataFrame) -> DataFrame:
    """(user_id, c, p): the share of a user's documents in each community."""
    return _share(user_community(assign), "user_id", "c")


def empirical_topics(assign: DataFrame) -> DataFrame:
    """(c, z, p): the share of a community's documents on each topic."""
    return _share(community_topic(assign), "c", "z")


def _smoothed(counts: DataFrame, of: str, kind: str, kinds: DataFrame, prior: float, dim: int | None = None) -> DataFrame:
    """(of, kind, p) over the full grid of the groups that occur and all kinds."""
    totals = counts.groupBy(of).agg(F.sum("n").alias("total"))
    grid = totals.crossJoin(F.broadcast(kinds))
    return grid.join(counts, [of, kind], "left").select(of, kind, ((F.coalesce("n", F.lit(0)) + prior) / (F.col("total") + prior * dim)).alias("p"))


def smoothed_membership(counts: DataFrame, communities: int, prior: float) -> DataFrame:
    """From ``user_community`` counts."""
    kinds = counts.sparkSession.range(communities).select(F.col("id").cast("int").alias("c"))
    return _smoothed(counts, "user_id", "c", kinds, prior, communities)


def smoothed_topics(counts: DataFrame, communities: int, topics: int, prior: float) -> DataFrame:
    """From ``community_topic`` counts, over all communities, empty ones included."""
    spark = counts.sparkSession
    grid = spark.range(communities).select(F.col("id").cast("int").alias("c")).crossJoin(spark.range(topics).select(F.col("id").cast("int").alias("z")))
    n = F.coalesce("n", F.lit(0))
    return grid.join(counts, ["c", "z"], "left").select("c", "z", ((n + prior) / (F.sum(n).over(W.partitionBy("c")) + prior * topics)).alias("p"))


def smoothed_words(counts: DataFrame, vocabulary: DataFrame, prior: float) -> DataFrame:
    """(z, word, p) from ``topic_word`` counts, over topics that occur and the whole vocabulary (column ``word``)."""
    words = vocabulary.select("word")
    return _smoothed(counts, "z", "word", words, prior, words.count())


def eta(diffs: DataFrame, assign: DataFrame, norm: str = "per_community", smooth: float = 0.0) -> DataFrame:
    """(c, c2, z, p): diffusion links counted by both communities and the diffuser's topic, then normalised over each community's links, over all links, or over the
    topics of each pair. ``smooth`` is added to cells that occur."""
    src = assign.select(F.col("doc_id").alias("src_doc"), "c", "z")
    dst = assign.select(F.col("doc_id").alias("dst_doc"), F.col("c").alias("c2"))
    n = diffs.select("src_doc", "dst_doc").join(src, "src_doc").join(dst, "dst_doc").groupBy("c", "c2", "z").agg((F.count("*") + smooth).alias("n"))
    over = {"per_community": W.partitionBy("c"), "joint": W.partitionBy(F.lit(0)), "per_pair_topic": W.partitionBy("c", "c2")}[norm]
    return n.select("c", "c2", "z", (F.col("n") / F.sum("n").over(over)).alias("p"))


def user_features(docs: DataFrame, friends: DataFrame, diffs: DataFrame) -> DataFrame:
    """(user_id, popularity, activeness) of every user: followers over followees and diffusing documents over documents; zero where the denominator is."""
    followers = friends.groupBy(F.col("dst").alias("user_id")).agg(F.count("*").alias("followers"))
    followees = friends.groupBy(F.col("src").alias("user_id")).agg(F.count("*").alias("followees"))
    written = docs.groupBy("user_id").agg(F.count("*").alias("n_docs"))
    diffusing = diffs.groupBy(F.col("src_user").alias("user_id")).agg(F.countDistinct("src_doc").alias("n_diff"))
    every = followers.join(followees, "user_id", "full_outer").join(written, "user_id", "full_outer").join(diffusing, "user_id", "full_outer")

    def ratio(a: str, b: str):
        return F.when(F.coalesce(b, F.lit(0)) > 0, F.coalesce(a, F.lit(0)) / F.col(b)).otherwise(F.lit(0.0))

    return every.select("user_id", ratio("followers", "followees").alias("popularity"), ratio("n_diff", "n_docs").alias("activeness"))
