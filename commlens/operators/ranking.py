"""Ranking of communities for queries, and its measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def reach(eta: DataFrame, theta: DataFrame) -> DataFrame:
    """(c, z, r): how much c diffuses on z, over all target communities weighted by their interest. Done once; it takes a factor of all communities off every query."""
    return eta.join(F.broadcast(theta.select(F.col("c").alias("c2"), "z", F.col("p").alias("t"))), ["c2", "z"]).groupBy("c", "z").agg(F.sum(F.col("p") * F.col("t")).alias("r"))


def query_topics(queries: DataFrame, phi: DataFrame) -> DataFrame:
    """(q_id, z, affinity) from (q_id, word): the product of the words' probabilities. Words out of the vocabulary have the same floor probability in
    every topic, which does not change the order, and are left out. Queries of several words are scaled by their best topic first, so that long ones do not vanish."""
    logs = queries.join(phi, "word").groupBy("q_id", "z").agg(F.sum(F.ln("p")).alias("l"), F.count("*").alias("n"))
    top = F.max("l").over(W.partitionBy("q_id"))
    return logs.select("q_id", "z", F.when(F.col("n") > 1, F.exp(F.col("l") - top)).otherwise(F.exp("l")).alias("affinity"))


def rank_communities(queries: DataFrame, phi: DataFrame, reached: DataFrame, top: int | None = None, normalise: bool = False) -> DataFrame:
    """(q_id, c, score, rank). ``normalise`` makes a query's topic affinities sum to one first."""
    topics = query_topics(queries, phi)
    if normalise:
        topics = topics.withColumn("affinity", F.col("affinity") / F.sum("affinity").over(W.partitionBy("q_id")))
    scores = topics.join(F.broadcast(reached), "z").groupBy("q_id", "c").agg(F.sum(F.col("r") * F.col("affinity")).alias("score"))
    ranked = scores.withColumn("rank", F.row_number().over(W.partitionBy("q_id").orderBy(F.round("score", 12).desc(), "c")))
    return ranked.where(F.col("rank") <= top) if top else ranked


def top_memberships(pi: DataFrame, k: int = 5) -> DataFrame:
    order = W.partitionBy("user_id").orderBy(F.round("p", 12).desc(), "c")
    return pi.withColumn("k", F.row_number().over(order)).where(F.col("k") <= k).select("user_id", "c")


def select_queries(tokens: DataFrame, diffs: DataFrame, min_freq: int, drop_top: int = 0) -> DataFrame:
    """(word, freq): words of diffusing documents that occur more than min_freq times, without the drop_top most frequent of all words."""
    common = tokens.groupBy("word").agg(F.sum("cnt").alias("n")).orderBy(F.desc("n"), "word").limit(drop_top)
    used = tokens.join(diffs.select(F.col("src_doc").alias("doc_id")).distinct(), "doc_id", "left_semi").groupBy("word").agg(F.sum("cnt").alias("freq"))
    return used.where(F.col("freq") > min_freq).join(common.select("word"), "word", "left_anti")


def frequency_bands(queries: DataFrame, bands: int = 5) -> DataFrame:
    """Queries with their equal-width frequency band, from 1."""
    ends = queries.agg(F.min("freq").alias("lo"), F.max("freq").alias("hi"))
    band = F.least(F.floor((F.col("freq") - F.col("lo")) * bands / F.greatest(F.col("hi") - F.col("lo"), F.lit(1))) + 1, F.lit(bands))
    return queries.crossJoin(F.broadcast(ends)).select("word", "freq", band.cast("int").alias("band"))


def relevant_users(tokens: DataFrame, diffs: DataFrame) -> DataFrame:
    """(q_id, user_id): users one of whose diffusing documents has the word."""
    return diffs.select(F.col("src_doc").alias("doc_id"), F.col("src_user").alias("user_id")).join(tokens.select("doc_id", F.col("word").alias("q_id")), "doc_id").select("q_id", "user_id").distinct()


def precision_recall(ranked: DataFrame, members: DataFrame, relevant: DataFrame, k: int) -> DataFrame:
    """(q_id, k, precision, recall) for 1..k: users of the first k communities against relevant users. Queries without relevant users are left out.
    A user counts from its best-ranked community on, so one aggregation serves every k."""
    first = ranked.join(members, "c").groupBy("q_id", "user_id").agg(F.min("rank").alias("k0"))
    ks = ranked.sparkSession.range(1, k + 1).select(F.col("id").cast("int").alias("k"))
    found = first.join(relevant.withColumn("hit", F.lit(1)), ["q_id", "user_id"], "left").groupBy("q_id", "k0").agg(F.count("*").alias("n"), F.count("hit").alias("h"))
    upto = found.join(F.broadcast(ks), F.col("k0") <= F.col("k")).groupBy("q_id", "k").agg(F.sum("n").alias("n"), F.sum("h").alias("h"))
    sizes = relevant.groupBy("q_id").agg(F.count("*").alias("rel"))
    return upto.join(sizes, "q_id").select("q_id", "k", (F.col("h") / F.col("n")).alias("precision"), (F.col("h") / F.col("rel")).alias("recall"))


def averages(pr: DataFrame, by_query: bool = False) -> DataFrame:
    """([q_id,] k, map, mar, maf): running means over 1..k, the mean over queries, and the harmonic mean of the two."""
    run = W.partitionBy("q_id").orderBy("k").rowsBetween(W.unboundedPreceding, 0)
    rows = pr.select("q_id", "k", F.avg("precision").over(run).alias("map"), F.avg("recall").over(run).alias("mar"))
    if not by_query:
        rows = rows.groupBy("k").agg(F.avg("map").alias("map"), F.avg("mar").alias("mar"))
    a, b = F.col("map"), F.col("mar")
    return rows.withColumn("maf", F.when(a + b > 0, 2 * a * b / (a + b)).otherwise(F.lit(0.0)))
