"""Reports on profiles: diffusion graphs, openness and generality, labels, exchanges, case studies, exports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens.sources.graphs import SocialGraph


def correlation(a: str, b: str) -> Column:
    """Pearson's correlation; null where a side does not vary."""
    return F.try_divide(F.covar_samp(a, b), F.stddev_samp(a) * F.stddev_samp(b))


def diffusion_edges(eta: DataFrame, topic: int | None = None) -> DataFrame:
    """(c, c2, w) on one topic, or over all."""
    if topic is not None:
        return eta.where(F.col("z") == topic).select("c", "c2", F.col("p").alias("w"))
    return eta.groupBy("c", "c2").agg(F.sum("p").alias("w"))


def prune_edges(edges: DataFrame) -> DataFrame:
    """Edges no weaker than the average."""
    mean = edges.agg(F.avg("w").alias("m"))
    return edges.crossJoin(F.broadcast(mean)).where(F.round("w", 9) >= F.round("m", 9)).drop("m")


def openness(eta: DataFrame) -> DataFrame:
    """(c, openness): the share of a community's diffusion that goes to others."""
    return eta.groupBy("c").agg((1 - F.sum(F.when(F.col("c") == F.col("c2"), F.col("p")).otherwise(0.0)) / F.sum("p")).alias("openness"))


def generality(eta: DataFrame) -> DataFrame:
    """(z, n_communities): communities that diffuse anything on a topic."""
    return eta.groupBy("z").agg(F.countDistinct("c").alias("n_communities"))


def top_words(phi: DataFrame, k: int) -> DataFrame:
    ranked = phi.withColumn("rank", F.row_number().over(W.partitionBy("z").orderBy(F.round("p", 12).desc(), "word")))
    return ranked.where(F.col("rank") <= k).select("z", "word", "rank")


def community_labels(theta: DataFrame, phi: DataFrame, k: int) -> DataFrame:
    """(c, label): a community's likeliest words."""
    p = theta.select("c", "z", F.col("p").alias("t")).join(phi, "z").groupBy("c", "word").agg(F.sum(F.col("t") * F.col("p")).alias("p"))
    ranked = p.withColumn("rank", F.row_number().over(W.partitionBy("c").orderBy(F.round("p", 12).desc(), "word"))).where(F.col("rank") <= k)
    return ranked.groupBy("c").agg(F.concat_ws(" ", F.transform(F.array_sort(F.collect_list(F.struct("rank", "word"))), lambda x: x["word"])).alias("label"))


def exchange(eta: DataFrame, a: int, b: int, k: int) -> DataFrame:
    """The k strongest topics between two communities, in each direction."""
    both = eta.where(((F.col("c") == a) & (F.col("c2") == b)) | ((F.col("c") == b) & (F.col("c2") == a)))
    return both.withColumn("k", F.row_number().over(W.partitionBy("c", "c2").orderBy(F.round("p", 12).desc(), "z"))).where(F.col("k") <= k).drop("k")


def individual_study(graph: SocialGraph, features: DataFrame) -> DataFrame:
    """Correlation over users of documents with diffusions made, and of popularity with diffusions received."""
    made = graph.diffs.groupBy(F.col("src_user").alias("user_id")).agg(F.count("*").alias("n_out"))
    got = graph.diffs.groupBy(F.col("dst_user").alias("user_id")).agg(F.count("*").alias("n_in"))
    users = graph.docs.groupBy("user_id").agg(F.count("*").alias("n_docs")).join(features, "user_id", "left").join(made, "user_id", "left").join(got, "user_id", "left").fillna(0, ["n_out", "n_in"])
    return users.agg(correlation("n_docs", "n_out").alias("corr_made"), correlation("popularity", "n_in").alias("corr_received"))


def topic_time_study(assign: DataFrame, graph: SocialGraph) -> DataFrame:
    """(z, corr): over time bins, documents on a topic against diffusions of it."""
    n = assign.select("doc_id", "z").join(graph.docs.select("doc_id", "tbin"), "doc_id").groupBy("z", "tbin").agg(F.count("*").alias("n"))
    e = graph.diffs.join(assign.select(F.col("doc_id").alias("src_doc"), "z"), "src_doc").groupBy("z", "tbin").agg(F.count("*").alias("e"))
    return n.join(e, ["z", "tbin"], "left").fillna(0, ["e"]).groupBy("z").agg(correlation("n", "e").alias("corr"))


def attribute_profile(pi: DataFrame, attributes: DataFrame) -> DataFrame:
    """(c, value, share): a community's distribution over a user attribute (user_id, value), users weighted by membership."""
    w = pi.join(attributes, "user_id").groupBy("c", "value").agg(F.sum("p").alias("w"))
    return w.select("c", "value", (F.col("w") / F.sum("w").over(W.partitionBy("c"))).alias("share"))


def export_graph(edges: DataFrame, path: str, fmt: str = "json") -> None:
    """Writes edges as JSON lines, or as the edge lines of a DOT graph."""
    if fmt == "json":
        edges.select(F.to_json(F.struct("c", "c2", "w")).alias("value")).write.mode("overwrite").text(path)
    elif fmt == "dot":
        edges.select(F.format_string('"%d" -> "%d" [weight=%.6f];', "c", "c2", "w").alias("value")).write.mode("overwrite").text(path)
    else:
        raise ValueError(f"no such format: {fmt}")
