"""The experiments: cross-validated tasks for the model, its ablations and the baselines, and scaling runs.

Held-out links are taken out of training entirely: features and diffusion profiles come from the training links of the fold. Negatives
are drawn once per fold, as many as positives, and exclude all positives.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens.config import ProfilerConfig
from commlens.functions.expressions import noise
from commlens.operators import counters, diffusion, factors, measures, ranking
from commlens.plans import baselines
from commlens.plans.profiler import JointProfiler, Profiles, negative_links, variant
from commlens.sources.graphs import SocialGraph

Keep = Callable[[DataFrame], DataFrame]


@dataclass
class Fold:
    """Training graph, labelled test pairs of both kinds of links, all tokens, and those of the documents held out."""

    train: SocialGraph
    friends: DataFrame
    diffs: DataFrame
    tokens: DataFrame
    held: DataFrame


def folds(graph: SocialGraph, keep: Keep, n: int = 10, only: int | None = None, seed: int = 5) -> list[Fold]:
    """The folds of both kinds of links and of documents by hash; ``only`` gives that many. Words and links of held-out documents are out of training."""
    out = []
    fold_t = measures.fold_of(n, seed, F.col("doc_id"))
    fold_f, fold_d = measures.fold_of(n, seed, F.col("src"), F.col("dst")), measures.fold_of(n, seed, F.col("src_doc"), F.col("dst_doc"))
    people = keep(measures.numbered(graph.docs, "user_id"))
    for k in range(only or n):
        test_f, test_d = graph.friends.where(fold_f == k), graph.diffs.where(fold_d == k)
        held = keep(graph.docs.where(fold_t == k).select("doc_id"))
        inside = graph.diffs.where(fold_d != k)
        for end in ("src_doc", "dst_doc"):
            inside = inside.join(held.withColumnRenamed("doc_id", end), end, "left_anti")
        train = SocialGraph(keep(graph.docs.join(held, "doc_id", "left_anti")), keep(graph.tokens.join(held, "doc_id", "left_anti")), keep(graph.friends.where(fold_f != k)), keep(inside.select(*graph.diffs.columns)))
        other_f = measures.non_links(test_f, people, salt=31 + k).join(graph.friends, ["src", "dst"], "left_anti")
        other_d = negative_links(replace_links(graph, test_d), seed * 100 + k).join(graph.diffs.select("src_doc", "dst_doc"), ["src_doc", "dst_doc"], "left_anti").select(*graph.diffs.columns)
        out.append(Fold(train, keep(_labelled(test_f, other_f)), keep(_labelled(test_d, other_d)), graph.tokens, keep(graph.tokens.join(held, "doc_id", "left_semi"))))
    return out


def replace_links(graph: SocialGraph, diffs: DataFrame) -> SocialGraph:
    return SocialGraph(graph.docs, graph.tokens, graph.friends, diffs)


def _labelled(positive: DataFrame, negative: DataFrame) -> DataFrame:
    return positive.withColumn("label", F.lit(1)).union(negative.withColumn("label", F.lit(0)))


def _auc(scored: DataFrame, score: str) -> float | None:
    return measures.auc(scored.select(F.round(score, 12).alias("score"), "label")).first().auc


def friendship_auc(pairs: DataFrame, pi: DataFrame) -> float | None:
    links = pairs.select("src", "dst").distinct()
    return _auc(factors.friend_scores(links, pi).join(pairs, ["src", "dst"]), "x")


def diffusion_auc(pairs: DataFrame, profiles: Profiles, tokens: DataFrame, config: ProfilerConfig) -> float | None:
    """Held-out diffusion with the averages over the source document's topics; homogeneous models score both ends' similarity instead."""
    if config.diffusion_kind == "similarity":
        return _auc(factors.similarity_scores(pairs, profiles.pi).join(pairs, ["src_doc", "dst_doc"]), "y")
    mix = profiles.pi.join(F.broadcast(profiles.theta.select("c", "z", F.col("p").alias("t"))), "c").groupBy("user_id", "z").agg(F.sum(F.col("p") * F.col("t")).alias("w"))
    topics = diffusion.topic_posterior(tokens, profiles.phi, config.topics, mix)
    return _auc(diffusion.score_pairs(pairs, topics, profiles.pi, profiles.tensor(), profiles.pop, profiles.features, profiles.nu, config.topics, config.factors or ("community",), ("label",)), "p")


def mean_conductance(graph: SocialGraph, pi: DataFrame, top: int = 5) -> float | None:
    return measures.conductance(graph.friends, ranking.top_memberships(pi, top)).agg(F.avg("conductance")).first()[0]


def ranking_maf(graph: SocialGraph, pi: DataFrame, theta: DataFrame, phi: DataFrame, eta: DataFrame, k: int = 5, min_freq: int = 5) -> list[tuple[int, float]]:
    """(k, MAF) for words of diffusing documents above a frequency."""
    queries = ranking.select_queries(graph.tokens, graph.diffs, min_freq).select(F.col("word").alias("q_id"), "word")
    ranked = ranking.rank_communities(queries, phi, ranking.reach(eta, theta), k)
    pr = ranking.precision_recall(ranked, ranking.top_memberships(pi), ranking.relevant_users(graph.tokens, graph.diffs), k)
    return [(r.k, r.maf) for r in ranking.averages(pr).orderBy("k").collect()]


def run_variant(name: str, config: ProfilerConfig, fold: Fold, keep: Keep) -> dict[str, float | None]:
    """The three tasks for the full model or a variant of it, on one fold."""
    cfg = variant(config, name)
    got = JointProfiler(cfg, keep).fit(fold.train)
    return {
        "conductance": mean_conductance(fold.train, got.pi), "friendship_auc": friendship_auc(fold.friends, got.pi), "diffusion_auc": diffusion_auc(fold.diffs, got, fold.tokens, cfg),
        "perplexity": measures.perplexity(fold.held, got.pi, got.theta, got.phi).first().perplexity, "maf": ranking_maf(fold.train, got.pi, got.theta, got.phi, got.eta)[-1][1],
    }


def run_aggregated(pi: DataFrame, fold: Fold, config: ProfilerConfig, keep: Keep) -> dict[str, float | None]:
    """Detect first, then aggregate: detected memberships with profiles summed from document mixtures and links."""
    doc_topics, phi, _ = baselines.topic_mixtures(fold.train, config.topics, 10, keep)
    theta, eta = keep(baselines.aggregate_content(pi, doc_topics)), keep(baselines.aggregate_diffusion(pi, doc_topics, fold.train.diffs))
    none = fold.train.docs.limit(0)
    mixed = Profiles(pi, theta, phi, eta, (0.0,) * 4, none.selectExpr("0 AS z", "tbin", "0D AS pop"), counters.user_features(fold.train.docs, fold.train.friends, fold.train.diffs), doc_topics, [])
    only = replace(config, factors=("community",))
    return {"diffusion_auc": diffusion_auc(fold.diffs, mixed, fold.tokens, only), "perplexity": measures.perplexity(fold.held, pi, theta, phi).first().perplexity, "maf": ranking_maf(fold.train, pi, theta, phi, eta)[-1][1]}


def run_baseline(name: str, fold: Fold, config: ProfilerConfig, keep: Keep) -> dict[str, float | None]:
    """TopicLink, UserFeatureLink or RoleBlock on one fold; tasks that a method has no part in are missing."""
    if name == "TopicLink":
        got = baselines.TopicLink(config.topics).fit(fold.train, keep)
        return {"conductance": mean_conductance(fold.train, got.member), "friendship_auc": friendship_auc(fold.friends, got.member), "diffusion_auc": _auc(got.link_scores(fold.diffs), "score")}
    if name == "UserFeatureLink":
        negative = negative_links(fold.train, 77)
        got = baselines.UserFeatureLink(fold.train).fit(_labelled(fold.train.diffs, negative))
        return {"diffusion_auc": _auc(got.link_scores(fold.diffs), "score")}
    if name == "RoleBlock":
        got = baselines.RoleBlock(config.communities).fit(fold.train, keep)
        pairs = fold.diffs.select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst"), "label")
        return {
            "conductance": mean_conductance(fold.train, got.member), "friendship_auc": _auc(got.scores(fold.friends.select("src", "dst").distinct()).join(fold.friends, ["src", "dst"]), "x"),
            "diffusion_auc": _auc(got.scores(pairs.select("src", "dst").distinct(), "diff").join(pairs, ["src", "dst"]), "x"),
        }
    raise ValueError(f"no such baseline: {name}")


def sample_graph(graph: SocialGraph, fraction: float, seed: int = 3) -> SocialGraph:
    """A share of the documents, and of both kinds of links among what is left, by hash."""
    docs = graph.docs.where(noise(seed, F.col("doc_id")) < fraction)
    ids = docs.select("doc_id")
    diffs = graph.diffs.where(noise(seed + 1, F.col("src_doc"), F.col("dst_doc")) < fraction).join(ids.withColumnRenamed("doc_id", "src_doc"), "src_doc", "left_semi").join(ids.withColumnRenamed("doc_id", "dst_doc"), "dst_doc", "left_semi")
    return SocialGraph(docs, graph.tokens.join(ids, "doc_id", "left_semi"), graph.friends.where(noise(seed + 2, F.col("src"), F.col("dst")) < fraction), diffs)


def sweep_seconds(graph: SocialGraph, config: ProfilerConfig, keep: Keep) -> float:
    """Seconds of one sweep."""
    began = time.time()
    JointProfiler(replace(config, sweeps=1), keep).fit(graph)
    return time.time() - began


def linearity(points: list[tuple[float, float]]) -> float:
    """R squared of seconds against fractions."""
    n = len(points)
    mx, my = sum(x for x, _ in points) / n, sum(y for _, y in points) / n
    sxy, sxx, syy = sum((x - mx) * (y - my) for x, y in points), sum((x - mx) ** 2 for x, _ in points), sum((y - my) ** 2 for _, y in points)
    return sxy * sxy / (sxx * syy) if sxx and syy else 1.0


def relative_gain(ours: float, other: float) -> float:
    return (ours - other) / other
