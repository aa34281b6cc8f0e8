"""Joint detection and profiling: the sampling and estimation loop.

A sweep scores all documents of a block from counters frozen at its start, draws topics, refreshes, and draws communities; only every
``blocks``-th document of a user moves at once, so a membership changes by a share of its documents at a time. Every step's
assignment is written through ``checkpoint`` (a table, or DataFrame.checkpoint), which cuts lineage and is where a run resumes.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens import scratch
from commlens.config import ProfilerConfig
from commlens.functions.expressions import sigmoid
from commlens.operators import counters, factors, measures, sampling
from commlens.sources.graphs import SocialGraph


def log_joint_terms(assign: DataFrame, tokens: DataFrame, communities: int, topics: int, alpha: float, rho: float, beta: float) -> DataFrame:
    """One row (users, communities, topics): the Dirichlet-multinomial parts of the log joint. Counts are summed by value first, so the
    factorial walk is done once per distinct count."""
    from commlens.functions.expressions import log_rising

    def part(counts: DataFrame, of: str, prior: float, dim: int, digits: int) -> DataFrame:
        cell = counts.groupBy("n").agg(F.count("*").alias("k")).select((F.col("k") * log_rising(F.lit(prior), F.col("n"))).alias("v"))
        whole = counts.groupBy(of).agg(F.sum("n").alias("n")).groupBy("n").agg(F.count("*").alias("k")).select((F.col("k") * log_rising(F.lit(prior * dim), F.col("n"))).alias("v"))
        return cell.agg(F.round(F.sum("v"), digits).alias("a")).crossJoin(whole.agg(F.round(F.sum("v"), digits).alias("b"))).select((F.col("a") - F.col("b")).alias("v"))

    n_words = tokens.select("word").distinct().count()
    users = part(counters.user_community(assign), "user_id", rho, communities, 4).withColumnRenamed("v", "users")
    comms = part(counters.community_topic(assign), "c", alpha, topics, 4).withColumnRenamed("v", "communities")
    words = part(counters.topic_word(assign, tokens), "z", beta, n_words, 3).withColumnRenamed("v", "topics")
    return users.crossJoin(comms).crossJoin(words)


def nu_gradient(scored: DataFrame, features: DataFrame) -> DataFrame:
    """One row (g1..g4, n): the gradient of the log likelihood of labelled, scored pairs in the individual weights."""
    miss = F.col("label") - sigmoid(F.col("y"))
    rows = factors.with_features(scored, features)
    names = ["s_popularity", "s_activeness", "d_popularity", "d_activeness"]
    return rows.agg(*(F.sum(miss * F.coalesce(F.col(c), F.lit(0.0))).alias(f"g{i}") for i, c in enumerate(names, 1)), F.count("*").alias("n"))


def negative_links(graph: SocialGraph, seed: int) -> DataFrame:
    """As many document pairs as diffusion links that are none, of different users: each link's source with documents picked by hash until one will do."""
    docs, links = graph.docs.select("doc_id", "user_id"), graph.diffs.select(F.col("src_doc").alias("src"), F.col("dst_doc").alias("dst")).distinct()
    own = graph.diffs.select("src_doc", F.col("src_user").alias("user_id")).distinct()
    targets, avoid = measures.numbered(docs, "doc_id"), None
    for _ in range(8):
        pairs = measures.non_links(links, targets, seed, avoid=avoid)
        owned = pairs.join(own.withColumnRenamed("src_doc", "src"), "src").join(docs.select(F.col("doc_id").alias("dst"), F.col("user_id").alias("to_user")), "dst")
        same = scratch.written(owned.where("user_id = to_user").select("src", "dst"))
        if same.isEmpty():
            break
        avoid = same if avoid is None else scratch.written(avoid.union(same))
    bins = graph.diffs.groupBy("src_doc", "src_user").agg(F.min("tbin").alias("tbin"))
    made = owned.where("user_id <> to_user").select(F.col("src").alias("src_doc"), F.col("dst").alias("dst_doc"), F.col("to_user").alias("dst_user"))
    return made.join(bins, "src_doc").select(*graph.diffs.columns)


def log_joint_links(friends: DataFrame, diffs: DataFrame) -> DataFrame:
    """One row (friends, diffusions): sums of the log probability of observed links, from their scores x and y."""
    sure = lambda x: -F.when(F.col(x) > 0, F.log1p(F.exp(-F.col(x)))).otherwise(F.log1p(F.exp(F.col(x))) - F.col(x))
    one = lambda df, x, name: df.agg(F.coalesce(F.sum(sure(x)), F.lit(0.0)).alias(name))
    return one(friends, "x", "friends").crossJoin(one(diffs, "y", "diffusions"))


@dataclass
class Profiles:
    """What a run gives: memberships (user_id, c, p), content profiles (c, z, p), topics (z, word, p), diffusion profiles (c, c2, z, p), weights of
    the individual factor, popularity (z, tbin, pop), user features, the last assignment, and the log joint of each sweep."""

    pi: DataFrame
    theta: DataFrame
    phi: DataFrame
    eta: DataFrame
    nu: tuple[float, ...]
    pop: DataFrame
    features: DataFrame
    assign: DataFrame
    trace: list[float]

    def tensor(self) -> DataFrame:
        return factors.tensor(self.theta, self.eta)


class JointProfiler:
    """``checkpoint`` writes what a step reads more than once and what it leaves behind; by default to tables in the shared folder, which go when no later step needs them."""

    def __init__(self, config: ProfilerConfig, checkpoint: Callable[[DataFrame], DataFrame] | None = None) -> None:
        self.config = config
        self.checkpoint = checkpoint or scratch.written

    def fit(self, graph: SocialGraph, start: DataFrame | None = None) -> Profiles:
        cfg, keep = self.config, self.checkpoint
        if cfg.freeze_communities and start is None:
            start = JointProfiler(variant(cfg, "links_only"), keep).fit(graph).assign
        block = F.pmod(F.row_number().over(W.partitionBy("user_id").orderBy("doc_id")), F.lit(cfg.blocks)).alias("block")
        blocks = keep(graph.docs.select("doc_id", block))
        assign = keep(start if start is not None else counters.first_assignment(graph.docs, cfg.communities, cfg.topics, cfg.seed))
        features = keep(counters.user_features(graph.docs, graph.friends, graph.diffs))
        negative = keep(negative_links(graph, cfg.seed)) if cfg.use_diffusion and "individual" in cfg.factors else None
        n_words = graph.tokens.select("word").distinct().count()
        nu: tuple[float, ...] = (0.0, 0.0, 0.0, 0.0)
        trace: list[float] = []
        sums: tuple[DataFrame, ...] | None = None
        for sweep in range(cfg.sweeps):
            for b in range(cfg.blocks):
                assign = self._step(graph, assign, blocks.where(F.col("block") == b).select("doc_id"), features, nu, n_words, (sweep * cfg.blocks + b) * 2)
            if negative is not None:
                nu = self._fit_nu(graph, assign, negative, features, nu)
            trace.append(self.log_joint(graph, assign, features, nu))
            if sweep >= cfg.burnin:
                sums = self._added(sums, graph, assign)
        return self._profiles(graph, assign, features, nu, trace, sums, cfg.sweeps - cfg.burnin)

    def log_joint(self, graph: SocialGraph, assign: DataFrame, features: DataFrame, nu: tuple[float, ...]) -> float:
        """Dirichlet parts and observed links of the kinds in use."""
        cfg = self.config
        row = log_joint_terms(assign, graph.tokens, cfg.communities, cfg.topics, cfg.topic_prior, cfg.community_prior, cfg.beta).first()
        parts = self._links(graph, assign)
        friends = factors.friend_scores(graph.friends, parts[0]) if cfg.use_friends else graph.friends.limit(0).withColumn("x", F.lit(0.0))
        diffs = self._scored(graph.diffs, assign, parts, features, nu) if self._by_profile else graph.diffs.limit(0).withColumn("y", F.lit(0.0))
        links = log_joint_links(friends, diffs).first()
        for df in parts:
            scratch.drop(df)
        return sum(row) + sum(links)

    @property
    def _by_profile(self) -> bool:
        return self.config.use_diffusion and self.config.diffusion_kind == "profile" and bool(self.config.factors)

    def _added(self, sums: tuple[DataFrame, ...] | None, graph: SocialGraph, assign: DataFrame) -> tuple[DataFrame, ...]:
        """Counters summed over sweeps."""
        now = (counters.user_community(assign), counters.community_topic(assign), counters.topic_word(assign, graph.tokens))
        if sums is not None:
            now = tuple(a.unionByName(b).groupBy(*[c for c in a.columns if c != "n"]).agg(F.sum("n").alias("n")) for a, b in zip(sums, now, strict=True))
        out = tuple(self.checkpoint(x) for x in now)
        for old in sums or ():
            scratch.drop(old)
        return out

    def _augment(self, salt: int) -> Callable[[DataFrame, str, str], DataFrame]:
        """Adds a link's augmentation variable: its mean, or a draw by the link, written once so that both ends see the same."""
        cfg = self.config
        if cfg.pg == "mean":
            return factors.augmentation_means

        def draw(scored: DataFrame, score: str, name: str) -> DataFrame:
            from commlens.functions.udfs import pg_draw

            key = F.xxhash64(*(c for c in ("src", "dst", "nth", "src_doc", "dst_doc") if c in scored.columns))
            return self.checkpoint(scored.withColumn(name, pg_draw(F.col(score), key, cfg.seed * 7919 + salt, cfg.pg)))

        return draw

    def _links(self, graph: SocialGraph, assign: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
        """Empirical memberships, tensor and popularity of an assignment, each written once: several terms of a step read them."""
        cfg, keep = self.config, self.checkpoint
        tensor = factors.tensor(counters.empirical_topics(assign), counters.eta(graph.diffs, assign, cfg.eta_norm))
        pop = counters.popularity(counters.topic_time(assign, graph.docs), cfg.popularity)
        return keep(counters.empirical_membership(assign)), keep(tensor), keep(pop)

    def _sent(self, graph: SocialGraph, parts: tuple[DataFrame, DataFrame, DataFrame]) -> tuple | None:
        """Tensor and popularity as arrays, or none where they have too many cells to send."""
        cfg = self.config
        bins = (graph.docs.agg(F.max("tbin")).first()[0] or 0) + 1
        if max(cfg.communities**2, bins) * cfg.topics > factors.TENSOR_CELLS:
            return None
        return sampling.sent(parts[1], (cfg.topics, cfg.communities, cfg.communities), ["z", "c", "c2"], "g"), sampling.sent(parts[2], (cfg.topics, bins), ["z", "tbin"], "pop")

    def _scored(self, links: DataFrame, assign: DataFrame, parts: tuple[DataFrame, DataFrame, DataFrame], features: DataFrame, nu: tuple[float, ...]) -> DataFrame:
        cfg = self.config
        pi, tensor, pop = parts
        return factors.diffusion_scores(factors.link_topics(links, assign, cfg.link_topic), pi, tensor, pop, features, nu, cfg.factors, cells=cfg.communities**2 * cfg.topics)

    def _step(self, graph: SocialGraph, assign: DataFrame, block: DataFrame, features: DataFrame, nu: tuple[float, ...], n_words: int, salt: int) -> DataFrame:
        """The assignment after a block's topics, then its communities, are drawn; tables of the step before are removed."""
        cfg, first = self.config, assign
        made: list[DataFrame] = []
        if cfg.use_topics:
            scores = sampling.topic_text_arrays(assign, graph.tokens, graph.docs, cfg.communities, cfg.topics, cfg.topic_prior, cfg.beta, n_words).join(block, "doc_id", "left_semi")
            if self._by_profile:
                parts = self._links(graph, assign)
                made += parts
                flat = self._sent(graph, parts)
                if flat:
                    terms = sampling.topic_link_arrays(graph.diffs, assign, parts[0], *flat, features, nu, cfg.factors, cfg.link_topic, cfg.pg, cfg.seed * 7919 + salt)
                else:
                    terms = sampling.wide_topic_link_arrays(graph.diffs, assign, *parts, features, nu, cfg.topics, cfg.factors, self._augment(salt), cfg.link_topic)
                scores = sampling.plus(scores, terms)
            drawn = sampling.draw_arrays(scores, "z", cfg.draw, cfg.seed * 100_003 + salt)
            assign = self.checkpoint(assign.join(drawn.withColumnRenamed("z", "z1"), "doc_id", "left").select("doc_id", "user_id", "c", F.coalesce("z1", "z").alias("z")))
            made.append(first)
        if not cfg.freeze_communities:
            made.append(assign)
            scores = sampling.community_text_arrays(assign, cfg.communities, cfg.topics, cfg.topic_prior, cfg.community_prior, cfg.use_text).join(block, "doc_id", "left_semi")
            parts = self._links(graph, assign) if self._by_profile else (self.checkpoint(counters.empirical_membership(assign)), None, None)
            made += [p for p in parts if p is not None]
            friends = graph.friends.select("src", "dst")
            if cfg.use_diffusion and cfg.diffusion_kind == "similarity":
                friends = friends.union(graph.diffs.select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst"))).groupBy("src", "dst").agg(F.count("*").alias("times"))
            if cfg.use_friends:
                scores = sampling.plus(scores, sampling.community_friend_arrays(assign, friends, parts[0], cfg.communities, self._augment(salt + 1)))
            if self._by_profile and "community" in cfg.factors:
                flat = self._sent(graph, parts)
                if flat:
                    terms = sampling.community_link_arrays(graph.diffs, assign, parts[0], *flat, features, nu, cfg.factors, cfg.link_topic, cfg.pg, cfg.seed * 7919 + salt + 1)
                else:
                    scored = self.checkpoint(self._scored(graph.diffs, assign, parts, features, nu))
                    made.append(scored)
                    terms = sampling.wide_community_link_arrays(scored, assign, parts[0], parts[1], cfg.communities, self._augment(salt + 1))
                scores = sampling.plus(scores, terms)
            drawn = sampling.draw_arrays(scores, "c", cfg.draw, cfg.seed * 100_003 + salt + 1)
            assign = self.checkpoint(assign.join(drawn.withColumnRenamed("c", "c1"), "doc_id", "left").select("doc_id", "user_id", F.coalesce("c1", "c").alias("c"), "z"))
        for df in made:
            scratch.drop(df)
        return assign

    def _fit_nu(self, graph: SocialGraph, assign: DataFrame, negative: DataFrame, features: DataFrame, nu: tuple[float, ...]) -> tuple[float, ...]:
        """Weights with the other factors fixed, over pairs scored once: gradient steps, each one aggregation of four sums, or a
        generalised linear regression with the other factors as its offset."""
        fixed = replace(self.config, factors=tuple(f for f in self.config.factors if f != "individual"))
        rest = JointProfiler(fixed, self.checkpoint)
        parts = rest._links(graph, assign)
        both = rest._scored(graph.diffs, assign, parts, features, nu).withColumn("label", F.lit(1)).union(rest._scored(negative, assign, parts, features, nu).withColumn("label", F.lit(0)))
        base = self.checkpoint(factors.with_features(both, features))
        names = ["s_popularity", "s_activeness", "d_popularity", "d_activeness"]
        if self.config.nu_fit == "glr":
            from pyspark.ml.feature import VectorAssembler
            from pyspark.ml.regression import GeneralizedLinearRegression

            data = VectorAssembler(inputCols=names, outputCol="x").transform(base.fillna(0.0, names).withColumn("label", F.col("label").cast("double")))
            if data.isEmpty():
                return nu
            return tuple(GeneralizedLinearRegression(family="binomial", link="logit", offsetCol="y", featuresCol="x", fitIntercept=False, regParam=1e-3).fit(data).coefficients.toArray().tolist())
        for _ in range(self.config.nu_steps):
            miss = F.col("label") - sigmoid(F.col("y") + factors.individual_score(nu))
            row = base.agg(*(F.sum(miss * F.coalesce(F.col(c), F.lit(0.0))) for c in names), F.count("*")).first()
            if not row[4]:
                break
            nu = tuple(w + self.config.nu_rate * (g or 0.0) / row[4] for w, g in zip(nu, row[:4], strict=True))
        for df in (*parts, base):
            scratch.drop(df)
        return nu

    def _profiles(self, graph: SocialGraph, assign: DataFrame, features: DataFrame, nu: tuple[float, ...], trace: list[float], sums: tuple[DataFrame, ...] | None, kept: int) -> Profiles:
        """Estimates from counters averaged over the sweeps after ``burnin``, or from the last ones; the diffusion profile and popularity from the last sweep."""
        cfg, keep = self.config, self.checkpoint
        counts = tuple(x.withColumn("n", F.col("n") / kept) for x in sums) if sums else (counters.user_community(assign), counters.community_topic(assign), counters.topic_word(assign, graph.tokens))
        return Profiles(
            keep(counters.smoothed_membership(counts[0], cfg.communities, cfg.community_prior)), keep(counters.smoothed_topics(counts[1], cfg.communities, cfg.topics, cfg.topic_prior)),
            keep(counters.smoothed_words(counts[2], graph.vocab(), cfg.beta)), keep(counters.eta(graph.diffs, assign, cfg.eta_norm)), nu,
            keep(counters.popularity(counters.topic_time(assign, graph.docs), cfg.popularity)), features, assign, trace,
        )


def variant(config: ProfilerConfig, name: str) -> ProfilerConfig:
    """The settings of an ablation or of the strength-block baseline."""
    changes = {
        "full": {}, "two_stage": {"freeze_communities": True}, "homogeneous": {"diffusion_kind": "similarity"}, "community_only": {"factors": ("community",)},
        "no_topic": {"factors": ("community", "individual")}, "strength_block": {"use_friends": False, "factors": ("community",)}, "friends_only": {"use_diffusion": False},
        "links_only": {"use_text": False, "use_topics": False, "use_diffusion": False, "factors": ()},
    }
    return replace(config, **changes[name])
