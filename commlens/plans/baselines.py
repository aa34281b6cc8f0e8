"""Baselines: topic links, user features, role blocks, strength blocks, and profiles aggregated after detection."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens import scratch
from commlens.functions.expressions import uniform
from commlens.operators import counters, factors, sampling
from commlens.sources.graphs import SocialGraph


def hard_topics(assign: DataFrame) -> DataFrame:
    """(doc_id, user_id, z, p) with all weight on the assigned topic."""
    return assign.select("doc_id", "user_id", "z", F.lit(1.0).alias("p"))


# Aggregated profiles


def aggregate_content(pi: DataFrame, doc_topics: DataFrame, normalise: bool = True) -> DataFrame:
    """(c, z, p): users' mean topics, weighted by membership; a distribution per community if ``normalise``, else the plain sum."""
    sizes = doc_topics.groupBy("user_id").agg(F.countDistinct("doc_id").alias("n"))
    mean = doc_topics.groupBy("user_id", "z").agg(F.sum("p").alias("s")).join(sizes, "user_id").select("user_id", "z", (F.col("s") / F.col("n")).alias("m"))
    w = pi.join(mean, "user_id").groupBy("c", "z").agg(F.sum(F.col("p") * F.col("m")).alias("p"))
    return w.select("c", "z", (F.col("p") / F.sum("p").over(W.partitionBy("c"))).alias("p")) if normalise else w


def aggregate_diffusion(pi: DataFrame, doc_topics: DataFrame, diffs: DataFrame) -> DataFrame:
    """(c, c2, z, p): links weighted by both memberships and both documents' topics, per community."""
    s = doc_topics.select(F.col("doc_id").alias("src_doc"), "z", F.col("p").alias("ps"))
    d = doc_topics.select(F.col("doc_id").alias("dst_doc"), "z", F.col("p").alias("pd"))
    a = pi.select(F.col("user_id").alias("src_user"), "c", F.col("p").alias("pa"))
    b = pi.select(F.col("user_id").alias("dst_user"), F.col("c").alias("c2"), F.col("p").alias("pb"))
    links = diffs.join(s, "src_doc").join(d, ["dst_doc", "z"]).groupBy("src_user", "dst_user", "z").agg(F.sum(F.col("ps") * F.col("pd")).alias("w"))
    cells = links.join(a, "src_user").join(b, "dst_user").groupBy("c", "c2", "z").agg(F.sum(F.col("w") * F.col("pa") * F.col("pb")).alias("w"))
    return cells.select("c", "c2", "z", (F.col("w") / F.sum("w").over(W.partitionBy("c"))).alias("p"))


# Topic links


def topic_link_rates(doc_topics: DataFrame, diffs: DataFrame) -> DataFrame:
    """(z, rate): links whose ends share a topic, over the pairs of documents that could."""
    s = doc_topics.select(F.col("doc_id").alias("src_doc"), "z", F.col("p").alias("ps"))
    d = doc_topics.select(F.col("doc_id").alias("dst_doc"), "z", F.col("p").alias("pd"))
    n = diffs.select("src_doc", "dst_doc").join(s, "src_doc").join(d, ["dst_doc", "z"]).groupBy("z").agg(F.sum(F.col("ps") * F.col("pd")).alias("n"))
    size = doc_topics.groupBy("z").agg(F.sum("p").alias("m"))
    return n.join(size, "z").select("z", (F.col("n") / (F.col("m") * F.col("m"))).alias("rate"))


def mixture_step(tokens: DataFrame, theta: DataFrame, phi: DataFrame, topics: int, alpha: float, beta: float, n_words: int, diffs: DataFrame | None = None, rate: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """One step of expectation and maximisation: (doc_id, user_id, z, p) mixtures and (z, word, p) topics from the former ones. Each token is shared among topics
    by mixture and topic; with ``diffs`` and (z, rate), each diffusion link is one more token of both its documents, shared by both mixtures and the rate.
    A token, a document, a link and a word each are one row with an array of all topics."""
    every = range(topics)
    own, by_word = sampling.dense(theta, ["doc_id"], "z", "p", topics, "t"), sampling.dense(phi, ["word"], "z", "p", topics, "b")
    by_word = F.broadcast(by_word) if n_words * topics <= factors.TENSOR_CELLS else by_word
    near = tokens.select("doc_id", "word", "cnt").join(own, "doc_id").join(by_word, "word")
    near = near.withColumn("h", F.array(*(F.col("t")[i] * F.col("b")[i] for i in every))).withColumn("all", sum(F.col("h")[i] for i in every)).where(F.col("all") > 0)
    near = near.select("doc_id", "word", F.transform("h", lambda x: F.col("cnt") * x / F.col("all")).alias("h"))
    parts = near.select("doc_id", "h")
    if diffs is not None:
        rates = F.broadcast(sampling.dense(rate.withColumn("one", F.lit(1)), ["one"], "z", "rate", topics, "r").select("r"))
        ends = diffs.select("src_doc", "dst_doc").join(own.toDF("src_doc", "s"), "src_doc").join(own.toDF("dst_doc", "d"), "dst_doc").crossJoin(rates)
        ends = ends.withColumn("w", F.array(*(F.col("s")[i] * F.col("d")[i] * F.col("r")[i] + 1e-12 for i in every))).withColumn("all", sum(F.col("w")[i] for i in every))
        parts = parts.unionByName(ends.select(F.explode(F.array("src_doc", "dst_doc")).alias("doc_id"), F.transform("w", lambda x: x / F.col("all")).alias("h")))
    counts = parts.groupBy("doc_id").agg(*(F.sum(F.col("h")[i]).alias(f"h{i}") for i in every))
    counts = counts.select("doc_id", F.array(*(f"h{i}" for i in every)).alias("n")).withColumn("all", sum(F.col("n")[i] for i in every))
    fresh = theta.select("doc_id", "user_id", "z").join(counts, "doc_id")
    fresh = fresh.select("doc_id", "user_id", "z", ((F.get("n", F.col("z")) + alpha) / (F.col("all") + alpha * topics)).alias("p"))
    words = near.groupBy("word").agg(*(F.sum(F.col("h")[i]).alias(f"h{i}") for i in every)).select("word", F.posexplode(F.array(*(f"h{i}" for i in every))).alias("z", "n"))
    words = words.join(phi.select("z", "word"), ["z", "word"], "left_semi")
    sizes = words.groupBy("z").agg(F.sum("n").alias("all"))
    return fresh, words.join(F.broadcast(sizes), "z").select("z", "word", ((F.col("n") + beta) / (F.col("all") + beta * n_words)).alias("p"))


def link_shares(diffs: DataFrame, theta: DataFrame, rate: DataFrame) -> DataFrame:
    """(src_doc, dst_doc, z, q): each link shared among topics by both documents' mixtures and the topic's rate."""
    s = theta.select(F.col("doc_id").alias("src_doc"), "z", F.col("p").alias("ps"))
    d = theta.select(F.col("doc_id").alias("dst_doc"), "z", F.col("p").alias("pd"))
    q = diffs.select("src_doc", "dst_doc").join(s, "src_doc").join(d, ["dst_doc", "z"]).join(F.broadcast(rate), "z").withColumn("w", F.col("ps") * F.col("pd") * F.col("rate") + 1e-12)
    total = q.groupBy("src_doc", "dst_doc").agg(F.sum("w").alias("all"))
    return q.join(total, ["src_doc", "dst_doc"]).select("src_doc", "dst_doc", "z", (F.col("w") / F.col("all")).alias("q"))


def link_rates(diffs: DataFrame, theta: DataFrame, rate: DataFrame) -> DataFrame:
    """(z, rate): links shared to each topic over the pairs of documents that could carry it."""
    n = link_shares(diffs, theta, rate).groupBy("z").agg(F.sum("q").alias("n"))
    return theta.groupBy("z").agg(F.sum("p").alias("m")).join(n, "z", "left").select("z", (F.coalesce("n", F.lit(0.0)) / (F.col("m") * F.col("m"))).alias("rate"))


def first_mixtures(docs: DataFrame, tokens: DataFrame, topics: int) -> tuple[DataFrame, DataFrame]:
    """Mixtures and topics to start from: every document's and word's weights by hash."""
    grid = F.explode(F.sequence(F.lit(0), F.lit(topics - 1))).alias("z")
    theta = docs.select("doc_id", "user_id", grid).withColumn("w", uniform(F.col("doc_id") * 1009 + F.col("z"), 505) + 0.5)
    phi = tokens.select("word").distinct().select("word", grid).withColumn("w", uniform(F.pmod(F.crc32("word"), F.lit(1_000_003)) * 1009 + F.col("z"), 606) + 0.5)
    share = lambda df, *by: F.col("w") / F.sum("w").over(W.partitionBy(*by))
    return theta.select("doc_id", "user_id", "z", share(theta, "doc_id").alias("p")), phi.select("z", "word", share(phi, "z").alias("p"))


def topic_mixtures(graph: SocialGraph, topics: int, steps: int, checkpoint, links: bool = False, alpha: float = 0.1, beta: float = 0.1) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(doc_id, user_id, z, p) mixtures of documents, (z, word, p) topics and (z, rate) link rates; with ``links`` diffusion links shape the mixtures too."""
    n_words = graph.tokens.select("word").distinct().count()
    theta, phi = (checkpoint(x) for x in first_mixtures(graph.docs, graph.tokens, topics))
    rate = graph.docs.sparkSession.range(topics).select(F.col("id").cast("int").alias("z"), F.lit(1.0).alias("rate"))
    for _ in range(steps):
        old = (theta, phi)
        theta, phi = (checkpoint(x) for x in mixture_step(graph.tokens, theta, phi, topics, alpha, beta, n_words, graph.diffs if links else None, rate if links else None))
        if links:
            rate = checkpoint(link_rates(graph.diffs, theta, rate))
        for x in old:
            scratch.drop(x)
    return theta, phi, rate if links else checkpoint(topic_link_rates(theta, graph.diffs))


class TopicLink:
    """Mixtures of topics that words and diffusion links share, fitted together, and a link rate per topic. A user's membership is the mean of its documents' topics."""

    def __init__(self, topics: int, steps: int = 10, beta: float = 0.1) -> None:
        self.topics, self.steps, self.beta = topics, steps, beta

    def fit(self, graph: SocialGraph, checkpoint) -> TopicLink:
        self.doc_topics, self.phi, self.rates = topic_mixtures(graph, self.topics, self.steps, checkpoint, True, beta=self.beta)
        self.member = self.doc_topics.groupBy("user_id", "z").agg(F.sum("p").alias("s")).select("user_id", F.col("z").alias("c"), (F.col("s") / F.sum("s").over(W.partitionBy("user_id"))).alias("p"))
        return self

    def link_scores(self, pairs: DataFrame) -> DataFrame:
        """(src_doc, dst_doc, score)"""
        s = self.doc_topics.select(F.col("doc_id").alias("src_doc"), "z", F.col("p").alias("ps"))
        d = self.doc_topics.select(F.col("doc_id").alias("dst_doc"), "z", F.col("p").alias("pd"))
        got = pairs.join(s, "src_doc").join(d, ["dst_doc", "z"]).join(F.broadcast(self.rates), "z").groupBy("src_doc", "dst_doc").agg(F.sum(F.col("ps") * F.col("pd") * F.col("rate")).alias("score"))
        return pairs.join(got, ["src_doc", "dst_doc"], "left").fillna(0.0, ["score"])

    def friend_scores(self, pairs: DataFrame) -> DataFrame:
        return factors.friend_scores(pairs, self.member)


# User features


def link_design(graph: SocialGraph, pairs: DataFrame, features: DataFrame) -> DataFrame:
    """Pairs (src_doc, dst_doc, src_user, dst_user, ...) with features of both users and of their relation."""
    friends = graph.friends.select(F.col("src").alias("src_user"), F.col("dst").alias("dst_user")).distinct().withColumn("friend", F.lit(1))
    past = graph.diffs.groupBy("src_user", "dst_user").agg(F.count("*").alias("past"))
    out = factors.with_features(pairs, features).join(friends, ["src_user", "dst_user"], "left").join(past, ["src_user", "dst_user"], "left")
    return out.fillna(0, ["friend", "past"]).fillna(0.0, ["s_popularity", "s_activeness", "d_popularity", "d_activeness"])


class UserFeatureLink:
    """Logistic regression on link features and on the cosine of the users' words; it has no communities."""

    columns = ["friend", "past", "s_popularity", "s_activeness", "d_popularity", "d_activeness", "cosine"]

    def __init__(self, graph: SocialGraph) -> None:
        self.graph = graph
        self.features = counters.user_features(graph.docs, graph.friends, graph.diffs)

    def _design(self, pairs: DataFrame) -> DataFrame:
        n = self.graph.tokens.groupBy("user_id", "word").agg(F.sum("cnt").alias("n"))
        unit = n.select("user_id", "word", (F.col("n") / F.sqrt(F.sum(F.col("n") * F.col("n")).over(W.partitionBy("user_id")))).alias("v"))
        both = pairs.select("src_user", "dst_user").distinct()
        cosine = both.join(unit.select(F.col("user_id").alias("src_user"), "word", F.col("v").alias("va")), "src_user").join(unit.select(F.col("user_id").alias("dst_user"), "word", F.col("v").alias("vb")), ["dst_user", "word"])
        cosine = cosine.groupBy("src_user", "dst_user").agg(F.sum(F.col("va") * F.col("vb")).alias("cosine"))
        return link_design(self.graph, pairs, self.features).join(cosine, ["src_user", "dst_user"], "left").fillna(0.0, ["cosine"])

    def fit(self, pairs: DataFrame) -> UserFeatureLink:
        """``pairs`` has a label besides the link's columns."""
        from pyspark.ml.classification import LogisticRegression
        from pyspark.ml.feature import VectorAssembler

        self._assembler = VectorAssembler(inputCols=self.columns, outputCol="features")
        data = self._assembler.transform(self._design(pairs)).select("features", F.col("label").cast("double").alias("label"))
        self.model = LogisticRegression(maxIter=25, regParam=1e-3).fit(data)
        return self

    def link_scores(self, pairs: DataFrame) -> DataFrame:
        from pyspark.ml.functions import vector_to_array

        out = self.model.transform(self._assembler.transform(self._design(pairs)))
        return out.withColumn("score", vector_to_array("probability")[1]).drop("features", "rawPrediction", "probability", "prediction")


# Role blocks


def block_counts(pi: DataFrame, friends: DataFrame) -> DataFrame:
    """(c, c2, n): expected friendship links between communities."""
    a = pi.select(F.col("user_id").alias("src"), "c", F.col("p").alias("pa"))
    b = pi.select(F.col("user_id").alias("dst"), F.col("c").alias("c2"), F.col("p").alias("pb"))
    return friends.join(a, "src").join(b, "dst").groupBy("c", "c2").agg(F.sum(F.col("pa") * F.col("pb")).alias("n"))


def block_rates(q: DataFrame, links: DataFrame) -> DataFrame:
    """(b, b2, rate) over all pairs of blocks: links between them over the pairs of users that could have one."""
    size = q.groupBy("b").agg(F.sum("p").alias("m"))
    n = block_counts(q.withColumnRenamed("b", "c"), links).select(F.col("c").alias("b"), F.col("c2").alias("b2"), "n")
    grid = size.crossJoin(F.broadcast(size.select(F.col("b").alias("b2"), F.col("m").alias("m2"))))
    return grid.join(n, ["b", "b2"], "left").select("b", "b2", ((F.coalesce("n", F.lit(0.0)) + 0.01) / (F.col("m") * F.col("m2") + 1)).alias("rate"))


def role_step(q: DataFrame, links: list[DataFrame], rates: list[DataFrame]) -> DataFrame:
    """(user_id, b, p): memberships of blocks after one mean-field step, from the neighbours' memberships over all kinds of links, in both directions."""
    size = q.groupBy("b").agg(F.sum("p").alias("m"))
    total = size.agg(F.sum("m").alias("all"))
    base = size.crossJoin(F.broadcast(total)).select("b", F.ln(F.col("m") / F.col("all") + 1e-9).alias("v"))
    seen = None
    for e, w in zip(links, rates, strict=True):
        logs = w.withColumn("l", F.ln("rate"))
        for here, there, own, other in (("src", "dst", "b", "b2"), ("dst", "src", "b2", "b")):
            near = e.select(F.col(here).alias("user_id"), F.col(there).alias("v")).join(q.select(F.col("user_id").alias("v"), F.col("b").alias("o"), "p"), "v").groupBy("user_id", "o").agg(F.sum("p").alias("s"))
            part = near.join(F.broadcast(logs.select(F.col(own).alias("k"), F.col(other).alias("o"), "l")), "o").groupBy("user_id", F.col("k").alias("b")).agg(F.sum(F.col("s") * F.col("l")).alias("v"))
            seen = part if seen is None else seen.union(part)
            less = logs.join(size.select(F.col("b").alias(other), "m"), other).groupBy(F.col(own).alias("b")).agg((-F.sum(F.col("rate") * F.col("m"))).alias("v"))
            base = base.union(less)
    base = base.groupBy("b").agg(F.sum("v").alias("base"))
    pull = seen.groupBy("user_id", "b").agg(F.sum("v").alias("v"))
    x = q.select("user_id").distinct().crossJoin(F.broadcast(base)).join(pull, ["user_id", "b"], "left").select("user_id", "b", (F.col("base") + F.coalesce("v", F.lit(0.0))).alias("x"))
    own = W.partitionBy("user_id")
    e = x.select("user_id", "b", F.exp(F.col("x") - F.max("x").over(own)).alias("e"))
    return e.select("user_id", "b", (F.col("e") / F.sum("e").over(own)).alias("p"))


class RoleBlock:
    """Users in blocks of a community and a role, fitted on friendship and diffusion links together and without any text; the rates of links between
    blocks score a pair."""

    def __init__(self, communities: int = 6, roles: int = 2, steps: int = 10) -> None:
        self.communities, self.roles, self.steps = communities, roles, steps

    def fit(self, graph: SocialGraph, checkpoint) -> RoleBlock:
        users = graph.docs.select("user_id").union(graph.friends.select("src")).union(graph.friends.select("dst")).distinct()
        w = users.select("user_id", F.explode(F.sequence(F.lit(0), F.lit(self.communities * self.roles - 1))).alias("b")).withColumn("w", -F.ln(uniform(F.pmod(F.col("user_id"), F.lit(2147483647)) * 1009 + F.col("b"), 707)))
        q = checkpoint(w.select("user_id", "b", (F.col("w") / F.sum("w").over(W.partitionBy("user_id"))).alias("p")))
        links = [graph.friends.select("src", "dst"), graph.diffs.select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst"))]
        for step in range(self.steps):
            rates = [checkpoint(block_rates(q, e)) for e in links]
            fresh = role_step(q, links, rates)
            if step < self.steps // 2:
                fresh = fresh.join(q.withColumnRenamed("p", "p0"), ["user_id", "b"]).select("user_id", "b", ((F.col("p") + F.col("p0")) / 2).alias("p"))
            old, q = q, checkpoint(fresh)
            for x in (old, *rates):
                scratch.drop(x)
        self.block, (self.friend_rates, self.diff_rates) = q, (checkpoint(block_rates(q, e)) for e in links)
        self.member = q.groupBy("user_id", F.floor(F.col("b") / self.roles).cast("int").alias("c")).agg(F.sum("p").alias("p"))
        return self

    def scores(self, pairs: DataFrame, kind: str = "friend") -> DataFrame:
        """(src, dst, x)"""
        rates = self.friend_rates if kind == "friend" else self.diff_rates
        a = self.block.select(F.col("user_id").alias("src"), "b", F.col("p").alias("pa"))
        b = self.block.select(F.col("user_id").alias("dst"), F.col("b").alias("b2"), F.col("p").alias("pb"))
        got = pairs.join(a, "src").join(F.broadcast(rates), "b").join(b, ["dst", "b2"]).groupBy("src", "dst").agg(F.sum(F.col("pa") * F.col("pb") * F.col("rate")).alias("x"))
        return pairs.select("src", "dst").join(got, ["src", "dst"], "left").fillna(0.0, ["x"])


# Strength blocks


def strengths(diffs: DataFrame, assign: DataFrame) -> DataFrame:
    """(c, c2, z, strength): the share of a topic's diffusion links that run between two communities."""
    src = assign.select(F.col("doc_id").alias("src_doc"), "c", "z")
    dst = assign.select(F.col("doc_id").alias("dst_doc"), F.col("c").alias("c2"))
    n = diffs.join(src, "src_doc").join(dst, "dst_doc").groupBy("c", "c2", "z").agg(F.count("*").alias("n"))
    return n.select("c", "c2", "z", (F.col("n") / F.sum("n").over(W.partitionBy("z"))).alias("strength"))


#: What each method uses and does; fixed facts of the methods.
CAPABILITIES = [
    # method, text, friendship, diffusion links, individual, topic, community factor, detection, friendship task, diffusion task, ranking
    ("TopicLink", 1, 0, 1, 0, 1, 0, 1, 1, 1, 0),
    ("UserFeatureLink", 1, 1, 1, 1, 0, 0, 0, 0, 1, 0),
    ("RoleBlock", 0, 1, 1, 1, 0, 1, 1, 1, 1, 0),
    ("StrengthBlock", 1, 0, 1, 0, 0, 1, 1, 1, 1, 1),
    ("JointProfiler", 1, 1, 1, 1, 1, 1, 1, 1, 1, 1),
]


CAPABILITY_COLUMNS = ["text", "friendship", "diffusion", "individual_factor", "topic_factor", "community_factor", "detection", "friendship_task", "diffusion_task", "ranking_task"]


def capabilities(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(CAPABILITIES, "method string, " + ", ".join(f"{n} int" for n in CAPABILITY_COLUMNS))
