"""Graphs drawn from the model itself, with the truth kept: the generative steps over ranges of ids, with hashed uniforms and Dirichlet draws.

Parameters are small (topics, communities) and drawn on the driver from a seed; users, documents, words and links are drawn in parallel, each from
its own ids, so that a partition made again is the same.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from commlens.functions.expressions import noise
from commlens.sources.graphs import SocialGraph


@dataclass(frozen=True)
class PlantedConfig:
    users: int = 200
    docs_per_user: int = 10
    words_per_doc: int = 8
    vocabulary: int = 60
    communities: int = 4
    topics: int = 5
    friends_per_user: int = 20
    diffs_per_doc: float = 1.0
    membership: float = 0.05
    interest: float = 0.1
    words: float = 0.05
    loyalty: float = 0.9
    stars: float = 0.0
    trends: float = 0.0
    bins: int = 10
    seed: int = 3


@dataclass
class Planted:
    graph: SocialGraph
    truth: DataFrame
    users: DataFrame
    eta: np.ndarray


def _pick(p: np.ndarray, u: Column, row: Column) -> Column:
    """The column of a row of ``p`` that a uniform falls in, by its cumulative sums."""
    upto = F.array(*(F.array(*(F.lit(float(x)) for x in np.minimum(1.0, np.cumsum(r)))) for r in p))
    return F.least(F.size(F.filter(F.element_at(upto, row + 1), lambda x: x < u)), F.lit(p.shape[1] - 1)).cast("int")


def generate(spark: SparkSession, cfg: PlantedConfig = PlantedConfig()) -> Planted:
    """A graph, (doc_id, user_id, c, z) truth of documents, (user_id, c) main communities, and the diffusion profile.

    A document diffuses documents of the community that its community follows on its topic: with ``loyalty`` the target is drawn there, else anywhere. A friend
    comes from the same main community with that chance, else from anywhere. ``stars``: the chance that a target anywhere is one of a tenth of the users, whom others
    befriend and diffuse more, and, for the other half of the users, that a document diffuses nothing. ``trends``: the chance that a document's bin is its topic's own."""
    rng = np.random.default_rng(cfg.seed)
    theta = rng.dirichlet(np.full(cfg.topics, cfg.interest), cfg.communities)
    phi = rng.dirichlet(np.full(cfg.vocabulary, cfg.words), cfg.topics)
    follows = rng.integers(0, cfg.communities, (cfg.communities, cfg.topics))
    eta = np.zeros((cfg.communities, cfg.communities, cfg.topics))
    for c in range(cfg.communities):
        for z in range(cfg.topics):
            eta[c, follows[c, z], z] = theta[c, z]
    pi = rng.dirichlet(np.full(cfg.communities, cfg.membership), cfg.users)
    main = pi.argmax(axis=1)

    users = spark.createDataFrame([(i, int(main[i]), [float(x) for x in np.minimum(1, np.cumsum(pi[i]))]) for i in range(cfg.users)], "user_id bigint, c int, upto array<double>")
    ids = spark.range(cfg.users * cfg.docs_per_user).select(F.col("id").alias("doc_id"), F.floor(F.col("id") / cfg.docs_per_user).cast("bigint").alias("user_id"))
    u = lambda k, *cols: noise(cfg.seed * 1000 + k, *cols)
    docs = ids.join(F.broadcast(users.select("user_id", "upto")), "user_id")
    docs = docs.withColumn("c", F.least(F.size(F.filter("upto", lambda x: x < u(1, F.col("doc_id")))), F.lit(cfg.communities - 1)).cast("int"))
    docs = docs.withColumn("z", _pick(theta, u(2, F.col("doc_id")), F.col("c")))
    spread = F.when(u(12, F.col("doc_id")) < cfg.trends, F.pmod(F.col("z") * 3 + F.floor(u(13, F.col("doc_id")) * 2), F.lit(cfg.bins))).otherwise(F.floor(u(3, F.col("doc_id")) * cfg.bins))
    docs = docs.withColumn("tbin", spread.cast("int"))
    truth = docs.select("doc_id", "user_id", "c", "z", "tbin").persist()

    words = truth.select("doc_id", "user_id", "z", F.explode(F.sequence(F.lit(1), F.lit(cfg.words_per_doc))).alias("k"))
    words = words.withColumn("word", F.format_string("w%03d", _pick(phi, u(4, F.col("doc_id"), F.col("k")), F.col("z"))))
    tokens = words.groupBy("doc_id", "user_id", "word").agg(F.count("*").alias("cnt"))

    places = users.select("user_id", "c").persist()
    members = {r["c"]: r["n"] for r in places.groupBy("c").agg(F.count("*").alias("n")).collect()}
    size = F.element_at(F.create_map(*(F.lit(x) for kv in members.items() for x in kv)), F.col("c"))
    numbered = places.selectExpr("c AS tc", "row_number() OVER (PARTITION BY c ORDER BY user_id) - 1 AS i", "user_id AS dst")
    tries = places.select(F.col("user_id").alias("src"), "c", F.explode(F.sequence(F.lit(1), F.lit(cfg.friends_per_user // 2))).alias("k"))
    near = tries.where(u(5, F.col("src"), F.col("k")) < cfg.loyalty).withColumn("i", F.floor(u(6, F.col("src"), F.col("k")) * size).cast("int"))
    near = near.join(F.broadcast(numbered), (F.col("c") == F.col("tc")) & (near["i"] == numbered["i"])).select("src", "dst")
    star = lambda v, key: F.when(u(14, *key) < cfg.stars, F.floor(v / 10) * 10).otherwise(v).cast("bigint")
    far = tries.where(u(5, F.col("src"), F.col("k")) >= cfg.loyalty).select("src", star(F.floor(u(7, F.col("src"), F.col("k")) * cfg.users), (F.col("src"), F.col("k"))).alias("dst"))
    friends = near.union(far).where("src <> dst").distinct()

    target = F.element_at(F.array(*(F.array(*(F.lit(int(x)) for x in row)) for row in follows)), F.col("c") + 1)
    quiet = (u(15, F.col("user_id")) < 0.5) & (u(16, F.col("doc_id")) < cfg.stars)
    links = truth.where((u(8, F.col("doc_id")) < cfg.diffs_per_doc) & ~quiet).select(F.col("doc_id").alias("src_doc"), F.col("user_id").alias("src_user"), "tbin", "z", F.element_at(target, F.col("z") + 1).alias("tc"))
    pool = truth.selectExpr("c AS tc", "z", "doc_id AS dst_doc", "user_id AS dst_user", "row_number() OVER (PARTITION BY c, z ORDER BY doc_id) - 1 AS i", "count(*) OVER (PARTITION BY c, z) AS n")
    sizes = pool.select("tc", "z", "n").distinct()
    aimed = links.where(u(9, F.col("src_doc")) < cfg.loyalty).join(F.broadcast(sizes), ["tc", "z"]).withColumn("i", F.floor(u(10, F.col("src_doc")) * F.col("n")).cast("int")).drop("n")
    aimed = aimed.join(pool.drop("n"), ["tc", "z", "i"])
    loose = links.where(u(9, F.col("src_doc")) >= cfg.loyalty).withColumn("dst_user", star(F.floor(u(11, F.col("src_doc")) * cfg.users), (F.col("src_doc"),)))
    loose = loose.withColumn("dst_doc", (F.col("dst_user") * cfg.docs_per_user + F.floor(u(17, F.col("src_doc")) * cfg.docs_per_user)).cast("bigint"))
    cols = ["src_doc", "dst_doc", "src_user", "dst_user", "tbin"]
    diffs = aimed.select(*cols).union(loose.select(*cols)).where("src_user <> dst_user").distinct()
    docs = truth.select("doc_id", "user_id", F.timestamp_seconds(F.col("tbin") * 86400).alias("ts"), "tbin", F.lit(cfg.words_per_doc).cast("bigint").alias("n_tok"))
    return Planted(SocialGraph(docs, tokens, friends, diffs), truth.select("doc_id", "user_id", "c", "z"), places, eta)
