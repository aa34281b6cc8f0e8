"""Probabilities of links, and the statistics that let a sweep score all candidates of a document at once.

Memberships stay sparse: a user has at most as many communities as documents. The tensor over (z, c, c2) is sent to every
task while it has TENSOR_CELLS cells or fewer, and joined by topic beyond.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from commlens.functions.expressions import log_psi, pg_mean, sigmoid

TENSOR_CELLS = 4_000_000


def friend_scores(friends: DataFrame, pi: DataFrame) -> DataFrame:
    """(src, dst, x): inner product of both memberships; zero where nothing is shared."""
    left = pi.select(F.col("user_id").alias("src"), "c", F.col("p").alias("pa"))
    right = pi.select(F.col("user_id").alias("dst"), "c", F.col("p").alias("pb"))
    shared = friends.join(left, "src").join(right, ["dst", "c"]).groupBy("src", "dst").agg(F.sum(F.col("pa") * F.col("pb")).alias("x"))
    return friends.join(shared, ["src", "dst"], "left").select("src", "dst", F.coalesce("x", F.lit(0.0)).alias("x"))


def friend_probabilities(friends: DataFrame, pi: DataFrame) -> DataFrame:
    return friend_scores(friends, pi).select("src", "dst", sigmoid(F.col("x")).alias("p"))


def tensor(theta: DataFrame, eta: DataFrame) -> DataFrame:
    """(z, c, c2, g): the diffusion profile weighted by both communities' interest in the topic."""
    a = theta.select("c", "z", F.col("p").alias("ta"))
    b = theta.select(F.col("c").alias("c2"), "z", F.col("p").alias("tb"))
    return eta.join(a, ["c", "z"]).join(b, ["c2", "z"]).select("z", "c", "c2", (F.col("p") * F.col("ta") * F.col("tb")).alias("g"))


def _sent(g: DataFrame, cells: int | None) -> DataFrame:
    return F.broadcast(g) if cells is not None and cells <= TENSOR_CELLS else g


def link_topics(diffs: DataFrame, assign: DataFrame, which: str = "source") -> DataFrame:
    """Diffusion links with the topic ``z`` that they carry."""
    side = "src_doc" if which == "source" else "dst_doc"
    return diffs.join(assign.select(F.col("doc_id").alias(side), "z"), side)


def community_factor(links: DataFrame, pi: DataFrame, g: DataFrame, keys: list[str], cells: int | None = None) -> DataFrame:
    """(keys, y): sum over both users' communities of the tensor at the link's topic; links have src_user, dst_user, z."""
    a = pi.select(F.col("user_id").alias("src_user"), "c", F.col("p").alias("pa"))
    b = pi.select(F.col("user_id").alias("dst_user"), F.col("c").alias("c2"), F.col("p").alias("pb"))
    half = links.select(*keys, "src_user", "dst_user", "z").join(a, "src_user").join(_sent(g, cells), ["z", "c"])
    half = half.groupBy(*keys, "dst_user", "c2").agg(F.sum(F.col("pa") * F.col("g")).alias("h"))
    return half.join(b, ["dst_user", "c2"]).groupBy(*keys).agg(F.sum(F.col("h") * F.col("pb")).alias("y"))


def individual_score(nu: tuple[float, ...], src: str = "s", dst: str = "d") -> Column:
    parts = [f"{src}_popularity", f"{src}_activeness", f"{dst}_popularity", f"{dst}_activeness"]
    return sum((F.lit(w) * F.coalesce(F.col(c), F.lit(0.0)) for w, c in zip(nu, parts, strict=True)), F.lit(0.0))


def with_features(links: DataFrame, features: DataFrame) -> DataFrame:
    s, d = (features.select(F.col("user_id").alias(f"{x}_user"), F.col("popularity").alias(f"{x[0]}_popularity"), F.col("activeness").alias(f"{x[0]}_activeness")) for x in ("src", "dst"))
    return links.join(s, "src_user", "left").join(d, "dst_user", "left")


def diffusion_scores(
    links: DataFrame, pi: DataFrame, g: DataFrame, pop: DataFrame, features: DataFrame, nu: tuple[float, ...],
    factors: tuple[str, ...] = ("community", "topic", "individual"), keys: tuple[str, ...] = ("src_doc", "dst_doc"), cells: int | None = None,
) -> DataFrame:
    """(keys, z, tbin, src_user, dst_user, y): the sum of the chosen factors for links with a topic."""
    out = links.select(*keys, "src_user", "dst_user", "tbin", "z")
    y = F.lit(0.0)
    if "community" in factors:
        out = out.join(community_factor(links, pi, g, list(keys), cells).withColumnRenamed("y", "y_comm"), list(keys), "left")
        y = y + F.coalesce("y_comm", F.lit(0.0))
    if "topic" in factors:
        out = out.join(pop, ["z", "tbin"], "left")
        y = y + F.coalesce("pop", F.lit(0.0))
    if "individual" in factors:
        out = with_features(out, features)
        y = y + individual_score(nu)
    return out.select(*keys, "z", "tbin", "src_user", "dst_user", y.alias("y"))


def similarity_scores(diffs: DataFrame, pi: DataFrame) -> DataFrame:
    """Diffusion links scored like friendship links: (src_doc, dst_doc, y)."""
    pairs = diffs.select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst")).distinct()
    return diffs.join(friend_scores(pairs, pi).select(F.col("src").alias("src_user"), F.col("dst").alias("dst_user"), F.col("x").alias("y")), ["src_user", "dst_user"]).select("src_doc", "dst_doc", "y")


def augmentation_means(scored: DataFrame, score: str, name: str) -> DataFrame:
    """The scored links with the mean of their augmentation variable."""
    return scored.withColumn(name, pg_mean(F.col(score)))


def friend_statistics(friends: DataFrame, pi: DataFrame, augment: Callable[[DataFrame, str, str], DataFrame] = augmentation_means) -> tuple[DataFrame, DataFrame]:
    """For each user, over the neighbours in either direction: (user_id, c, s1), the sum of memberships, and (user_id, c, c2, q), the
    augmented second moments. They replace a walk over all links for each document; hubs are sums, not lists. ``friends`` may have a
    column ``times``, how often a pair is linked; each such link has an augmentation variable of its own."""
    scored = friend_scores(friends, pi)
    if "times" in friends.columns:
        scored = scored.join(friends, ["src", "dst"]).select("src", "dst", "x", F.explode(F.sequence(F.lit(1), F.col("times").cast("int"))).alias("nth"))
    scored = augment(scored, "x", "lam")
    ends = scored.select(F.col("src").alias("user_id"), F.col("dst").alias("v"), "lam").union(scored.select(F.col("dst").alias("user_id"), F.col("src").alias("v"), "lam"))
    mine = pi.select(F.col("user_id").alias("v"), "c", "p")
    seen = ends.join(mine, "v")
    s1 = seen.groupBy("user_id", "c").agg(F.sum("p").alias("s1"))
    vectors = pi.groupBy("user_id").agg(F.collect_list(F.struct("c", "p")).alias("cells")).select(F.col("user_id").alias("v"), "cells")
    pairs = ends.join(vectors, "v").select("user_id", "lam", F.explode("cells").alias("a"), "cells").select("user_id", "lam", "a", F.explode("cells").alias("b"))
    q = pairs.groupBy("user_id", F.col("a.c").alias("c"), F.col("b.c").alias("c2")).agg(F.sum(F.col("lam") * F.col("a.p") * F.col("b.p")).alias("q"))
    return s1, q


def link_vectors(scored: DataFrame, pi: DataFrame, g: DataFrame, cells: int | None = None) -> DataFrame:
    """(doc_id, src_doc, dst_doc, c, g): for each end of a diffusion link, the community factor if the end's user were wholly in c."""
    a = pi.select(F.col("user_id").alias("dst_user"), F.col("c").alias("c2"), F.col("p").alias("pv"))
    out = scored.join(a, "dst_user").join(_sent(g, cells), ["z", "c2"]).groupBy(F.col("src_doc").alias("doc_id"), "src_doc", "dst_doc", "c").agg(F.sum(F.col("g") * F.col("pv")).alias("g"))
    b = pi.select(F.col("user_id").alias("src_user"), "c", F.col("p").alias("pu"))
    back = scored.join(b, "src_user").join(_sent(g, cells), ["z", "c"]).groupBy(F.col("dst_doc").alias("doc_id"), "src_doc", "dst_doc", F.col("c2").alias("cc")).agg(F.sum(F.col("g") * F.col("pu")).alias("g"))
    return out.union(back.withColumnRenamed("cc", "c"))


def link_term(y: Column, a: Column) -> Column:
    return log_psi(y, a)
