"""Scores of candidate topics and communities of every document, and draws from them.

Counters are frozen for a step; a document's own contribution is taken out of them. A document's scores are one array, an entry a candidate:
rows are exchanged by document, user or word, never by document and candidate. Tables that every task needs (the diffusion tensor,
popularity, communities by topics) are sent while their cells are under TENSOR_CELLS; beyond, terms of links are made by joins (``wide_*``).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens.functions.augmentation import KeyedRandom, pg_exact, pg_mean_of, pg_series
from commlens.functions.expressions import noise, uniform
from commlens.operators import counters, factors

#: Words of a document up to which its rising factorial is a sum of logs; longer ones take a difference of log-gammas.
_STEPS = 64
Augment = Callable[[DataFrame, str, str], DataFrame]


# Arrays


def dense(rows: DataFrame, keys: list[str], index: str, value: str, n: int, name: str) -> DataFrame:
    """(keys, name): the values of each key as an array of n, zero where there is no row."""
    cells = rows.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct(F.col(index).cast("int"), F.col(value).cast("double")))).alias("__m"))
    return cells.select(*keys, F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.coalesce(F.try_element_at(F.col("__m"), i), F.lit(0.0))).alias(name))


def spread(arrays: DataFrame, candidate: str, value: str = "score") -> DataFrame:
    """(doc_id, candidate, value) from (doc_id, value ARRAY)."""
    return arrays.select("doc_id", F.posexplode(value).alias(candidate, value))


def plus(scores: DataFrame, terms: DataFrame) -> DataFrame:
    """(doc_id, score): arrays of scores with the arrays ``term`` of the same documents added."""
    both = scores.join(terms.select("doc_id", "term"), "doc_id", "left")
    return both.select("doc_id", F.when(F.col("term").isNull(), F.col("score")).otherwise(F.zip_with("score", "term", lambda a, b: a + b)).alias("score"))


def summed(rows: DataFrame) -> DataFrame:
    """(doc_id, term): sums of the arrays ``term`` by document, summed within tasks first, so a document of many links is no list."""
    return rows.groupBy("doc_id").agg(Summarizer.sum(array_to_vector("term")).alias("v")).select("doc_id", vector_to_array("v").alias("term"))


def sent(rows: DataFrame, shape: tuple[int, ...], keys: list[str], value: str) -> np.ndarray:
    """A table of bounded cells as an array."""
    if int(np.prod(shape)) > factors.TENSOR_CELLS:
        raise ValueError(f"{shape} cells are more than the {factors.TENSOR_CELLS} that may be sent to every task")
    out = np.zeros(shape)
    for r in rows.select(*keys, value).collect():
        out[tuple(r[:-1])] = r[-1]
    return out


def _lists(column: pa.Array) -> tuple[np.ndarray, pa.Array]:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.offsets.to_numpy() - column.offsets[0].as_py(), column.flatten()


def _array_column(values: np.ndarray) -> pa.Array:
    offsets = np.arange(len(values) + 1, dtype=np.int32) * values.shape[1]
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.ascontiguousarray(values, dtype=float).ravel()))


# Topics


def topic_text_arrays(assign: DataFrame, tokens: DataFrame, docs: DataFrame, communities: int, topics: int, alpha: float, beta: float, n_words: int) -> DataFrame:
    """(doc_id, score): prior of each topic in the document's community and likelihood of its words, without the document itself.

    Words meet their counts as one row of all topics; tokens are exchanged once, by document. A frequent word of a vocabulary too large to send is
    split by the adaptive join."""
    from commlens.functions.udfs import _lgamma

    tw = counters.topic_word(assign, tokens)
    nz = sent(tw.groupBy("z").agg(F.sum("n").alias("n")), (topics,), ["z"], "n")
    ct = sent(counters.community_topic(assign), (communities, topics), ["c", "z"], "n")
    rows = dense(tw, ["word"], "z", "n", topics, "n")
    rows = F.broadcast(rows) if n_words * topics <= factors.TENSOR_CELLS else rows
    bags = tokens.select("doc_id", "word", "cnt").repartition("doc_id").join(rows, "word").groupBy("doc_id").agg(F.collect_list(F.struct(F.col("cnt").cast("int").alias("cnt"), "n")).alias("bag"))
    held = assign.select("doc_id", "c", "z").join(docs.select("doc_id", F.col("n_tok").cast("bigint").alias("n_tok")), "doc_id").join(bags, "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            c, z, n = (batch.column(x).to_numpy().astype(np.int64) for x in ("c", "z", "n_tok"))
            at, flat = _lists(batch.column("bag"))
            doc = np.repeat(np.arange(len(c)), np.diff(at))
            cnt = flat.field("cnt").to_numpy().astype(np.int64)
            near = flat.field("n").flatten().to_numpy(zero_copy_only=False).reshape(-1, topics).copy()
            near[np.arange(len(doc)), z[doc]] -= cnt
            fit = np.log1p(near / beta)
            for step in range(1, int(cnt.max(initial=1))):
                more = np.flatnonzero(cnt > step)
                fit[more] += np.log1p(near[more] / (beta + step))
            same = np.zeros((len(c), topics))
            same[np.arange(len(c)), z] = 1
            whole = nz - same * n[:, None] + n_words * beta
            score = np.log(ct[c] - same + alpha) + np.add.reduceat(fit, at[:-1])
            long = n > _STEPS
            for step in range(int(n[~long].max(initial=0))):
                more = np.flatnonzero((n > step) & ~long)
                score[more] -= np.log(whole[more] + step)
            score[long] -= _lgamma(whole[long] + n[long, None]) - _lgamma(whole[long])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), _array_column(score)], ["doc_id", "score"])

    return held.select("doc_id", "c", "z", "n_tok", "bag").mapInArrow(run, "doc_id bigint, score array<double>")


def topic_text_scores(assign: DataFrame, tokens: DataFrame, docs: DataFrame, communities: int, topics: int, alpha: float, beta: float, n_words: int) -> DataFrame:
    """(doc_id, z, score): ``topic_text_arrays``, a row a topic."""
    return spread(topic_text_arrays(assign, tokens, docs, communities, topics, alpha, beta, n_words), "z")


# Links


def link_rows(links: DataFrame, assign: DataFrame, pi: DataFrame, features: DataFrame, nu: tuple[float, ...], link_topic: str = "source") -> DataFrame:
    """Diffusion links with both users' memberships (pa, pb: arrays of c and p), both documents' communities and users' sizes, the link's topic and individual score."""
    member = pi.groupBy("user_id").agg(F.collect_list(F.struct(F.col("c").cast("int").alias("c"), "p")).alias("m"))
    sizes = assign.groupBy("user_id").agg(F.count("*").alias("n"))
    users = member.join(sizes, "user_id")
    ends = [assign.select(F.col("doc_id").alias(f"{d}_doc"), F.col("c").cast("int").alias(f"c_{x}"), F.col("z").cast("int").alias(f"z_{x}")) for d, x in (("src", "a"), ("dst", "b"))]
    both = links.select("src_doc", "dst_doc", "src_user", "dst_user", "tbin").join(ends[0], "src_doc").join(ends[1], "dst_doc")
    both = both.join(users.select(F.col("user_id").alias("src_user"), F.col("m").alias("m_a"), F.col("n").alias("n_a")), "src_user").join(users.select(F.col("user_id").alias("dst_user"), F.col("m").alias("m_b"), F.col("n").alias("n_b")), "dst_user")
    both = factors.with_features(both, features)
    z = F.col("z_a" if link_topic == "source" else "z_b").alias("z")
    return both.select("src_doc", "dst_doc", "tbin", z, "c_a", "c_b", "n_a", "n_b", "m_a", "m_b", factors.individual_score(nu).alias("own"))


def link_terms(rows: DataFrame, tensor: np.ndarray, pop: np.ndarray, active: tuple[str, ...], what: str, pg: str = "mean", salt: int = 0) -> DataFrame:
    """(doc_id, term ARRAY): for each end of each link, its log factor at every topic, or every community, of that end's document. The augmentation
    variable is that of the score in force: its mean, or a draw by the link and ``salt``."""
    topics, communities = tensor.shape[:2]
    g = rows.sparkSession.sparkContext.broadcast((tensor, pop))

    def members(column: pa.Array, n: int) -> np.ndarray:
        at, flat = _lists(column)
        out = np.zeros((n, communities))
        out[np.repeat(np.arange(n), np.diff(at)), flat.field("c").to_numpy()] = flat.field("p").to_numpy()
        return out

    def some(batch: pa.RecordBatch) -> pa.RecordBatch:
        n = batch.num_rows
        col = {x: batch.column(x).to_numpy(zero_copy_only=False) for x in ("src_doc", "dst_doc", "tbin", "z", "c_a", "c_b", "n_a", "n_b", "own")}
        a, b = members(batch.column("m_a"), n), members(batch.column("m_b"), n)
        t, q = g.value
        z, each = col["z"], np.arange(n)
        if what == "topic":
            y = np.zeros((n, topics))
            if "community" in active:
                for k in range(topics):
                    y[:, k] = np.einsum("ec,ec->e", a @ t[k], b)
            if "topic" in active:
                y += q[:, col["tbin"]].T
            if "individual" in active:
                y += col["own"][:, None]
            now = y[each, z]
        else:
            left, right = np.empty((n, communities)), np.empty((n, communities))
            for k in np.unique(z):
                at = z == k
                left[at], right[at] = b[at] @ t[k].T, a[at] @ t[k]
            now = np.einsum("ec,ec->e", a, left) if "community" in active else np.zeros(n)
            now = now + (q[z, col["tbin"]] if "topic" in active else 0.0) + (col["own"] if "individual" in active else 0.0)
        if pg == "mean":
            aug = pg_mean_of(now)
        else:
            keys = col["src_doc"].astype(np.int64) * np.int64(1_000_003) ^ col["dst_doc"].astype(np.int64)
            aug = (pg_exact if pg == "exact" else pg_series)(now, KeyedRandom(keys, salt))
        aug = aug[:, None]
        if what == "topic":
            one = two = (y - aug * y * y) / 2
        else:
            own = left - left[each, col["c_a"]][:, None], right - right[each, col["c_b"]][:, None]
            x, w = now[:, None] + own[0] / col["n_a"][:, None], now[:, None] + own[1] / col["n_b"][:, None]
            one, two = (x - aug * x * x) / 2, (w - aug * w * w) / 2
        ids = np.concatenate([col["src_doc"], col["dst_doc"]])
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), _array_column(np.concatenate([one, two]))], ["doc_id", "term"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 2048):
                yield some(batch.slice(i, 2048))

    return rows.mapInArrow(run, "doc_id bigint, term array<double>")


def topic_link_arrays(diffs: DataFrame, assign: DataFrame, pi: DataFrame, tensor: np.ndarray, pop: np.ndarray, features: DataFrame, nu: tuple[float, ...], active: tuple[str, ...], link_topic: str = "source", pg: str = "mean", salt: int = 0) -> DataFrame:
    """(doc_id, term): the diffusion terms of each end of a link, were its topic z."""
    return summed(link_terms(link_rows(diffs, assign, pi, features, nu, link_topic), tensor, pop, active, "topic", pg, salt))


def community_link_arrays(diffs: DataFrame, assign: DataFrame, pi: DataFrame, tensor: np.ndarray, pop: np.ndarray, features: DataFrame, nu: tuple[float, ...], active: tuple[str, ...], link_topic: str = "source", pg: str = "mean", salt: int = 0) -> DataFrame:
    """(doc_id, term): the diffusion terms of each end of a link at each community of its document, at the topic in force."""
    return summed(link_terms(link_rows(diffs, assign, pi, features, nu, link_topic), tensor, pop, active, "community", pg, salt))


def wide_topic_link_arrays(diffs: DataFrame, assign: DataFrame, pi: DataFrame, g: DataFrame, pop: DataFrame, features: DataFrame, nu: tuple[float, ...], topics: int, active: tuple[str, ...], augment: Augment, link_topic: str = "source") -> DataFrame:
    """The same by joins, for a tensor of too many cells to send."""
    now = augment(factors.diffusion_scores(factors.link_topics(diffs, assign, link_topic), pi, g, pop, features, nu, active), "y", "a").select("src_doc", "dst_doc", "a")
    links = diffs.select("*", F.explode(F.sequence(F.lit(0), F.lit(topics - 1))).alias("z")).withColumn("link", F.struct("src_doc", "dst_doc", "z"))
    scored = factors.diffusion_scores(links, pi, g, pop, features, nu, active, ("link",)).select("link.src_doc", "link.dst_doc", "link.z", "y")
    terms = scored.join(now, ["src_doc", "dst_doc"]).withColumn("t", factors.link_term(F.col("y"), F.col("a")))
    arrays = dense(terms, ["src_doc", "dst_doc"], "z", "t", topics, "term")
    return summed(arrays.select(F.explode(F.array("src_doc", "dst_doc")).alias("doc_id"), "term"))


def wide_community_link_arrays(scored: DataFrame, assign: DataFrame, pi: DataFrame, g: DataFrame, communities: int, augment: Augment) -> DataFrame:
    """The same by joins, from ``scored`` links (y at the topic in force)."""
    vectors = dense(factors.link_vectors(scored, pi, g), ["doc_id", "src_doc", "dst_doc"], "c", "g", communities, "g")
    ends = augment(scored, "y", "a").select("src_doc", "dst_doc", "y", "a").withColumn("doc_id", F.explode(F.array("src_doc", "dst_doc")))
    sizes = assign.groupBy("user_id").agg(F.count("*").alias("n"))
    base = ends.join(assign.join(sizes, "user_id").select("doc_id", "c", "n"), "doc_id").join(vectors, ["doc_id", "src_doc", "dst_doc"], "left")
    g = F.coalesce("g", F.array_repeat(F.lit(0.0), communities))
    return summed(base.select("doc_id", F.transform(g, lambda x: factors.link_term(F.col("y") + (x - F.element_at(g, F.col("c") + 1)) / F.col("n"), F.col("a"))).alias("term")))


# Communities


def community_text_arrays(assign: DataFrame, communities: int, topics: int, alpha: float, rho: float, use_text: bool = True) -> DataFrame:
    """(doc_id, score): the user's and, with ``use_text``, the topic's weight of each community, without the document itself."""
    ct = counters.community_topic(assign)
    mine = dense(counters.user_community(assign), ["user_id"], "c", "n", communities, "mine")
    base = assign.select("doc_id", "user_id", "z", "c").join(mine, "user_id")
    same = lambda c: F.when(c == F.col("c"), 1.0).otherwise(0.0)
    if not use_text:
        return base.select("doc_id", F.transform("mine", lambda n, c: F.ln(n - same(c) + rho)).alias("score"))
    nc = dense(ct.groupBy("c").agg(F.sum("n").alias("n")).withColumn("k", F.lit(0)), ["k"], "c", "n", communities, "nc").select("nc")
    base = base.join(F.broadcast(dense(ct, ["z"], "c", "n", communities, "ncz")), "z").crossJoin(F.broadcast(nc))
    every = F.arrays_zip("mine", "ncz", "nc")
    score = F.transform(every, lambda x, c: F.ln(x["mine"] - same(c) + rho) + F.ln(x["ncz"] - same(c) + alpha) - F.ln(x["nc"] - same(c) + topics * alpha))
    return base.select("doc_id", score.alias("score"))


def community_text_scores(assign: DataFrame, communities: int, topics: int, alpha: float, rho: float) -> DataFrame:
    """(doc_id, c, score): ``community_text_arrays``, a row a community."""
    return spread(community_text_arrays(assign, communities, topics, alpha, rho), "c")


def community_friend_arrays(assign: DataFrame, friends: DataFrame, pi: DataFrame, communities: int, augment: Augment = factors.augmentation_means) -> DataFrame:
    """(doc_id, term): the friendship terms of all of a user's links as a quadratic form in the candidate, up to a constant of the document."""
    s1, q = factors.friend_statistics(friends, pi, augment)
    qp = q.join(pi.select("user_id", F.col("c").alias("c2"), "p"), ["user_id", "c2"]).groupBy("user_id", "c").agg(F.sum(F.col("q") * F.col("p")).alias("qp"))
    diag = q.where("c = c2").select("user_id", "c", F.col("q").alias("qcc"))
    users = assign.groupBy("user_id").agg(F.count("*").cast("double").alias("n"))
    for rows, value in ((s1, "s1"), (qp, "qp"), (diag, "qcc")):
        users = users.join(dense(rows, ["user_id"], "c", value, communities, value), "user_id", "left")
    zero = F.array_repeat(F.lit(0.0), communities)
    row = dense(q, ["user_id", "c2"], "c", "q", communities, "row").withColumnRenamed("c2", "c")
    base = assign.select("doc_id", "user_id", "c").join(users, "user_id").join(row, ["user_id", "c"], "left")
    every = F.arrays_zip(*(F.coalesce(F.col(x), zero).alias(x) for x in ("s1", "qp", "qcc", "row")))
    n = F.col("n")
    return base.select("doc_id", F.transform(every, lambda x: x["s1"] / (2 * n) - (x["qp"] / n - x["row"] / (n * n) + x["qcc"] / (2 * n * n))).alias("term"))


def community_friend_scores(assign: DataFrame, friends: DataFrame, pi: DataFrame, communities: int) -> DataFrame:
    """(doc_id, c, term): ``community_friend_arrays``, a row a community."""
    return spread(community_friend_arrays(assign, friends, pi, communities), "c", "term")


# Draws


def draw_arrays(scores: DataFrame, candidate: str, how: str = "gumbel", salt: int = 0) -> DataFrame:
    """(doc_id, candidate): one draw per document from an array of unnormalised log scores; the rules and noise of ``draw``."""
    if how == "inverse":
        weights = scores.select("doc_id", F.transform("score", lambda s: F.exp(s - F.array_max("score"))).alias("w"))
        total = lambda w: F.aggregate(w, F.lit(0.0), lambda a, x: a + x)
        limit = noise(salt, F.col("doc_id")) * total(F.col("w"))
        return weights.select("doc_id", F.size(F.filter(F.transform("w", lambda _, i: total(F.slice("w", 1, i + 1))), lambda upto: upto < limit)).alias(candidate))
    more = (lambda i: -F.ln(-F.ln(noise(salt, F.col("doc_id"), i)))) if how == "gumbel" else (lambda i: F.lit(0.0))
    best = F.array_max(F.transform("score", lambda s, i: F.struct((F.round(s, 9) + more(i)).alias("v"), (-i).alias("i"))))
    return scores.select("doc_id", (-best["i"]).cast("int").alias(candidate))


def draw(scores: DataFrame, candidate: str, how: str = "gumbel", salt: int = 0, portable: bool = False) -> DataFrame:
    """(doc_id, candidate): one draw per document from unnormalised log scores, a row a candidate.

    ``gumbel`` adds noise and takes the largest in one hash aggregation; ``inverse`` walks the cumulative weights to a uniform; ``argmax`` takes the
    largest, the lower candidate on ties. Noise depends on document, candidate and salt alone; ``portable`` noise can be repeated by other engines."""
    one = uniform(F.col("doc_id"), 303 + salt) if portable else noise(salt, F.col("doc_id"))
    each = uniform(F.col("doc_id") * 1009 + F.col(candidate), 404 + salt) if portable else noise(salt, F.col("doc_id"), F.col(candidate))
    if how == "inverse":
        own = W.partitionBy("doc_id")
        weight = F.exp(F.col("score") - F.max("score").over(own))
        w = scores.select("doc_id", candidate, weight.alias("w"))
        order = own.orderBy(candidate)
        run = w.select("doc_id", candidate, F.sum("w").over(order.rowsBetween(W.unboundedPreceding, 0)).alias("upto"), F.sum("w").over(own).alias("all"))
        return run.where(F.col("upto") >= one * F.col("all")).groupBy("doc_id").agg(F.min(candidate).alias(candidate))
    value: Column = F.round("score", 9)
    if how == "gumbel":
        value = value - F.ln(-F.ln(each))
    return scores.groupBy("doc_id").agg(F.max_by(F.struct(candidate), F.struct(value, -F.col(candidate)))[candidate].alias(candidate))
