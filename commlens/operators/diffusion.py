"""Diffusion prediction: how likely a user diffuses a document, averaged over the document's topics.

A document's topics are one array, a user's memberships one map and a link one row: rows are exchanged by document or user, never by link and topic.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from commlens.functions.expressions import sigmoid
from commlens.operators import factors, sampling


def topic_posterior(tokens: DataFrame, phi: DataFrame, n_topics: int, mix: DataFrame | None = None) -> DataFrame:
    """(doc_id, w ARRAY): shares of the topics of a document from its words, and from its owner's mixture (user_id, z, w) where given. Topics that no word
    or mixture speaks of have a share of zero; documents without any other topic have no row."""

    def logs(rows: DataFrame, key: str, value: str, name: str) -> DataFrame:
        cells = rows.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct(F.col("z").cast("int"), F.ln(value)))).alias("m"))
        return cells.select(key, F.transform(F.sequence(F.lit(0), F.lit(n_topics - 1)), lambda z: F.try_element_at(F.col("m"), z)).alias(name))

    words = logs(phi, "word", "p", "l")
    words = F.broadcast(words) if phi.count() <= factors.TENSOR_CELLS else words
    keys = ["doc_id"] if mix is None else ["doc_id", "user_id"]
    fit = tokens.select(*keys, "word", "cnt").join(words, "word").groupBy(*keys).agg(*(F.sum(F.col("cnt") * F.col("l")[z]).alias(f"l{z}") for z in range(n_topics)))
    fit = fit.select(*keys, F.array(*(f"l{z}" for z in range(n_topics))).alias("l"))
    if mix is not None:
        fit = fit.join(logs(mix, "user_id", "w", "own"), "user_id").withColumn("l", F.zip_with("l", "own", lambda a, b: a + b))
    fit = fit.withColumn("top", F.array_max("l")).where("top is not null")
    e = fit.select("doc_id", F.transform("l", lambda x: F.coalesce(F.exp(x - F.col("top")), F.lit(0.0))).alias("e"))
    return e.select("doc_id", F.transform("e", lambda x: x / F.aggregate("e", F.lit(0.0), lambda a, b: a + b)).alias("w"))


def score_pairs(
    pairs: DataFrame, topics: DataFrame, pi: DataFrame, tensor: DataFrame, pop: DataFrame, features: DataFrame, nu: tuple[float, ...], n_topics: int,
    active: tuple[str, ...] = ("community", "topic", "individual"), keep: tuple[str, ...] = (), communities: int | None = None,
) -> DataFrame:
    """(src_user, src_doc, dst_doc, keep, p) for pairs (src_user, src_doc, dst_doc, dst_user, tbin, keep): the three-factor probability at each topic, weighted by
    the ``topic_posterior`` of the document that would be diffused. A tensor of too many cells to send is joined instead."""
    if communities is None:
        communities = (tensor.agg(F.max(F.greatest("c", "c2"))).first()[0] or 0) + 1
    if n_topics * communities**2 > factors.TENSOR_CELLS or "topic" in active and pop.count() > factors.TENSOR_CELLS:
        return wide_score_pairs(pairs, topics, pi, tensor, pop, features, nu, active, keep)
    popular = {(r.z, r.tbin): r.pop for r in pop.select("z", "tbin", "pop").collect()} if "topic" in active else {}
    times = sorted({t for _, t in popular})
    q = np.zeros((n_topics, len(times) + 1))
    for (z, t), value in popular.items():
        q[z, times.index(t)] = value
    g = sampling.sent(tensor, (n_topics, communities, communities), ["z", "c", "c2"], "g") if "community" in active else np.zeros((n_topics, communities, communities))
    sent = pairs.sparkSession.sparkContext.broadcast((g, q, np.array(times, dtype=np.int64)))
    member = pi.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("c").cast("int"), F.col("p").cast("double")))).alias("m"))
    users = features.select("user_id", "popularity", "activeness").join(member, "user_id", "full_outer")
    ids = ["src_user", "src_doc", "dst_doc", *keep]
    rows = pairs.select(*ids, "dst_user", "tbin")
    for end in ("src", "dst"):
        side = users.select(F.col("user_id").alias(f"{end}_user"), F.col("m").alias(f"m_{end[0]}"), F.col("popularity").alias(f"{end[0]}_popularity"), F.col("activeness").alias(f"{end[0]}_activeness"))
        rows = rows.join(side, f"{end}_user", "left")
    own = factors.individual_score(nu) if "individual" in active else F.lit(0.0)
    none = F.expr("cast(map() as map<int,double>)")
    rows = rows.select(*ids, F.coalesce(F.col("tbin").cast("bigint"), F.lit(-(1 << 62))).alias("tbin"), own.alias("own"), F.coalesce("m_s", none).alias("m_s"), F.coalesce("m_d", none).alias("m_d"))
    rows = rows.join(topics.withColumnRenamed("doc_id", "dst_doc"), "dst_doc").select(*ids, "tbin", "own", "m_s", "m_d", "w")

    def members(column: pa.Array, n: int) -> np.ndarray:
        out, at = np.zeros((n, communities)), column.offsets.to_numpy()
        stop = slice(at[0], at[-1])
        row, c, p = np.repeat(np.arange(n), np.diff(at)), column.keys.to_numpy()[stop], column.items.to_numpy()[stop]
        known = c < communities
        out[row[known], c[known]] = p[known]
        return out

    def some(batch: pa.RecordBatch) -> pa.RecordBatch:
        n = batch.num_rows
        t, q, times = sent.value
        a, b = members(batch.column("m_s"), n), members(batch.column("m_d"), n)
        tbin = batch.column("tbin").to_numpy()
        at = np.searchsorted(times, tbin)
        at = np.where(np.isin(tbin, times), at, len(times))
        w = batch.column("w").flatten().to_numpy().reshape(n, n_topics)
        p, own = np.zeros(n), batch.column("own").to_numpy()
        for z in range(n_topics):
            p += w[:, z] / (1 + np.exp(-(np.einsum("ec,ec->e", a @ t[z], b) + q[z, at] + own)))
        return pa.RecordBatch.from_arrays([*(batch.column(c) for c in ids), pa.array(p)], [*ids, "p"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 2048):
                yield some(batch.slice(i, 2048))

    return rows.mapInArrow(run, T.StructType([*(pairs.schema[c] for c in ids), T.StructField("p", T.DoubleType())]))


def wide_score_pairs(pairs: DataFrame, topics: DataFrame, pi: DataFrame, tensor: DataFrame, pop: DataFrame, features: DataFrame, nu: tuple[float, ...], active: tuple[str, ...], keep: tuple[str, ...] = ()) -> DataFrame:
    """The same by joins, a row a link and topic, for a tensor of too many cells to send."""
    ids = ["src_user", "src_doc", "dst_doc", *keep]
    each = topics.select(F.col("doc_id").alias("dst_doc"), F.posexplode("w").alias("z", "w")).where("w > 0")
    at = pairs.join(each, "dst_doc").withColumn("link", F.struct(*ids, "dst_user", "tbin", "z"))
    scored = factors.diffusion_scores(at, pi, tensor, pop, features, nu, active, ("link", "w"))
    p = scored.groupBy(*(F.col(f"link.{c}").alias(c) for c in ids), F.col("link.dst_user").alias("dst_user"), F.col("link.tbin").alias("tbin"))
    return p.agg(F.sum(F.col("w") * sigmoid(F.col("y"))).alias("p")).select(*ids, "p")
