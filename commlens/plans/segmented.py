"""The segmented schedule: segments of users are sampled side by side, and one document after another inside, on counters that are current within a segment.

Topics of documents come from a mixture over all documents (``baselines.topic_mixtures``); a user goes, with all documents and links, to the segment of
its most frequent topic; segments are packed on workers by load. A segment is cut into chunks of whole users by hash, of about ``chunk_docs`` documents, so that no
task holds more than a chunk; a chunk starts from the counters at the sweep's start and its changes meet the others' in the next count. With one chunk this is the
serial sampler.

A chunk gets the counts of the words it holds and no others. Friendship enters through each user's first and second moments of its neighbours, diffusion links as
lists of their ends with the other users' memberships, both as they were at the sweep's start with their augmentation variables. Documents of more than HUB_ENDS
link ends get, instead of a list, their terms at the assignment in force as two arrays, made by a distributed sum.
"""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens import scratch
from commlens.config import ProfilerConfig
from commlens.operators import counters, factors, partition, sampling
from commlens.plans.kernel import Ends, Kernel, State
from commlens.plans.profiler import JointProfiler, negative_links
from commlens.sources.graphs import SocialGraph

HUB_ENDS = 10_000


def segments_of(graph: SocialGraph, topics: int, checkpoint: Callable[[DataFrame], DataFrame], steps: int = 5) -> DataFrame:
    """(user_id, seg): by the likeliest topics of a mixture over all users' documents."""
    from commlens.plans.baselines import topic_mixtures

    soft, _, _ = topic_mixtures(graph, topics, steps, checkpoint)
    hard = soft.groupBy("doc_id", "user_id").agg(F.max_by("z", F.struct(F.round("p", 9), -F.col("z"))).alias("z"))
    return checkpoint(partition.segment_users(hard))


def _ends(graph: SocialGraph, assign: DataFrame, pi: DataFrame, parts: tuple, features: DataFrame, nu: tuple[float, ...], cfg: ProfilerConfig, augment: Callable) -> DataFrame:
    """(doc_id, other, source, tbin, own, aug, topic, src, m): both ends of every diffusion link, with its source and topic and the other user's memberships."""
    scored = augment(factors.diffusion_scores(factors.link_topics(graph.diffs, assign, cfg.link_topic), *parts, features, nu, cfg.factors, cells=cfg.communities**2 * cfg.topics), "y", "aug")
    rows = factors.with_features(scored.select("src_doc", "dst_doc", "src_user", "dst_user", "tbin", "z", "aug"), features)
    rows = rows.select("src_doc", "dst_doc", "src_user", "dst_user", "tbin", F.col("z").cast("int").alias("topic"), "aug", factors.individual_score(nu).alias("own"))
    member = pi.groupBy("user_id").agg(F.collect_list(F.struct(F.col("c").cast("int").alias("c"), "p")).alias("m")).withColumnRenamed("user_id", "other")
    out = rows.select(F.col("src_doc").alias("doc_id"), F.col("dst_user").alias("other"), F.lit(True).alias("source"), "tbin", "own", "aug", "topic", F.col("src_doc").alias("src"))
    back = rows.select(F.col("dst_doc").alias("doc_id"), F.col("src_user").alias("other"), F.lit(False).alias("source"), "tbin", "own", "aug", "topic", F.col("src_doc").alias("src"))
    return out.union(back).join(member, "other")


def sweep(graph: SocialGraph, assign: DataFrame, cfg: ProfilerConfig, number: int, segments: DataFrame, features: DataFrame, nu: tuple[float, ...] = (0.0,) * 4, chunk_docs: int = 20_000, placed: DataFrame | None = None) -> DataFrame:
    """(doc_id, user_id, c, z, worker, seconds) after one sweep. ``placed`` (seg, worker) puts all chunks of a segment on one worker's partition."""
    C, Z = cfg.communities, cfg.topics  # noqa: N806
    model = JointProfiler(cfg)
    parts = model._links(graph, assign)
    flat = model._sent(graph, parts)
    if flat is None:
        raise ValueError("the diffusion tensor is too large for chunks; use the blocked schedule")
    augment = model._augment(10_007 * number)
    ct = sampling.sent(counters.community_topic(assign), (C, Z), ["c", "z"], "n")
    tw = counters.topic_word(assign, graph.tokens)
    nz = sampling.sent(tw.groupBy("z").agg(F.sum("n").alias("n")), (Z,), ["z"], "n")
    n_words = tw.select("word").distinct().count()
    frozen = graph.docs.sparkSession.sparkContext.broadcast((ct, nz, *flat))

    sizes = segments.join(graph.docs.groupBy("user_id").agg(F.count("*").alias("nd")), "user_id").groupBy("seg").agg(F.sum("nd").alias("nd"))
    chunks = segments.join(F.broadcast(sizes), "seg").select("user_id", "seg", F.pmod(F.xxhash64("user_id"), F.ceil(F.col("nd") / chunk_docs)).cast("int").alias("chunk"))
    chunks = chunks.join(F.broadcast(placed), "seg") if placed is not None else chunks.withColumn("worker", F.lit(None).cast("int"))
    bags = graph.tokens.groupBy("doc_id").agg(F.collect_list("word").alias("words"), F.collect_list(F.col("cnt").cast("int")).alias("cnts"))
    rows = assign.select("doc_id", "user_id", F.col("c").cast("int").alias("c"), F.col("z").cast("int").alias("z")).join(bags, "doc_id").join(chunks, "user_id")
    none = lambda name, kind: F.lit(None).cast(kind).alias(name)
    if cfg.use_friends:
        s1, q = factors.friend_statistics(graph.friends, parts[0], augment)
        flat_q = sampling.dense(q.select("user_id", (F.col("c") * C + F.col("c2")).alias("k"), "q"), ["user_id"], "k", "q", C * C, "q")
        rows = rows.join(sampling.dense(s1, ["user_id"], "c", "s1", C, "s1").join(flat_q, "user_id"), "user_id", "left")
    else:
        rows = rows.select("*", none("s1", "array<double>"), none("q", "array<double>"))
    if model._by_profile:
        ends = _ends(graph, assign, parts[0], parts, features, nu, cfg, augment)
        count = ends.groupBy("doc_id").agg(F.count("*").alias("n_ends"))
        hubs = scratch.written(count.where(F.col("n_ends") > HUB_ENDS).select("doc_id"))
        lists = ends.join(F.broadcast(hubs) if hubs.count() <= 1_000_000 else hubs, "doc_id", "left_anti").groupBy("doc_id").agg(F.collect_list(F.struct("other", "source", F.col("tbin").cast("int").alias("tbin"), "own", "aug", "topic", "src", "m")).alias("ends"))
        rows = rows.join(lists, "doc_id", "left")
        some = graph.diffs.join(hubs.withColumnRenamed("doc_id", "src_doc").withColumn("h", F.lit(1)), "src_doc", "left").join(hubs.withColumnRenamed("doc_id", "dst_doc").withColumn("k", F.lit(1)), "dst_doc", "left").where("h = 1 or k = 1").select(*graph.diffs.columns)
        args = (some, assign, parts[0], *flat, features, nu, cfg.factors, cfg.link_topic, cfg.pg, cfg.seed * 7919 + number)
        terms = sampling.topic_link_arrays(*args).withColumnRenamed("term", "t_topic").join(sampling.community_link_arrays(*args).withColumnRenamed("term", "t_comm"), "doc_id").join(hubs, "doc_id")
        rows = rows.join(terms, "doc_id", "left")
    else:
        rows = rows.select("*", none("ends", "array<struct<other:bigint,source:boolean,tbin:int,own:double,aug:double,topic:int,src:bigint,m:array<struct<c:int,p:double>>>>"), none("t_topic", "array<double>"), none("t_comm", "array<double>"))
    held = graph.tokens.select("user_id", "word").join(chunks, "user_id").select("seg", "chunk", "word").distinct()
    words = scratch.written(held.join(sampling.dense(tw, ["word"], "z", "n", Z, "n"), "word").select("seg", "chunk", "word", "n"))

    def run(docs: pd.DataFrame, counts: pd.DataFrame) -> pd.DataFrame:
        began = time.process_time()
        ct, nz, tensor, pop = frozen.value
        docs = docs.sort_values(["user_id", "doc_id"], kind="stable")
        index = {w: i for i, w in enumerate(counts["word"])}
        local = np.array(counts["n"].tolist(), dtype=float).reshape(-1, Z).T.copy()
        users, user = np.unique(docs["user_id"].to_numpy(), return_inverse=True)
        uc = np.zeros((len(users), C))
        np.add.at(uc, (user, docs["c"].to_numpy()), 1)
        place = {u: i for i, u in enumerate(users.tolist())}
        spot = {d: i for i, d in enumerate(docs["doc_id"].tolist())}
        pi = [*(uc / uc.sum(axis=1, keepdims=True))]
        state = State(local, nz.copy(), ct.copy(), uc, np.zeros((0, C)), tensor, pop, n_words)
        for i, (u, s1, q, ends, t_topic, t_comm) in enumerate(zip(user.tolist(), docs["s1"], docs["q"], docs["ends"], docs["t_topic"], docs["t_comm"], strict=True)):
            if s1 is not None and u not in state.moments:
                state.moments[u] = (np.asarray(s1), np.asarray(q).reshape(C, C))
            if t_topic is not None:
                state.terms[i] = (np.asarray(t_topic), np.asarray(t_comm))
            if ends is not None and len(ends):
                for e in ends:
                    if e["other"] not in place:
                        row = np.zeros(C)
                        for m in e["m"]:
                            row[m["c"]] = m["p"]
                        place[e["other"]] = len(pi)
                        pi.append(row)
                got = lambda k, kind: np.array([e[k] for e in ends], dtype=kind)  # noqa: B023, E731
                state.ends[i] = Ends(np.array([place[e["other"]] for e in ends]), got("source", bool), got("tbin", int), got("own", float), got("aug", float), got("topic", int), np.array([spot.get(e["src"], -1) for e in ends]))
        state.pi = np.array(pi)
        bags = [(np.array([index[w] for w in ws], dtype=int), np.asarray(ks, dtype=float)) for ws, ks in zip(docs["words"], docs["cnts"], strict=True)]
        kernel = Kernel(cfg, state, user, docs["c"].to_numpy(), docs["z"].to_numpy(), [w for w, _ in bags], [k for _, k in bags])
        kernel.sweep(np.random.default_rng([cfg.seed, number, int(docs["doc_id"].min())]))
        took = time.process_time() - began
        worker = docs["worker"].iloc[0]
        return pd.DataFrame({"doc_id": docs["doc_id"].to_numpy(), "user_id": docs["user_id"].to_numpy(), "c": kernel.c, "z": kernel.z, "worker": None if pd.isna(worker) else int(worker), "seconds": took / len(docs)})

    return rows.groupBy("seg", "chunk").cogroup(words.groupBy("seg", "chunk")).applyInPandas(run, "doc_id bigint, user_id bigint, c int, z int, worker int, seconds double")


def fit(graph: SocialGraph, cfg: ProfilerConfig, checkpoint: Callable[[DataFrame], DataFrame] | None = None, chunk_docs: int = 20_000, workers: int | None = None, unit: tuple[float, float, float] = (3.0, 1.0, 2.0)) -> tuple[DataFrame, tuple[float, ...], DataFrame]:
    """The assignment after ``cfg.sweeps`` sweeps, the weights of the individual factor, and (sweep, worker, load, seconds): estimated and actual load of each worker."""
    keep = checkpoint or scratch.written
    segments = segments_of(graph, cfg.topics, keep)
    load = keep(partition.segment_load(segments, graph, unit))
    placed = partition.placement(load, workers) if workers else None
    features = keep(counters.user_features(graph.docs, graph.friends, graph.diffs))
    learn = cfg.use_diffusion and "individual" in cfg.factors and cfg.diffusion_kind == "profile"
    negative = keep(negative_links(graph, cfg.seed)) if learn else None
    nu: tuple[float, ...] = (0.0, 0.0, 0.0, 0.0)
    assign = keep(counters.first_assignment(graph.docs, cfg.communities, cfg.topics, cfg.seed))
    spent = []
    for k in range(cfg.sweeps):
        done = keep(sweep(graph, assign, cfg, k, segments, features, nu, chunk_docs, placed))
        assign = done.select("doc_id", "user_id", "c", "z")
        if negative is not None:
            nu = JointProfiler(cfg, keep)._fit_nu(graph, assign, negative, features, nu)
        spent.append(done.groupBy("worker").agg(F.sum("seconds").alias("seconds")).withColumn("sweep", F.lit(k)))
    report = spent[0]
    for more in spent[1:]:
        report = report.unionByName(more)
    if placed is not None:
        report = report.join(partition.balance(load, placed).select("worker", "load"), "worker")
    else:
        report = report.withColumn("load", F.lit(None).cast("double"))
    return assign, nu, report.select("sweep", "worker", "load", "seconds")


def calibrated(graph: SocialGraph, cfg: ProfilerConfig, fractions: tuple[float, ...] = (0.4, 0.7, 1.0)) -> tuple[float, float, float]:
    """Seconds per document, friendship link and diffusion link, from serial sweeps over shares of a graph small enough for one machine: each kind of work is timed with
    and without its links."""
    from dataclasses import replace

    from commlens.plans.experiments import sample_graph
    from commlens.plans.kernel import SerialSampler
    from commlens.plans.study import collect_graph

    rows = []
    for f in fractions:
        g = collect_graph(sample_graph(graph, f))
        for change, nf, ne in (({}, len(g.friends), len(g.diffs)), ({"use_friends": False}, 0, len(g.diffs)), ({"use_diffusion": False}, len(g.friends), 0)):
            sampler = SerialSampler(g, replace(cfg, **change))
            sampler.refresh()
            began = time.process_time()
            sampler.attach(0)
            sampler.kernel.sweep(sampler.rng)
            rows.append((len(g.user), nf, ne, time.process_time() - began))
    return partition.calibrate(rows)


