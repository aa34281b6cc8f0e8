"""Segments of users, their load, and their placement on workers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens.sources.graphs import SocialGraph

#: Steps of capacity that the exact packing tells apart.
RESOLUTION = 2000


def segment_users(doc_topics: DataFrame) -> DataFrame:
    """(user_id, seg): a user goes, with all documents, to its most frequent topic, the lower one on ties."""
    n = doc_topics.groupBy("user_id", "z").agg(F.count("*").alias("n"))
    return n.groupBy("user_id").agg(F.max_by(F.col("z"), F.struct("n", -F.col("z"))).cast("int").alias("seg"))


def calibrate(times: list[tuple[float, float, float, float]]) -> tuple[float, float, float]:
    """Seconds per document, friendship link and diffusion link, by least squares over serial runs of (documents, friends, diffusions, seconds)."""
    import numpy as np

    rows = np.array(times, dtype=float)
    got, *_ = np.linalg.lstsq(rows[:, :3], rows[:, 3], rcond=None)
    return tuple(float(max(0.0, x)) for x in got)


def user_load(graph: SocialGraph, unit: tuple[float, float, float]) -> DataFrame:
    """(user_id, load): the work for a user's documents and outgoing links."""
    docs = graph.docs.groupBy("user_id").agg(F.count("*").alias("nd"))
    friends = graph.friends.groupBy(F.col("src").alias("user_id")).agg(F.count("*").alias("nf"))
    diffs = graph.diffs.groupBy(F.col("src_user").alias("user_id")).agg(F.count("*").alias("ne"))
    joined = docs.join(friends, "user_id", "left").join(diffs, "user_id", "left").fillna(0, ["nf", "ne"])
    return joined.select("user_id", (unit[0] * F.col("nd") + unit[1] * F.col("nf") + unit[2] * F.col("ne")).alias("load"))


def segment_load(segments: DataFrame, graph: SocialGraph, unit: tuple[float, float, float]) -> DataFrame:
    return segments.join(user_load(graph, unit), "user_id").groupBy("seg").agg(F.sum("load").alias("load"))


def pack(loads: dict[int, float], workers: int, method: str = "dp") -> dict[int, int]:
    """Segment -> worker. ``dp`` solves one 0-1 knapsack of capacity total / workers after the other; what is left, and what is larger
    than a knapsack, goes to the least loaded worker. ``greedy`` gives the largest left segment to the least loaded worker."""
    total = sum(loads.values())
    left = dict(sorted(loads.items(), key=lambda x: (-x[1], x[0])))
    placed: dict[int, int] = {}
    sums = [0.0] * workers
    if method == "dp" and total > 0:
        room = total / workers
        for w in range(workers):
            best: dict[int, tuple[float, tuple[int, ...]]] = {0: (0.0, ())}
            for seg, load in left.items():
                for weight, (value, chosen) in sorted(best.items(), reverse=True):
                    if value + load <= room + 1e-9:
                        key = int((value + load) / room * RESOLUTION)
                        if key not in best or best[key][0] < value + load:
                            best[key] = (value + load, (*chosen, seg))
            for seg in max(best.values())[1]:
                placed[seg] = w
                sums[w] += left.pop(seg)
    for seg, load in left.items():
        w = min(range(workers), key=lambda i: (sums[i], i))
        placed[seg] = w
        sums[w] += load
    return placed


def placement(load: DataFrame, workers: int, method: str = "dp") -> DataFrame:
    """(seg, worker); there are as many rows as topics, so they are packed on the driver."""
    got = pack({r["seg"]: r["load"] for r in load.collect()}, workers, method)
    return load.sparkSession.createDataFrame(sorted(got.items()), "seg int, worker int")


def balance(load: DataFrame, placed: DataFrame) -> DataFrame:
    """(worker, load, ratio): ratio of the worker's load to the mean."""
    per = load.join(F.broadcast(placed), "seg").groupBy("worker").agg(F.sum("load").alias("load"))
    return per.crossJoin(per.agg(F.avg("load").alias("mean"))).select("worker", "load", (F.col("load") / F.col("mean")).alias("ratio"))
