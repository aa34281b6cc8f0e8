"""Accuracy measures: conductance, AUC, perplexity, folds, paired tests, recovery of planted labels."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens import scratch
from commlens.functions.expressions import hashed
from commlens.operators import factors
from commlens.sources.graphs import numbered as number_rows


def conductance(friends: DataFrame, members: DataFrame) -> DataFrame:
    """(c, cut, vol, conductance) of each community with members, over undirected friendship links; one pass of links by membership sets.

    The volume is the sum of degrees; the smaller of community and rest divides the cut. Zero volume gives zero."""
    both = friends.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
    sets = members.groupBy("user_id").agg(F.collect_set("c").alias("cs"))
    none = F.from_json(F.lit("[]"), "array<int>")
    a = both.join(sets.select(F.col("user_id").alias("a"), F.col("cs").alias("ca")), "a", "left").join(sets.select(F.col("user_id").alias("b"), F.col("cs").alias("cb")), "b", "left")
    a = a.select(F.coalesce("ca", none).alias("ca"), F.coalesce("cb", none).alias("cb"))
    ends = a.select(F.explode(F.concat(F.transform(F.array_union("ca", "cb"), lambda c: F.struct(c.alias("c"), (F.array_contains("ca", c).cast("int") + F.array_contains("cb", c).cast("int")).alias("n"))))).alias("e"))
    per = ends.groupBy(F.col("e.c").alias("c")).agg(F.sum(F.when(F.col("e.n") == 1, 1).otherwise(0)).alias("cut"), F.sum("e.n").alias("vol"))
    whole = both.agg((2 * F.count("*")).alias("whole"))
    out = members.select("c").distinct().join(per, "c", "left").fillna(0, ["cut", "vol"]).crossJoin(F.broadcast(whole))
    least = F.least(F.col("vol"), F.col("whole") - F.col("vol"))
    return out.select("c", "cut", "vol", F.when(least > 0, F.col("cut") / least).otherwise(F.lit(0.0)).alias("conductance"))


def auc(scored: DataFrame, score: str = "score", label: str = "label") -> DataFrame:
    """One row: the chance that a random positive outranks a random negative, ties counting a half. Scores are counted first, so the
    running sum goes over distinct scores: through ranges of scores, whose sums are added up, then within each."""
    hist = scored.groupBy(F.col(score).alias("s")).agg(F.sum(F.when(F.col(label) == 1, 1).otherwise(0)).alias("p"), F.sum(F.when(F.col(label) == 1, 0).otherwise(1)).alias("n"))
    ends = hist.agg(F.min("s").alias("lo"), F.max("s").alias("hi"))
    cell = F.when(F.col("hi") > F.col("lo"), F.floor((F.col("s") - F.col("lo")) / (F.col("hi") - F.col("lo")) * 4095)).otherwise(F.lit(0)).cast("int")
    placed = hist.crossJoin(F.broadcast(ends)).select("s", "p", "n", cell.alias("cell"))
    cells = placed.groupBy("cell").agg(F.sum("n").alias("cn"))
    below = cells.select("cell", (F.sum("cn").over(W.orderBy("cell")) - F.col("cn")).alias("below"))
    run = placed.join(F.broadcast(below), "cell").withColumn("lower", F.col("below") + F.sum("n").over(W.partitionBy("cell").orderBy("s")) - F.col("n"))
    total = run.agg(F.sum(F.col("p") * (F.col("lower") + F.col("n") / 2.0)).alias("u"), F.sum("p").alias("np"), F.sum("n").alias("nn"))
    return total.select(F.when((F.col("np") > 0) & (F.col("nn") > 0), F.col("u") / F.col("np") / F.col("nn")).alias("auc"), F.col("np").alias("n_pos"), F.col("nn").alias("n_neg"))


def fold_of(folds: int = 10, salt: int = 5, *keys: Column) -> Column:
    """The fold of a link by a linear hash of its ends."""
    mixed = keys[0].cast("bigint")
    for k in keys[1:]:
        mixed = F.pmod(mixed * 1000003 + k.cast("bigint"), F.lit(2147483647))
    return F.pmod(F.floor(hashed(mixed, salt) / F.lit(128)), F.lit(folds)).cast("int")


def non_links(links: DataFrame, targets: DataFrame, salt: int = 11, rounds: int = 12, avoid: DataFrame | None = None) -> DataFrame:
    """As many (src, dst) pairs as links that are no links: each link's source with a target picked by hash. Targets are an
    (i, id) table numbered from zero. A pick that is a link, a loop, or a pair that another link has picked is drawn again, in up to ``rounds``
    rounds; there are fewer pairs only where a source has hardly any target left that it does not link to. ``avoid`` has further pairs (src, dst) to keep out."""
    n = targets.count()
    known = links.select("src", "dst") if avoid is None else links.select("src", "dst").union(avoid.select("src", "dst"))
    wanted, taken = links.select("src", "dst"), None
    for turn in range(rounds):
        spot = F.pmod(F.floor(hashed(F.pmod(F.col("src") * 1000003 + F.col("dst"), F.lit(2147483647)), salt + 7919 * turn) / F.lit(16)), F.lit(max(1, n)))
        picked = wanted.withColumn("i", spot.cast("bigint")).join(targets, "i").where("src <> id").select("src", F.col("id").alias("to"), "dst")
        fresh = picked.join(known.select("src", F.col("dst").alias("to")), ["src", "to"], "left_anti")
        if taken is not None:
            fresh = fresh.join(taken.select("src", "to"), ["src", "to"], "left_anti")
        fresh = scratch.written(fresh.groupBy("src", "to").agg(F.min("dst").alias("dst")))
        taken = fresh if taken is None else scratch.written(taken.union(fresh))
        wanted = links.select("src", "dst").join(taken.select("src", "dst"), ["src", "dst"], "left_anti")
        if wanted.isEmpty():
            break
    return taken.select("src", F.col("to").alias("dst"))


def numbered(ids: DataFrame, name: str) -> DataFrame:
    """(i, id) of distinct ids in order."""
    return number_rows(ids.select(F.col(name).alias("id")).distinct(), "id").select("i", "id")


def perplexity(tokens: DataFrame, pi: DataFrame, theta: DataFrame, phi: DataFrame, form: str = "doc_topic") -> DataFrame:
    """One row (perplexity, n_tokens) over documents with the users of pi. ``doc_topic`` mixes topics per document, ``word_mix`` per token."""
    mix = pi.join(F.broadcast(theta.select("c", "z", F.col("p").alias("t"))), "c").groupBy("user_id", "z").agg(F.sum(F.col("p") * F.col("t")).alias("w"))
    if form == "word_mix":
        cells = lambda rows, key, value, name: rows.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("z", value))).alias(name))
        by_word = cells(phi, "word", "p", "topics")
        by_word = F.broadcast(by_word) if phi.count() <= factors.TENSOR_CELLS else by_word
        seen = tokens.select("user_id", "word", "cnt").join(cells(mix, "user_id", "w", "mix"), "user_id").join(by_word, "word").where(F.arrays_overlap(F.map_keys("mix"), F.map_keys("topics")))
        q = F.aggregate(F.map_entries("mix"), F.lit(0.0), lambda a, x: a + x["value"] * F.coalesce(F.try_element_at(F.col("topics"), x["key"]), F.lit(0.0)))
        per = seen.select("cnt", q.alias("q"))
        total = per.agg(F.sum(F.col("cnt") * F.ln("q")).alias("ll"), F.sum("cnt").alias("n"))
    else:
        seen = tokens.join(phi, "word")
        fit = seen.groupBy("doc_id", "user_id", "z").agg(F.sum(F.col("cnt") * F.ln("p")).alias("l"), F.sum("cnt").alias("n")).join(mix, ["user_id", "z"])
        peak = fit.withColumn("m", F.max("l").over(W.partitionBy("doc_id")))
        per = peak.groupBy("doc_id").agg((F.first("m") + F.ln(F.sum(F.col("w") * F.exp(F.col("l") - F.col("m"))))).alias("ll"), F.first("n").alias("n"))
        total = per.agg(F.sum("ll").alias("ll"), F.sum("n").alias("n"))
    return total.select(F.exp(-F.col("ll") / F.col("n")).alias("perplexity"), F.col("n").cast("bigint").alias("n_tokens"))


def paired_t(a: list[float], b: list[float]) -> tuple[float, float]:
    """t statistic and one-tailed p-value that a's mean exceeds b's, over folds."""
    d = [x - y for x, y in zip(a, b, strict=True)]
    n = len(d)
    mean = sum(d) / n
    spread = math.sqrt(sum((x - mean) ** 2 for x in d) / (n - 1))
    if spread == 0:
        return (math.inf if mean > 0 else -math.inf if mean < 0 else 0.0), (0.0 if mean > 0 else 1.0 if mean < 0 else 0.5)
    t = mean / (spread / math.sqrt(n))
    return t, student_tail(t, n - 1)


def student_tail(t: float, df: int) -> float:
    """P(T > t) by the incomplete beta function's continued fraction."""
    x = df / (df + t * t)
    half = 0.5 * _beta_share(df / 2, 0.5, x)
    return half if t >= 0 else 1 - half


def _beta_share(a: float, b: float, x: float) -> float:
    """The regularised incomplete beta function, by a power series on the side where it converges fast."""
    if x <= 0 or x >= 1:
        return 0.0 if x <= 0 else 1.0
    if x > (a + 1) / (a + b + 2):
        return 1 - _beta_share(b, a, 1 - x)
    term = total = 1.0
    n = 0
    while term > 1e-17 * total:
        term *= x * (a + b + n) / (a + 1 + n)
        total += term
        n += 1
    return math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x)) / a * total


def mutual_information(labels: DataFrame, a: str, b: str) -> DataFrame:
    """One row (nmi, ari) of two labelings, from their contingency counts."""
    cells = labels.groupBy(a, b).agg(F.count("*").alias("n"))
    rows, cols = cells.groupBy(a).agg(F.sum("n").alias("ra")), cells.groupBy(b).agg(F.sum("n").alias("rb"))
    total = labels.agg(F.count("*").alias("t"))
    pair = lambda c: F.col(c) * (F.col(c) - 1) / 2
    joint = cells.join(rows, a).join(cols, b).crossJoin(F.broadcast(total)).agg(F.sum(F.col("n") / F.col("t") * F.ln(F.col("n") * F.col("t") / F.col("ra") / F.col("rb"))).alias("mi"), F.sum(pair("n")).alias("same"))
    ent = lambda df, c: df.crossJoin(F.broadcast(total)).agg((-F.sum(F.col(c) / F.col("t") * F.ln(F.col(c) / F.col("t")))).alias(f"h{c}"), F.sum(pair(c)).alias(f"s{c}"))
    both = joint.crossJoin(ent(rows, "ra")).crossJoin(ent(cols, "rb")).crossJoin(total.select(pair("t").alias("st")))
    expect = F.col("sra") * F.col("srb") / F.col("st")
    nmi = F.when((F.col("hra") > 0) & (F.col("hrb") > 0), F.col("mi") / F.sqrt(F.col("hra") * F.col("hrb"))).otherwise(F.lit(0.0))
    top = (F.col("sra") + F.col("srb")) / 2 - expect
    return both.select(nmi.alias("nmi"), F.when(top != 0, (F.col("same") - expect) / top).otherwise(F.lit(1.0)).alias("ari"))
