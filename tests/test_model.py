"""Exact checks of the model's pieces on small graphs."""

import math
import random
import re
import time
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from commlens import scratch
from commlens.config import ProfilerConfig
from commlens.functions import expressions, text, udfs
from commlens.functions.augmentation import KeyedRandom
from commlens.operators import counters, factors, measures, partition, ranking, sampling
from commlens.plans import baselines, kernel, study
from commlens.plans.profiler import JointProfiler, log_joint_terms, negative_links, variant
from commlens.sources.graphs import SocialGraph
from commlens.sources.planted import PlantedConfig, generate


@pytest.fixture(scope="module")
def keep(spark, tmp_path_factory):
    """Cuts a step's lineage."""
    spark.sparkContext.setCheckpointDir(str(tmp_path_factory.mktemp("checkpoints")))
    return lambda df: df.checkpoint()


@pytest.fixture(scope="module")
def tiny(spark):
    """Six users, twelve documents of two words out of five, eight friendship and five diffusion links."""
    docs = [(i, i % 6, i % 3, 2 + i % 2) for i in range(12)]
    words = [(i, i % 6, f"w{(i * 7 + k) % 5}", 1 + (k and i % 2)) for i in range(12) for k in range(2)]
    friends = [(0, 1), (1, 2), (2, 0), (3, 4), (4, 5), (5, 3), (0, 3), (2, 5)]
    diffs = [(6, 1, 0, 1, 0), (7, 2, 1, 2, 1), (8, 0, 2, 0, 2), (9, 4, 3, 4, 0), (10, 3, 4, 3, 1)]
    return SocialGraph(
        spark.createDataFrame([(d, u, t, n) for d, u, t, n in docs], "doc_id bigint, user_id bigint, tbin int, n_tok bigint"),
        spark.createDataFrame(words, "doc_id bigint, user_id bigint, word string, cnt bigint"),
        spark.createDataFrame(friends, "src bigint, dst bigint"),
        spark.createDataFrame(diffs, "src_doc bigint, dst_doc bigint, src_user bigint, dst_user bigint, tbin int"),
    )


@pytest.fixture(scope="module")
def assign(spark, tiny):
    return spark.createDataFrame([(i, i % 6, (i * 5 + 1) % 7 % 2, (i * 3) % 5 % 2) for i in range(12)], "doc_id bigint, user_id bigint, c int, z int").persist()


def test_counts_are_conserved(tiny, assign):
    n = lambda df: df.agg(F.sum("n")).first()[0]
    assert n(counters.user_community(assign)) == n(counters.community_topic(assign)) == n(counters.topic_time(assign, tiny.docs)) == 12
    assert n(counters.topic_word(assign, tiny.tokens)) == tiny.tokens.agg(F.sum("cnt")).first()[0]
    for df, of in ((counters.smoothed_membership(counters.user_community(assign), 2, 25.0), "user_id"), (counters.smoothed_topics(counters.community_topic(assign), 2, 2, 25.0), "c"), (counters.smoothed_words(counters.topic_word(assign, tiny.tokens), tiny.vocab(), 0.1), "z"), (counters.eta(tiny.diffs, assign), "c")):
        assert all(abs(r.s - 1) < 1e-9 for r in df.groupBy(of).agg(F.sum("p").alias("s")).collect())


def test_scores_are_ratios_of_joints(spark, tiny, assign):
    """Text parts of both conditionals differ from the log joint by a constant of the document."""
    alpha, rho, beta = 0.7, 0.9, 0.1
    rows = {r.doc_id: r for r in assign.collect()}
    scores = {(r.doc_id, r.z): r.score for r in sampling.topic_text_scores(assign, tiny.tokens, tiny.docs, 2, 2, alpha, beta, 5).collect()}
    comm = {(r.doc_id, r.c): r.score for r in sampling.community_text_scores(assign, 2, 2, alpha, rho).collect()}

    def joint(**change):
        d = change.pop("doc")
        moved = [(i, r.user_id, change.get("c", r.c) if i == d else r.c, change.get("z", r.z) if i == d else r.z) for i, r in rows.items()]
        t = log_joint_terms(spark.createDataFrame(moved, assign.schema), tiny.tokens, 2, 2, alpha, rho, beta).first()
        return sum(t)

    for d in (0, 5):
        assert abs((scores[d, 1] - scores[d, 0]) - (joint(doc=d, z=1) - joint(doc=d, z=0))) < 2e-3
        assert abs((comm[d, 1] - comm[d, 0]) - (joint(doc=d, c=1) - joint(doc=d, c=0))) < 2e-3


def memberships(assign, user=None, doc=None, c=None):
    rows = [(r.user_id, c if r.doc_id == doc else r.c) for r in assign.collect()]
    out = {}
    for u, k in rows:
        out.setdefault(u, np.zeros(2))[k] += 1
    return {u: v / v.sum() for u, v in out.items()}


def test_friend_terms_match_a_walk_over_links(tiny, assign):
    pi0 = memberships(assign)
    links = [(r.src, r.dst) for r in tiny.friends.collect()]
    lam = {e: (0.25 if (x := pi0[e[0]] @ pi0[e[1]]) < 1e-6 else math.tanh(x / 2) / (2 * x)) for e in links}
    got = {(r.doc_id, r.c): r.term for r in sampling.community_friend_scores(assign, tiny.friends, counters.empirical_membership(assign), 2).collect()}
    for r in assign.collect():
        direct = []
        for c in range(2):
            mine = memberships(assign, doc=r.doc_id, c=c)[r.user_id]
            t = 0.0
            for e in links:
                if r.user_id in e:
                    x = mine @ pi0[e[1] if e[0] == r.user_id else e[0]]
                    t += (x - lam[e] * x * x) / 2
            direct.append(t)
        assert abs((got[r.doc_id, 1] - got[r.doc_id, 0]) - (direct[1] - direct[0])) < 1e-9


def test_link_terms_match_a_walk_over_links(tiny, assign):
    pi = counters.empirical_membership(assign)
    tensor = factors.tensor(counters.empirical_topics(assign), counters.eta(tiny.diffs, assign))
    pop, feat = counters.popularity(counters.topic_time(assign, tiny.docs), "share"), counters.user_features(tiny.docs, tiny.friends, tiny.diffs)
    nu = (0.1, 0.2, 0.3, -0.1)
    scored = factors.diffusion_scores(factors.link_topics(tiny.diffs, assign), pi, tensor, pop, feat, nu)
    g = sampling.sent(tensor, (2, 2, 2), ["z", "c", "c2"], "g")
    arrays = sampling.community_link_arrays(tiny.diffs, assign, pi, g, sampling.sent(pop, (2, 3), ["z", "tbin"], "pop"), feat, nu, ("community", "topic", "individual"))
    got = {(r.doc_id, c): v for r in arrays.collect() for c, v in enumerate(r.term)}
    wide = {r.doc_id: r.term for r in sampling.wide_community_link_arrays(scored, assign, pi, tensor, 2, factors.augmentation_means).collect()}
    assert all(abs((wide[i][1] - wide[i][0]) - (got[i, 1] - got[i, 0])) < 1e-9 for i in wide) and len(wide) * 2 == len(got)
    narrow = {r.doc_id: r.term for r in sampling.topic_link_arrays(tiny.diffs, assign, pi, g, sampling.sent(pop, (2, 3), ["z", "tbin"], "pop"), feat, nu, ("community", "topic", "individual")).collect()}
    joined = {r.doc_id: r.term for r in sampling.wide_topic_link_arrays(tiny.diffs, assign, pi, tensor, pop, feat, nu, 2, ("community", "topic", "individual"), factors.augmentation_means).collect()}
    assert narrow.keys() == joined.keys() and all(np.allclose(narrow[i], joined[i]) for i in narrow)
    pi0 = memberships(assign)
    for r in assign.collect():
        direct, seen = [0.0, 0.0], False
        for link in scored.collect():
            if r.doc_id in (link.src_doc, link.dst_doc):
                seen = True
                base = pi0[link.src_user] @ g[link.z] @ pi0[link.dst_user]
                a = math.tanh(link.y / 2) / (2 * link.y) if abs(link.y) > 1e-6 else 0.25
                for c in range(2):
                    mine = memberships(assign, doc=r.doc_id, c=c)[r.user_id]
                    y = link.y - base + (mine @ g[link.z] @ pi0[link.dst_user] if r.doc_id == link.src_doc else pi0[link.src_user] @ g[link.z] @ mine)
                    direct[c] += (y - a * y * y) / 2
        if seen:
            assert abs((got[r.doc_id, 1] - got[r.doc_id, 0]) - (direct[1] - direct[0])) < 1e-9


def test_augmentation_identities(spark):
    grid = [0.0, 0.1, 0.5, 1.0, 2.0, 5.0, 20.0]
    got = spark.createDataFrame([(b,) for b in grid], "b double").select(expressions.pg_mean(F.col("b")).alias("m")).collect()
    for b, r in zip(grid, got, strict=True):
        assert abs(r.m - (0.25 if b == 0 else math.tanh(b / 2) / (2 * b))) < 1e-12
    for b in grid:
        variance = 1 / 24 if b == 0 else (math.sinh(b) - b) / (4 * b**3 * math.cosh(b / 2) ** 2)
        mean = 0.25 if b == 0 else math.tanh(b / 2) / (2 * b)
        for draw in (udfs.pg_exact, udfs.pg_series):
            x = draw(np.full(20_000, b), KeyedRandom(np.arange(20_000), 1))
            assert abs(x.mean() - mean) < 5 * math.sqrt(variance / len(x)) and abs(x.var() - variance) < 0.12 * variance
    x = udfs.pg_exact(np.zeros(40_000), KeyedRandom(np.arange(40_000), 2))
    assert np.allclose(x[5_000:5_010], udfs.pg_exact(np.zeros(10), KeyedRandom(np.arange(5_000, 5_010), 2)))
    for w in (-1.0, 0.5, 2.0):
        assert abs(0.5 * np.exp((w - x * w * w) / 2).mean() - 1 / (1 + math.exp(-w))) < 0.01


def test_draws(spark):
    rows = [(i, z, float(z == i % 3) * 2) for i in range(3000) for z in range(3)]
    scores = spark.createDataFrame(rows, "doc_id bigint, z int, score double")
    assert all(r.z == r.doc_id % 3 for r in sampling.draw(scores, "z", "argmax").collect())
    want = math.exp(2) / (math.exp(2) + 2)
    for how in ("gumbel", "inverse"):
        got = sampling.draw(scores, "z", how, 9).collect()
        assert len(got) == 3000 and abs(sum(r.z == r.doc_id % 3 for r in got) / 3000 - want) < 0.03
        assert sorted(map(tuple, got)) == sorted(map(tuple, sampling.draw(scores.repartition(7), "z", how, 9).collect()))


def test_conductance_of_two_cliques(spark):
    edges = [(a, b) for k in (0, 5) for a in range(k, k + 5) for b in range(a + 1, k + 5)] + [(0, 5)]
    friends = spark.createDataFrame(edges, "src bigint, dst bigint")
    members = spark.createDataFrame([(u, u // 5) for u in range(10)], "user_id bigint, c int")
    assert [round(r.conductance * 21, 9) for r in measures.conductance(friends, members).collect()] == [1, 1]


def test_auc_counts_pairs(spark):
    rng = np.random.default_rng(3)
    p, n = rng.integers(0, 12, 50) / 4, rng.integers(0, 9, 60) / 4
    want = np.mean([(a > b) + 0.5 * (a == b) for a in p for b in n])
    df = spark.createDataFrame([(float(x), 1) for x in p] + [(float(x), 0) for x in n], "score double, label int")
    assert abs(measures.auc(df).first().auc - want) < 1e-12
    assert abs(df.agg(udfs.auc_udaf("score", "label")).first()[0] - want) < 1e-12
    assert measures.auc(df.limit(0)).first().auc is None


def test_published_ranking_rows(spark):
    """Harmonic means of three printed pairs of precision and recall."""
    rows = spark.createDataFrame([("a", 1, 0.919, 0.327), ("b", 1, 0.900, 0.424), ("c", 1, 0.891, 0.528)], "q_id string, k int, precision double, recall double")
    got = {r.q_id: r.maf for r in ranking.averages(rows, by_query=True).collect()}
    assert abs(got["a"] - 0.483) < 1e-3 and abs(got["b"] - 0.576) < 1e-3 and abs(got["c"] - 0.663) < 1e-3


def test_student_tail():
    assert abs(measures.student_tail(1.833113, 9) - 0.05) < 1e-6 and abs(measures.student_tail(2.821438, 9) - 0.01) < 1e-6
    t, p = measures.paired_t([0.9, 0.8, 0.85, 0.95], [0.7, 0.7, 0.8, 0.75])
    assert t > 0 and p < 0.05


def test_knapsack():
    loads = dict(enumerate([7.0, 6.0, 5.0, 4.0, 3.0, 3.0]))
    for workers, most in ((2, 14.0), (3, 10.0)):
        placed = partition.pack(loads, workers)
        sums = [sum(loads[s] for s, w in placed.items() if w == k) for k in range(workers)]
        assert len(placed) == 6 and max(sums) <= most
    assert set(partition.pack({0: 100.0, 1: 1.0, 2: 1.0}, 2).values()) == {0, 1}
    assert partition.calibrate([(10, 5, 1, 10 * 2 + 5 * 3 + 4), (20, 1, 3, 40 + 3 + 12), (5, 9, 9, 10 + 27 + 36)]) == pytest.approx((2, 3, 4))


def test_users_without_links(spark, tiny):
    got = {r.user_id: r for r in counters.user_features(tiny.docs, tiny.friends.where("src = 0"), tiny.diffs.limit(0)).collect()}
    assert got[0].popularity == 0 and got[1].popularity == 0 and got[5].activeness == 0 and len(got) == 6


def test_blocked_sweeps_climb(spark, keep):
    """Two synchronous sweeps over planted documents raise the log joint; the segmented tests hold labels against the truth."""
    planted = generate(spark, PlantedConfig(users=60, docs_per_user=6, communities=3, topics=3, friends_per_user=10, seed=2))
    graph = SocialGraph(*(keep(df) for df in (planted.graph.docs, planted.graph.tokens, planted.graph.friends, planted.graph.diffs)))
    cfg = ProfilerConfig(communities=3, topics=3, alpha=0.1, rho=0.1, sweeps=2, blocks=1, use_diffusion=False, factors=(), seed=4)
    got = JointProfiler(cfg, keep).fit(graph)
    assert got.trace[1] > got.trace[0] and got.assign.count() == 360


def test_full_sweep_runs(spark, tiny):
    """With means, draws and the other ways; draws move the assignment, and the same seed gives the same again."""
    cfg = ProfilerConfig(communities=2, topics=2, sweeps=1, blocks=1, nu_steps=1, alpha=0.5, rho=0.5)
    got = {}
    for name, change in (("mean", {}), ("exact", {"pg": "exact", "burnin": 0, "nu_fit": "glr"}), ("again", {"pg": "exact", "burnin": 0, "nu_fit": "glr"})):
        got[name] = JointProfiler(replace(cfg, **change)).fit(tiny)
        assert got[name].assign.count() == 12 and all(math.isfinite(w) for w in got[name].nu) and got[name].eta.count() > 0 and all(math.isfinite(x) for x in got[name].trace)
    rows = {k: sorted(map(tuple, v.assign.collect())) for k, v in got.items()}
    assert rows["exact"] == rows["again"] and got["exact"].trace == pytest.approx(got["again"].trace)
    assert rows["mean"] != rows["exact"] or got["mean"].nu != got["exact"].nu
    uc = {(r.user_id, r.c): r.p for r in got["exact"].pi.collect()}
    assert all(abs(sum(uc[u, c] for c in range(2)) - 1) < 1e-9 for u in range(6))


def test_communities_from_links_alone(spark, tiny):
    """Other words change neither the first stage of the two-stage variant nor the role blocks."""
    other = replace(tiny, tokens=tiny.tokens.withColumn("word", F.lit("same")).groupBy("doc_id", "user_id", "word").agg(F.sum("cnt").alias("cnt")))
    cfg = variant(ProfilerConfig(communities=2, topics=2, sweeps=1, blocks=1), "links_only")
    a, b = (sorted((r.doc_id, r.c) for r in JointProfiler(cfg).fit(g).assign.collect()) for g in (tiny, other))
    assert a == b
    a, b = (sorted((r.user_id, r.b, round(r.p, 9)) for r in baselines.RoleBlock(2, 2, 2).fit(g, scratch.written).block.collect()) for g in (tiny, other))
    assert a == b


def test_kernel_scores_are_ratios_of_the_joint(tiny):
    """Differences of candidate scores equal differences of the log joint given the augmentation variables, tensor and popularity, all written out, with the diffusion links of the document."""
    g = study.collect_graph(tiny)
    cfg = ProfilerConfig(communities=3, topics=2, alpha=0.4, rho=0.3, pg="exact", seed=5)
    m = kernel.SerialSampler(g, cfg)
    m.refresh()
    m.nu = np.array([0.1, 0.2, -0.1, 0.3])
    m.attach(0)
    k, s = m.kernel, m.kernel.s

    def joint(c, z, doc):
        uc, ct, tw = np.zeros((g.n_users, 3)), np.zeros((3, 2)), np.zeros((2, g.n_words))
        np.add.at(uc, (g.user, c), 1)
        np.add.at(ct, (c, z), 1)
        for i in range(len(z)):
            tw[z[i], g.words[i]] += g.counts[i]
        lg = lambda x: np.vectorize(math.lgamma)(x)
        part = lambda n, a: (lg(n + a) - math.lgamma(a)).sum() - (lg(n.sum(axis=1) + a * n.shape[1]) - math.lgamma(a * n.shape[1])).sum()
        total = part(uc, 0.3) + part(ct, 0.4) + part(tw, cfg.beta)
        pi = uc / uc.sum(axis=1, keepdims=True)
        n = len(m.links)
        lam = {}
        for u, (v, aug) in s.friends.items():
            for x, y in zip(v, aug, strict=True):
                lam[u, int(x)] = y
        total += sum(kernel.log_factor(pi[a] @ pi[b], lam[a, b]) for a, b in m.links.tolist()) if n else 0.0
        own = m.design(g.user[g.diffs[:, 0]], g.user[g.diffs[:, 1]]) @ m.nu
        for e, (i, j) in enumerate(g.diffs.tolist()):
            if doc not in (i, j):
                continue
            aug = s.ends[i].aug[np.flatnonzero((s.ends[i].other == g.user[j]) & s.ends[i].source)[0]]
            y = pi[g.user[i]] @ s.tensor[z[i]] @ pi[g.user[j]] + s.pop[z[i], g.tbin[i]] + own[e]
            total += kernel.log_factor(y, aug)
        return total

    linked = set(g.diffs.ravel().tolist())
    for i in sorted(linked):
        s.ct[k.c[i], k.z[i]] -= 1
        s.tw[k.z[i], k.words[i]] -= k.counts[i]
        s.nz[k.z[i]] -= k.size[i]
        got = k.topic_scores(i)
        s.tw[k.z[i], k.words[i]] += k.counts[i]
        s.nz[k.z[i]] += k.size[i]
        if not (g.diffs[:, 1] == i).any():
            want = [joint(k.c, np.where(np.arange(len(k.z)) == i, z, k.z), i) for z in range(2)]
            assert got[1] - got[0] == pytest.approx(want[1] - want[0], abs=1e-9)
        s.uc[g.user[i], k.c[i]] -= 1
        got = k.community_scores(i)
        want = [joint(np.where(np.arange(len(k.c)) == i, c, k.c), k.z, i) for c in range(3)]
        assert got - got[0] == pytest.approx(np.array(want) - want[0], abs=1e-9)
        s.uc[g.user[i], k.c[i]] += 1
        s.ct[k.c[i], k.z[i]] += 1


def test_mixtures_against_arrays(spark, tiny):
    """Steps of the DataFrame mixtures and of the arrays of a study agree, with links and without."""
    theta, phi = baselines.first_mixtures(tiny.docs, tiny.tokens, 2)
    rate = spark.createDataFrame([(0, 1.0), (1, 1.0)], "z int, rate double")
    t0 = {(r.doc_id, r.z): r.p for r in theta.collect()}
    p0 = {(r.z, r.word): r.p for r in phi.collect()}
    for links in (False, True):
        n = {k: 0.0 for k in t0}
        for r in tiny.tokens.collect():
            h = [t0[r.doc_id, z] * p0[z, r.word] for z in range(2)]
            for z in range(2):
                n[r.doc_id, z] += r.cnt * h[z] / sum(h)
        for r in tiny.diffs.collect() if links else ():
            h = [t0[r.src_doc, z] * t0[r.dst_doc, z] for z in range(2)]
            for z in range(2):
                n[r.src_doc, z] += h[z] / sum(h)
                n[r.dst_doc, z] += h[z] / sum(h)
        got = baselines.mixture_step(tiny.tokens, theta, phi, 2, 0.1, 0.1, 5, tiny.diffs if links else None, rate if links else None)[0]
        for r in got.collect():
            assert r.p == pytest.approx((n[r.doc_id, r.z] + 0.1) / (n[r.doc_id, 0] + n[r.doc_id, 1] + 0.2), abs=1e-6)


def test_non_links_are_as_many_as_links(spark, tiny):
    pairs = negative_links(tiny, 3)
    assert pairs.count() == tiny.diffs.count() and pairs.where("src_user = dst_user").count() == 0
    assert pairs.join(tiny.diffs, ["src_doc", "dst_doc"]).count() == 0 and pairs.select("src_doc", "dst_doc").distinct().count() == 5


def test_variants():
    assert variant(ProfilerConfig(), "no_topic").factors == ("community", "individual")


def test_rows_are_never_exchanged_by_document_and_candidate(spark, tiny, assign):
    pi = counters.empirical_membership(assign)
    plans = [sampling.topic_text_scores(assign, tiny.tokens, tiny.docs, 2, 2, 1.0, 0.1, 5), sampling.community_text_scores(assign, 2, 2, 1.0, 1.0), sampling.community_friend_scores(assign, tiny.friends, pi, 2)]
    for df in plans:
        plan = df._jdf.queryExecution().executedPlan().toString()
        assert not re.search(r"hashpartitioning\(doc_id#\d+L, (z|c)#", plan) and "CartesianProduct" not in plan


def test_query_of_many_words_keeps_its_order(spark):
    phi = spark.createDataFrame([(z, f"w{i}", 1e-5 * (1 + z)) for z in range(2) for i in range(200)], "z int, word string, p double")
    queries = spark.createDataFrame([("long", f"w{i}") for i in range(200)] + [("one", "w1"), ("long", "unknown")], "q_id string, word string")
    reached = spark.createDataFrame([(0, 0, 1.0), (1, 1, 1.0)], "c int, z int, r double")
    got = {(r.q_id, r.c): (r.rank, r.score) for r in ranking.rank_communities(queries, phi, reached).collect()}
    assert got["long", 1][0] == got["one", 1][0] == 1 and got["long", 1][1] > 0


def test_preprocessing(spark):
    rows = [(1, 1, "The networks were quickly ROUTING beautiful #Spark stories, stopped"), (2, 1, "only the"), (3, 2, None), (4, 2, "")]
    got = text.preprocessed(spark.createDataFrame(rows, "doc_id bigint, user_id bigint, text string")).collect()
    assert [(r.doc_id, r.words) for r in got] == [(1, ["network", "rout", "#spark", "story", "stop"])]


def test_prepared_graph_follows_its_tables(spark, tmp_path):
    from commlens.sources import graphs

    def put(n):
        spark.createDataFrame([(i, i % 2, r, "some words here") for i in range(n) for r in ("user",)], "conv_id bigint, turn bigint, role string, text string").coalesce(1).write.mode("overwrite").parquet(f"{tmp_path}/conversations.parquet")

    put(3)
    assert graphs.prepared(spark, str(tmp_path), "dialog").docs.count() == 3 and graphs.prepared(spark, str(tmp_path), "dialog") is graphs.prepared(spark, str(tmp_path), "dialog")
    time.sleep(1.1)
    put(5)
    assert graphs.prepared(spark, str(tmp_path), "dialog").docs.count() == 5


def test_large_groups_keep_all_pairs(spark):
    """Groups of any size give every ordered pair once, in one block or dealt over many."""
    from itertools import permutations

    from commlens.sources import graphs

    rows = [("big", u) for u in range(1100)] + [("mid", u) for u in range(2000, 2030)] + [("one", 5000)] + [("mid", 2000)]
    members = spark.createDataFrame(rows, "g string, u bigint")
    want = 1100 * 1099 + 30 * 29
    pairs = graphs._pairs(members, ["g"], "u")
    assert pairs.count() == want
    small = members.where("g <> 'big'")
    for block in (1, 7, 1000):
        assert {tuple(r) for r in graphs._pairs(small, ["g"], "u", block).collect()} == set(permutations(range(2000, 2030), 2))
    left, right = graphs._blocked(members.where("g = 'mid'").distinct(), ["g"], "u", 7)
    assert left.join(right.withColumnRenamed("u", "v"), ["g", "block_l", "block_r"]).count() == 30 * 30


def test_web_hosts_of_a_common_target_are_friends(spark, tmp_path):
    from commlens.sources import graphs

    rows = [(i, f"http://h{i}.example/p", f'<title>some page</title><a href="/all">x</a><a href="/{i // 2}">y</a>') for i in range(40)]
    spark.createDataFrame(rows, "page_id bigint, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    assert graphs.web(spark, str(tmp_path)).friends.count() == 40 * 39


def test_corpus_keeps_lines_of_many_documents(spark, tmp_path):
    from commlens.sources import graphs

    line = "this line stands in every one of the documents"
    rows = [(i, f"{line}\nword{i} alone", "en", f"src{i % 3}") for i in range(40)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    graph = graphs.corpus(spark, str(tmp_path))
    assert {(r.src_doc, r.dst_doc) for r in graph.diffs.collect()} == {(a, b) for a in range(40) for b in range(a)}
    assert graph.friends.count() == 6


def test_corpus_reads_whole_texts(spark, tmp_path):
    from commlens.sources import graphs

    letters = "abcdefghijklmnopqrstuvwxyz"
    text = " ".join(f"word{a}{b}" for a in letters for b in letters)
    spark.createDataFrame([(1, text, "en", "src0")], "doc_id bigint, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    graph = graphs.corpus(spark, str(tmp_path))
    assert graph.docs.first().n_tok == 676 and graph.tokens.select("word").distinct().count() == 676

def test_corpus_links_are_counted_without_pairs(spark, tmp_path):
    """Copies, common lines, repeated and null ids: the counts are those of the links; they come from groups of documents, not from pairs of them."""
    from commlens.sources import graphs

    rng = random.Random(5)
    pool = [f"line {i} of thirty characters or more, shared" for i in range(12)]
    rows = [(rng.choice([None, rng.randrange(150), i + 200]), "\n".join(rng.sample(pool, rng.randrange(4)) + [pool[0]] * (i % 3 == 0) + [f"a line that only text {i} has, and no other"]), f"s{i % 4}", rng.choice(["en", "de", None])) for i in range(300)]
    rows += [(1000 + i, "\n".join(pool[:9]), "s9", "fr") for i in range(40)] + [(5000 + i, "a common line of thirty characters at least", "s1", "it") for i in range(400)]
    spark.createDataFrame(rows, "doc_id bigint, text string, source string, lang string").write.parquet(str(tmp_path / "documents.parquet"))
    want = graphs.statistics(graphs.corpus(spark, str(tmp_path))).first().asDict()
    for block in (1000, 7):
        friends, diffs = graphs.line_link_counts(graphs._corpus_parts(spark, str(tmp_path))[2], block)
        assert (friends.first()[0], diffs.first()[0]) == (want["n_friends"], want["n_diffs"])
    assert graphs.corpus_statistics(spark, str(tmp_path)).first().asDict() == want and want["n_diffs"] > 80_000
