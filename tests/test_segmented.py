"""The segmented schedule and the streams without an oracle."""

import pytest
from pyspark.sql import functions as F

from commlens.config import ProfilerConfig
from commlens.operators import counters, measures
from commlens.plans import segmented, study
from commlens.sources.graphs import SocialGraph
from commlens.sources.planted import PlantedConfig, generate
from commlens.streaming import events as st

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def planted(spark, tmp_path_factory):
    spark.sparkContext.setCheckpointDir(str(tmp_path_factory.mktemp("checkpoints")))
    p = generate(spark, PlantedConfig(users=120, docs_per_user=10, communities=3, topics=4, friends_per_user=16, seed=2))
    return p, SocialGraph(*(df.checkpoint() for df in (p.graph.docs, p.graph.tokens, p.graph.friends, p.graph.diffs)))


@pytest.mark.parametrize("chunk", [10_000, 200])
def test_segmented_sampler_finds_planted_topics(planted, chunk):
    p, graph = planted
    cfg = ProfilerConfig(communities=3, topics=4, alpha=0.1, rho=0.1, sweeps=8, seed=3, use_diffusion=False, factors=())
    got, _, _ = segmented.fit(graph, cfg, chunk_docs=chunk)
    assert got.count() == 1200
    both = got.select("doc_id", F.col("z").alias("z1"), F.col("c").alias("c1")).join(p.truth, "doc_id")
    assert measures.mutual_information(both, "z1", "z").first().nmi > 0.7


def test_segmented_sweep_is_repeatable(planted):
    _, graph = planted
    cfg = ProfilerConfig(communities=3, topics=4, alpha=0.1, rho=0.1, sweeps=1, seed=3, pg="exact")
    start = counters.first_assignment(graph.docs, 3, 4)
    features = counters.user_features(graph.docs, graph.friends, graph.diffs)
    segments = graph.users().selectExpr("user_id", "CAST(user_id % 3 AS INT) AS seg")
    a, b = (sorted(tuple(r)[:4] for r in segmented.sweep(graph, start, cfg, 0, segments, features, (0.1,) * 4, 300).collect()) for _ in range(2))
    assert a == b and len(a) == 1200


def test_outer_join_stream_keeps_matches(spark):
    rows = st.run(st.diffusion_links(st.event_stream(spark, SF), outer=True)).where("src is not null")
    inner = st.diffusion_links(st.event_batch(spark, SF))
    assert rows.exceptAll(inner).count() == 0 and inner.exceptAll(rows).count() == 0


def test_scores_reach_the_sink(spark):
    """The streamed scores are those of the same pairs in a batch, and lie between zero and one."""
    from commlens.contract.engine import _profiles

    seen = []
    profiles, nu = _profiles(spark, SF), (0.1, 0.2, 0.1, 0.3)
    st.score_to(st.candidate_pairs(st.event_stream(spark, SF)), profiles, nu, lambda df, i: seen.extend(df.collect()))
    want = st.scored(st.candidate_pairs(st.event_batch(spark, SF)), profiles, nu).collect()
    assert sorted(map(tuple, seen)) == sorted(map(tuple, want)) and len(seen) > 10 and all(0 < r.p < 1 for r in seen)


def _plain_pairs(rows):
    """Pairs by key alone, each compared."""
    a, b = rows.selectExpr("event_id AS src", "ts AS ts_a", "user_id AS src_user", "k"), rows.selectExpr("event_id AS dst", "ts AS ts_b", "user_id AS dst_user", "k")
    near = a.join(b, "k").where("src_user <> dst_user AND ts_b < ts_a AND ts_a <= ts_b + INTERVAL 6 HOUR")
    return sorted(map(tuple, near.selectExpr("src", "dst", "src_user", "dst_user", "k", "dayofmonth(ts_a)").collect()))


def test_pairs_of_packs_are_all_pairs(spark, monkeypatch):
    """Packs cut short, events on the edges of cells and of reach, before 1970, without key or user, and twice the same; the join's state has packs, not events."""
    edges = [(0, 5), (1, 0), (2, 21_600_000_000), (3, 21_600_000_001), (4, 43_199_999_999), (5, 43_200_000_000), (6, -1), (7, -21_600_000_000), (8, -21_600_000_001), (8, -21_600_000_001)]
    rows = spark.createDataFrame([(i, at, i % 3 if i != 4 else None, 7 if i != 1 else None) for i, at in [*edges, *((9 + j, j * 900_000_000) for j in range(60))]], "event_id long, at long, user_id long, k int")
    rows = rows.withColumn("ts", F.timestamp_micros("at"))
    want = _plain_pairs(rows)
    for most, held in ((1000, 500_000), (3, 500_000), (1000, 7), (1, 1)):
        monkeypatch.setattr(st, "PACK_EVENTS", most)
        monkeypatch.setattr(st, "HELD_EVENTS", held)
        assert sorted(map(tuple, st.candidate_pairs(rows).collect())) == want and len(want) > 100
    monkeypatch.undo()
    plan = st.candidate_pairs(rows)._jdf.queryExecution().optimizedPlan().toString()
    assert 0 <= plan.find("Join") < plan.find("MapInArrow")


def test_pairs_meet_over_files(spark, tmp_path):
    """Events that come in four files, one after another in time, give the pairs of the whole table, and past packs leave the state."""
    import os

    import pyarrow.parquet as pq

    (tmp_path / "events.parquet").mkdir()
    rows = pq.read_table(f"{SF}/events.parquet").sort_by("ts")
    step = -(-rows.num_rows // 4)
    for i in range(4):
        pq.write_table(rows.slice(i * step, step), f := tmp_path / "events.parquet" / f"part-{i}.parquet")
        os.utime(f, (1_700_000_000 + 60 * i,) * 2)
    got = st.run(st.candidate_pairs(st.event_stream(spark, str(tmp_path))))
    assert sorted(map(tuple, got.collect())) == _plain_pairs(st.event_batch(spark, SF))
    assert st.run.progress["stateOperators"][0]["numRowsTotal"] < rows.num_rows / 2


def test_scored_pairs_are_not_exchanged(spark, monkeypatch):
    """Profiles under the bound go to the pairs, whatever Spark's own threshold; larger ones are joined by exchanges and give the same scores."""
    from commlens.contract.engine import _profiles

    profiles, pairs = _profiles(spark, SF), st.candidate_pairs(st.event_batch(spark, SF))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plans, got = [], []
        for cells in (st.PROFILE_CELLS, 0):
            monkeypatch.setattr(st, "PROFILE_CELLS", cells)
            df = st.scored(pairs, profiles, (0.1, 0.2, 0.1, 0.3))
            plans.append(df._jdf.queryExecution().executedPlan().toString())
            got.append({(r.src, r.dst): r.p for r in df.collect()})
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    assert not any(f"hashpartitioning({c}#" in plans[0] for c in ("src_user", "dst_user")) and "hashpartitioning(src_user#" in plans[1]
    assert got[0] == pytest.approx(got[1], abs=1e-12) and len(got[0]) > 10


def test_workers_load_is_reported(planted):
    _, graph = planted
    cfg = ProfilerConfig(communities=3, topics=4, alpha=0.1, rho=0.1, sweeps=1, seed=3)
    unit = segmented.calibrated(graph, cfg, (0.5, 1.0))
    assert all(x >= 0 for x in unit) and sum(unit) > 0
    _, _, report = segmented.fit(graph, cfg, workers=2, unit=unit)
    rows = report.collect()
    assert {r.worker for r in rows} == {0, 1} and all(r.load > 0 and r.seconds > 0 for r in rows)


def test_study_runs_all_methods(planted):
    _, graph = planted
    got = study.run(graph, ProfilerConfig(communities=3, topics=4, sweeps=2, alpha=0.5, rho=0.5), folds=4, only=2, top=1, most=2)
    rows = study.table(got)
    assert {r["method"] for r in rows} == set(study.METHODS) and {r["measure"] for r in rows} >= {"conductance", "friendship_auc", "diffusion_auc", "perplexity", "maf1"}
