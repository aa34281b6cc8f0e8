"""Registered queries against DuckDB on the smallest tables, and plans."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
SOME = [
    "graph_stats_commerce", "graph_stats_activity", "vocab_commerce", "user_features", "topic_scores_text", "comm_scores_friend", "diffusion_prob", "draw_gumbel", "rank_communities", "conductance_top5", "auc_friend",
    "maf_at_k", "perplexity_doc", "agg_diffusion_profile", "range_diffs", "coactive_friends", "salted_word_join", "eta_grouping_sets", "lateral_topk", "edges_intersect", "stream_sessions", "stream_diffusion_links", "sql_functions",
]


@pytest.fixture(scope="module")
def oracle():
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    return con


def close(a, b):
    return a == b or isinstance(a, float) and isinstance(b, float) and abs(a - b) <= 2e-6 * max(1.0, abs(a))


@pytest.mark.parametrize("name", SOME)
def test_matches_oracle(spark, oracle, name):
    df = entry.queries()[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted((tuple(r[c] for c in columns) for r in df.collect()), key=repr)
    cursor = oracle.execute(entry.oracle_sql()[name])
    names = [d[0] for d in cursor.description]
    want = sorted((tuple(r[names.index(c)] for c in columns) for r in cursor.fetchall()), key=repr)
    assert sorted(names) == columns and len(got) == len(want)
    assert all(close(x, y) for a, b in zip(got, want, strict=True) for x, y in zip(a, b, strict=True))


@pytest.mark.parametrize("name", ["knapsack_pack", "balance_report", "planted_source", "approx_sketches", "auc_diffusion", "stream_score"])
def test_runs(spark, name):
    assert entry.queries()[name](spark, SF).count() > 0


def test_entry_ranks(spark):
    assert entry.entry(spark).count() == 6


def test_exact_draws_have_the_closed_mean(spark):
    for r in entry.queries()["pg_exact_udf"](spark, SF).collect():
        assert abs(r["mean"] - r["expected"]) < 0.02


def test_no_cartesian_product(spark):
    for name in ("friends_commerce", "topic_scores_text", "comm_scores_friend", "range_diffs"):
        plan = entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in plan, name


def test_scans_are_pruned(spark):
    plan = entry.queries()["pred_between"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(p_size)" in plan and "p_retailprice" not in plan.split("ReadSchema")[1]


def test_rising_factorial_reads_parts(spark, oracle):
    test_matches_oracle(spark, oracle, "log_rising_factorial")
    assert any("part.parquet" in f for f in entry.queries()["log_rising_factorial"](spark, SF).inputFiles())


def test_exact_draws_read_lines(spark):
    got = entry.queries()["pg_exact_udf"](spark, SF)
    assert any("lineitem.parquet" in f for f in got.inputFiles())
    assert got.agg(F.sum("n")).first()[0] == spark.read.parquet(f"{SF}/lineitem.parquet").count()


def test_planted_source_serves_customers(spark, oracle):
    test_matches_oracle(spark, oracle, "planted_source")
    assert entry.queries()["planted_source"](spark, SF).agg(F.sum("n")).first()[0] == spark.read.parquet(f"{SF}/customer.parquet").count()


def test_profile_grid_reads_orders(spark, oracle):
    test_matches_oracle(spark, oracle, "profile_grid")
    assert any("orders.parquet" in f for f in entry.queries()["profile_grid"](spark, SF).inputFiles())


def test_stream_pairs_meet_in_cells_of_time(spark):
    """Both stream joins meet by key and stretch of time, not by key alone, and a stream ends when its input does."""
    import inspect

    from commlens.streaming import events as st

    rows = st.event_batch(spark, SF)
    for pairs in (st.diffusion_links(rows), st.diffusion_links(rows, outer=True), st.candidate_pairs(rows)):
        joins = [x for x in pairs._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join" in x]
        assert joins and all("(cell#" in x.replace("(cell_b#", "(cell#") for x in joins)
    assert inspect.signature(st.run).parameters["timeout"].default is None
    lone = st.diffusion_links(rows, outer=True).where("src IS NULL")
    assert lone.count() == rows.join(st.diffusion_links(rows), rows.event_id == F.col("dst"), "left_anti").count() == lone.select("dst").distinct().count()


def test_mean_grid_reads_parts(spark, oracle):
    test_matches_oracle(spark, oracle, "pg_mean_grid")
    assert any("part.parquet" in f for f in entry.queries()["pg_mean_grid"](spark, SF).inputFiles())


@pytest.mark.parametrize("name", ["lda_step_mixtures", "lda_step_topics", "topiclink_step_mixtures"])
def test_mixtures_move_tokens_once(spark, oracle, name):
    """Tokens and links are exchanged by document, not by topic or word with it."""
    test_matches_oracle(spark, oracle, name)
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    moved = [x.split("hashpartitioning(")[1] for x in plan.splitlines() if "hashpartitioning(doc_id#" in x or "hashpartitioning(src_doc#" in x]
    assert moved and not any(", word#" in x or ", z#" in x or ", dst_doc#" in x for x in moved)


def test_word_perplexity_has_a_row_per_token(spark, oracle):
    """No exchange by document and word: a token stays one row, whatever the topics."""
    test_matches_oracle(spark, oracle, "perplexity_word")
    plan = entry.queries()["perplexity_word"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert not any("hashpartitioning(doc_id#" in x and ", word#" in x for x in plan.splitlines())


@pytest.mark.parametrize("name", ["score_pairs", "auc_diffusion"])
def test_scored_links_are_one_row_each(spark, oracle, name):
    """No exchange by a link's documents with a topic or community, nor by document and topic."""
    if name == "score_pairs":
        test_matches_oracle(spark, oracle, name)
    plan = entry.queries()[name](spark, SF)._jdf.queryExecution().executedPlan().toString()
    moved = [x.split("hashpartitioning(")[1].split(")")[0] for x in plan.splitlines() if "hashpartitioning(" in x]
    assert moved and not any("link#" in x or "_doc#" in x and "," in x.replace(", 4", "").replace(", ENSURE", "") and ("z#" in x or "c2#" in x) or "doc_id#" in x and "z#" in x for x in moved)


def test_scored_links_by_joins_agree(spark):
    from commlens.contract.registry import NU, C, Slice, Z
    from commlens.operators import diffusion

    s = Slice(spark, SF)
    topics = diffusion.topic_posterior(s.g.tokens, s.phi_s, Z, s.pi.selectExpr("user_id", "c AS z", "p AS w"))
    parts = (s.g.diffs, topics, s.pi, s.tensor, s.pop(), s.features, NU)
    for active in (("community", "topic", "individual"), ("community",), ("topic",)):
        wide = {(r.src_doc, r.dst_doc): r.p for r in diffusion.wide_score_pairs(*parts, active).collect()}
        got = {(r.src_doc, r.dst_doc): r.p for r in diffusion.score_pairs(*parts, Z, active).collect()}
        assert got == pytest.approx(wide, abs=1e-9) and got
