"""Queries of the general operators around the methods: scans, joins, aggregates, windows, functions, streams."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens import scratch
from commlens.contract import oracles as sql
from commlens.functions import expressions, udfs
from commlens.operators import counters
from commlens.sources import graphs
from commlens.sources.graphs import read
from commlens.streaming import events as st

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def query(oracle: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        _QUERIES[f.__name__] = f
        if oracle:
            _ORACLES[f.__name__] = sql.statement(oracle)
        return f

    return add


def _shared(spark: SparkSession) -> str:
    return scratch.new_path(spark, "io")


# Scans and sources


@query(" UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def scan_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [read(spark, sf_dir, t).agg(F.lit(t).alias("name"), F.count("*").alias("n")) for t in TABLES]
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def _round_trip(fmt: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = read(spark, sf_dir, "nation").select("n_nationkey", "n_name")
        path = _shared(spark)
        if fmt == "text":
            rows.select("n_name").write.text(path)
            return spark.read.text(path).select(F.col("value").alias("n_name"))
        rows.write.format(fmt).save(path)
        return spark.read.schema(rows.schema).format(fmt).load(path)

    run.__name__ = f"io_roundtrip_{fmt}"
    return run


for _fmt in ("csv", "json", "orc", "text"):
    query("SELECT n_name FROM nation" if _fmt == "text" else "SELECT n_nationkey, n_name FROM nation")(_round_trip(_fmt))


@query("SELECT tbin, count(*) AS n FROM docs WHERE tbin BETWEEN 12 AND 23 GROUP BY tbin")
def partition_pruned_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _shared(spark)
    graphs.commerce(spark, sf_dir).docs.repartition("tbin").write.partitionBy("tbin").parquet(path)
    return spark.read.parquet(path).where(F.col("tbin").between(12, 23)).groupBy("tbin").agg(F.count("*").alias("n"))


@query("SELECT user_id, c, count(*) AS n FROM assign GROUP BY ALL")
def bucketed_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Assignments stored in buckets of the user: counting by user needs no exchange."""
    from commlens.operators import counters

    name = f"assign_{uuid.uuid4().hex}"
    assign = counters.first_assignment(graphs.commerce(spark, sf_dir).docs, sql.C, sql.Z)
    assign.write.bucketBy(8, "user_id").sortBy("user_id").option("path", _shared(spark)).saveAsTable(name)
    return counters.user_community(spark.table(name))


@query(f"SELECT CAST({sql.hashed('i', 2)} // 64 % 4 AS INT) AS c, count(*) AS n FROM (SELECT row_number() OVER (ORDER BY c_custkey) - 1 AS i FROM customer) GROUP BY ALL")
def planted_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers by the planted community of the document that each is given in order of their keys."""
    from commlens.sources.planted_source import PlantedSource

    spark.dataSource.register(PlantedSource)
    customers = graphs.numbered(read(spark, sf_dir, "customer").select("c_custkey"), "c_custkey", "doc_id")
    return spark.read.format("planted").option("docs", customers.count()).load().join(customers, "doc_id").groupBy("c").agg(F.count("*").alias("n"))


# Projections and filters


@query("SELECT doc_id, n_chars, length(text) AS n, n_chars = length(text) AS same, CASE WHEN length(text) < 200 THEN 'short' WHEN length(text) < 2000 THEN 'middle' ELSE 'long' END AS size FROM documents")
def doc_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.length("text")
    return read(spark, sf_dir, "documents").select("doc_id", "n_chars", n.cast("bigint").alias("n"), (F.col("n_chars") == n).alias("same"), F.when(n < 200, "short").when(n < 2000, "middle").otherwise("long").alias("size"))


_PREDICATES = {
    "pred_in": (lambda: F.col("p_type").isin("PROMO", "SMALL"), "p_type IN ('PROMO', 'SMALL')"),
    "pred_like": (lambda: F.col("p_name").like("%ring%"), "p_name LIKE '%ring%'"),
    "pred_rlike": (lambda: F.col("p_brand").rlike("#1[0-4]$"), "regexp_matches(p_brand, '#1[0-4]$')"),
    "pred_between": (lambda: F.col("p_size").between(10, 20), "p_size BETWEEN 10 AND 20"),
    "pred_nullsafe": (lambda: F.nullif("p_size", F.lit(7)).eqNullSafe(F.lit(None)), "nullif(p_size, 7) IS NOT DISTINCT FROM NULL"),
}
for _name, (_cond, _text) in _PREDICATES.items():

    def _pred(spark: SparkSession, sf_dir: str, _c=_cond) -> DataFrame:
        return read(spark, sf_dir, "part").where(_c()).select("p_partkey", "p_name")

    _pred.__name__ = _name
    query(f"SELECT p_partkey, p_name FROM part WHERE {_text}")(_pred)


@query("SELECT doc_id, count(*) AS n_lines FROM bought GROUP BY doc_id HAVING count(*) >= 5")
def docs_min_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read(spark, sf_dir, "lineitem").join(read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey")
    return lines.groupBy(F.col("l_orderkey").alias("doc_id")).agg(F.count("*").alias("n_lines")).where("n_lines >= 5")


# Joins


@query("SELECT z, word, n, cf, round(n / cf, 6) AS share FROM tw JOIN vocab USING (word)")
def topic_word_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    g = graphs.commerce(spark, sf_dir)
    tw = counters.topic_word(counters.first_assignment(g.docs, sql.C, sql.Z), g.tokens)
    return tw.hint("merge").join(g.vocab().select("word", "cf"), "word").select("z", "word", "n", "cf", F.round(F.col("n") / F.col("cf"), 6).alias("share"))


@query("SELECT doc_id, round(p, 6) AS p FROM assign JOIN theta USING (c, z)")
def broadcast_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    assign = counters.first_assignment(graphs.commerce(spark, sf_dir).docs, sql.C, sql.Z)
    return assign.join(F.broadcast(counters.empirical_topics(assign)), ["c", "z"]).select("doc_id", F.round("p", 6).alias("p"))


@query("SELECT coalesce(f.user_id, c.c_custkey) AS user_id, coalesce(n, 0) AS n, c_acctbal FROM (SELECT src_user AS user_id, count(*) AS n FROM diffs GROUP BY ALL) f FULL JOIN customer c ON c.c_custkey = f.user_id")
def user_features_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = graphs.commerce(spark, sf_dir).diffs.groupBy(F.col("src_user").alias("user_id")).agg(F.count("*").alias("n"))
    c = read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_acctbal")
    return n.join(c, "user_id", "full_outer").select("user_id", F.coalesce("n", F.lit(0)).alias("n"), "c_acctbal")


@query("SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def users_with_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    return read(spark, sf_dir, "customer").join(orders, "c_custkey", "left_semi").select("c_custkey", "c_name")


@query(f"SELECT src, dst FROM friends WHERE {sql.hashed('(src * 1000003 + dst) % 2147483647', 5)} // 128 % 10 <> 0")
def train_minus_test(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import measures

    links = graphs.commerce(spark, sf_dir).friends
    test = links.where(measures.fold_of(10, 5, F.col("src"), F.col("dst")) == 0)
    return links.join(test, ["src", "dst"], "left_anti")


@query("SELECT count(*) AS n FROM bought a JOIN bought b ON a.l_partkey = b.l_partkey AND a.user_id <> b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 7 DAY")
def range_diffs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All earlier orders of the same part within a week: days are cut into weeks, and a week meets itself and the one before."""
    lines = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey")
    rows = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate").join(lines, "o_orderkey").withColumn("day", F.datediff("o_orderdate", F.lit("1990-01-01").cast("date")))
    late = rows.select("l_partkey", F.col("o_custkey").alias("ua"), F.col("day").alias("da"), F.explode(F.array(F.floor(F.col("day") / 7), F.floor(F.col("day") / 7) - 1)).alias("week"))
    early = rows.select("l_partkey", F.col("o_custkey").alias("ub"), F.col("day").alias("db"), F.floor(F.col("day") / 7).alias("week"))
    return late.join(early, ["l_partkey", "week"]).where("ua <> ub AND db < da AND db >= da - 7").agg(F.count("*").alias("n"))


@query("SELECT o_orderkey, p FROM (SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS p FROM orders)")
def asof_prev_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").select("o_orderkey", F.lag("o_orderkey").over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")).alias("p"))


@query("SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON json_extract_string(a.props, '$.k') = json_extract_string(b.props, '$.k') AND a.user_id <> b.user_id AND b.ts < a.ts AND b.ts >= a.ts - INTERVAL 1 HOUR")
def coactive_friends(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = st.event_batch(spark, sf_dir).select("user_id", "k", F.unix_micros("ts").alias("t"))
    hour = 3_600_000_000
    cell = F.floor(F.col("t") / hour)
    a = rows.select(F.col("user_id").alias("src"), "k", F.col("t").alias("ta"), F.explode(F.array(cell, cell - 1)).alias("cell"))
    b = rows.select(F.col("user_id").alias("dst"), "k", F.col("t").alias("tb"), cell.alias("cell"))
    return a.join(b, ["k", "cell"]).where((F.col("src") != F.col("dst")) & (F.col("tb") < F.col("ta")) & (F.col("tb") >= F.col("ta") - hour)).select("src", "dst").distinct()


@query("SELECT c, z FROM (SELECT DISTINCT c FROM assign) CROSS JOIN (SELECT DISTINCT z FROM assign)")
def profile_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells of a profile: each community beside each topic that documents are assigned to."""
    assign = counters.first_assignment(graphs.commerce(spark, sf_dir).docs, sql.C, sql.Z)
    return assign.select("c").distinct().crossJoin(assign.select("z").distinct())


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM customer JOIN orders ON o_custkey = c_custkey) WHERE k <= 2")
def lateral_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers, orders = read(spark, sf_dir, "customer"), read(spark, sf_dir, "orders")
    best = orders.where(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return customers.lateralJoin(best).select("c_custkey", "o_orderkey")


@query("SELECT word, CAST(sum(cnt * df) AS BIGINT) AS n FROM tokens JOIN vocab USING (word) GROUP BY word")
def salted_word_join(spark: SparkSession, sf_dir: str, salts: int = 8) -> DataFrame:
    """Hot words are dealt out over salts; the small side is repeated for each."""
    g = graphs.commerce(spark, sf_dir)
    tokens = g.tokens.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("int"))
    words = g.vocab().select("word", "df").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    part = tokens.hint("merge").join(words, ["word", "salt"]).groupBy("word", "salt").agg(F.sum(F.col("cnt") * F.col("df")).alias("n"))
    return part.groupBy("word").agg(F.sum("n").alias("n"))


# Aggregation


@query("SELECT count(DISTINCT src_user) AS users, count(DISTINCT src_doc) AS docs FROM diffs")
def distinct_diffusers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.commerce(spark, sf_dir).diffs.agg(F.countDistinct("src_user").alias("users"), F.countDistinct("src_doc").alias("docs"))


@query("SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 100000) AS n_large, round(sum(o_totalprice) FILTER (WHERE o_orderstatus = 'F'), 2) AS s FROM orders GROUP BY ALL")
def agg_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    read(spark, sf_dir, "orders").createOrReplaceTempView("orders_v")
    return spark.sql("SELECT o_orderpriority, count(*) FILTER (WHERE o_totalprice > 100000) AS n_large, round(sum(o_totalprice) FILTER (WHERE o_orderstatus = 'F'), 2) AS s FROM orders_v GROUP BY ALL")


@query("SELECT n_regionkey, c_mktsegment, year(o_orderdate) AS y, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY CUBE (n_regionkey, c_mktsegment, year(o_orderdate))")
def counts_cube_nation_segment_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read(spark, sf_dir, "orders").join(read(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(read(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return o.select("n_regionkey", "c_mktsegment", F.year("o_orderdate").cast("bigint").alias("y")).cube("n_regionkey", "c_mktsegment", "y").agg(F.count("*").alias("n"))


def _eta_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    g = graphs.commerce(spark, sf_dir)
    a = counters.first_assignment(g.docs, sql.C, sql.Z)
    return g.diffs.join(a.select(F.col("doc_id").alias("src_doc"), "c", "z"), "src_doc").join(a.select(F.col("doc_id").alias("dst_doc"), F.col("c").alias("c2")), "dst_doc").select("c", "c2", "z")


@query("SELECT c, c2, z, count(*) AS n FROM lk GROUP BY ROLLUP (c, c2, z)")
def eta_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _eta_counts(spark, sf_dir).rollup("c", "c2", "z").agg(F.count("*").alias("n"))


@query("SELECT c, c2, z, count(*) AS n FROM lk GROUP BY GROUPING SETS ((c, c2, z), (c, c2), (z))")
def eta_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _eta_counts(spark, sf_dir).groupingSets([["c", "c2", "z"], ["c", "c2"], ["z"]], "c", "c2", "z").agg(F.count("*").alias("n"))


@query("SELECT c, " + ", ".join(f"round(coalesce(sum(p) FILTER (WHERE z = {z}), 0), 6) AS z{z}" for z in range(sql.Z)) + " FROM theta GROUP BY c")
def theta_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _theta(spark, sf_dir).groupBy("c").pivot("z", list(range(sql.Z))).agg(F.round(F.sum("p"), 6)).fillna(0.0).select("c", *(F.col(str(z)).alias(f"z{z}") for z in range(sql.Z)))


def _theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    return counters.empirical_topics(counters.first_assignment(graphs.commerce(spark, sf_dir).docs, sql.C, sql.Z))


@query("SELECT cs.c, 'z' || zs.z AS topic, round(coalesce(p, 0), 6) AS p FROM (SELECT DISTINCT c FROM theta) cs CROSS JOIN zs LEFT JOIN theta t ON t.c = cs.c AND t.z = zs.z")
def theta_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return theta_pivot(spark, sf_dir).unpivot("c", [f"z{z}" for z in range(sql.Z)], "topic", "p")


@query("SELECT round(corr(o_totalprice, n), 6) AS corr, round(regr_slope(o_totalprice, n), 3) AS slope, round(regr_r2(o_totalprice, n), 6) AS r2, round(stddev_samp(o_totalprice), 3) AS sd, round(quantile_cont(o_totalprice, 0.5), 3) AS median FROM orders JOIN (SELECT l_orderkey AS o_orderkey, count(*) AS n FROM lineitem GROUP BY ALL) USING (o_orderkey)")
def stats_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = read(spark, sf_dir, "lineitem").groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.count("*").alias("n"))
    o = read(spark, sf_dir, "orders").join(n, "o_orderkey")
    y, x = F.col("o_totalprice"), F.col("n")
    return o.agg(F.round(F.corr(y, x), 6).alias("corr"), F.round(F.regr_slope(y, x), 3).alias("slope"), F.round(F.regr_r2(y, x), 6).alias("r2"), F.round(F.stddev_samp(y), 3).alias("sd"), F.round(F.percentile(y, 0.5), 3).alias("median"))


@query("SELECT user_id, CAST(arg_max(z, (n, -z)) AS INT) AS z FROM (SELECT user_id, z, count(*) AS n FROM assign GROUP BY ALL) GROUP BY user_id")
def user_top_topic(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    n = counters.first_assignment(graphs.commerce(spark, sf_dir).docs, sql.C, sql.Z).groupBy("user_id", "z").agg(F.count("*").alias("n"))
    return n.groupBy("user_id").agg(F.max_by("z", F.struct("n", -F.col("z"))).alias("z"))


@query()
def approx_sketches(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read(spark, sf_dir, "orders")
    return o.agg(F.approx_count_distinct("o_custkey", 0.02).alias("users"), F.approx_percentile("o_totalprice", 0.5, 1000).alias("median"), F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey")).alias("hll"))


@query("SELECT doc_id, string_agg(word || ':' || cnt, ' ' ORDER BY word) AS bag FROM tokens GROUP BY doc_id")
def user_bow_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graphs.commerce(spark, sf_dir).tokens.groupBy("doc_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("word", "cnt")))).alias("m"))
    return g.select("doc_id", F.array_join(F.transform(F.map_entries("m"), lambda e: F.concat_ws(":", e["key"], e["value"].cast("string"))), " ").alias("bag"))


# Windows and sorting

_RANKS = {"row_number": "row_number()", "rank": "rank()", "dense_rank": "dense_rank()", "ntile": "ntile(4)", "percent_rank": "percent_rank()", "cume_dist": "cume_dist()"}
for _name, _text in _RANKS.items():

    def _rank(spark: SparkSession, sf_dir: str, _n=_name) -> DataFrame:
        over = W.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
        f = F.ntile(4) if _n == "ntile" else getattr(F, _n)()
        value = F.round(f.over(over), 9) if _n in ("percent_rank", "cume_dist") else f.over(over).cast("bigint")
        return read(spark, sf_dir, "customer").select("c_custkey", value.alias("v"))

    _rank.__name__ = f"rank_{_name}"
    _v = f"round({_text} OVER w, 9)" if _name in ("percent_rank", "cume_dist") else f"CAST({_text} OVER w AS BIGINT)"
    query(f"SELECT c_custkey, {_v} AS v FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey)")(_rank)


@query("SELECT o_orderkey, lag(o_orderkey) OVER w AS a, lead(o_orderkey, 2) OVER w AS b, first_value(o_orderkey) OVER w AS f, nth_value(o_orderkey, 2) OVER w AS n FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def lag_diffs(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    k = "o_orderkey"
    return read(spark, sf_dir, "orders").select(k, F.lag(k).over(w).alias("a"), F.lead(k, 2).over(w).alias("b"), F.first_value(k).over(w).alias("f"), F.nth_value(k, 2).over(w).alias("n"))


@query("SELECT c, z, round(sum(p) OVER (PARTITION BY c ORDER BY z ROWS UNBOUNDED PRECEDING), 6) AS upto FROM theta")
def inverse_cdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _theta(spark, sf_dir).select("c", "z", F.round(F.sum("p").over(W.partitionBy("c").orderBy("z").rowsBetween(W.unboundedPreceding, 0)), 6).alias("upto"))


@query("SELECT z, tbin, round(avg(n) OVER (PARTITION BY z ORDER BY tbin ROWS UNBOUNDED PRECEDING), 6) AS mean FROM tt")
def map_running_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _popularity(spark, sf_dir).select("z", "tbin", F.round(F.avg("n").over(W.partitionBy("z").orderBy("tbin").rowsBetween(W.unboundedPreceding, 0)), 6).alias("mean"))


def _popularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    g = graphs.commerce(spark, sf_dir)
    return counters.topic_time(counters.first_assignment(g.docs, sql.C, sql.Z), g.docs)


@query("SELECT z, tbin, CAST(sum(n) OVER (PARTITION BY z ORDER BY tbin RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS n FROM tt")
def rolling_popularity_30d(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _popularity(spark, sf_dir).select("z", "tbin", F.sum("n").over(W.partitionBy("z").orderBy("tbin").rangeBetween(-2, 0)).alias("n"))


@query("SELECT user_id, c, CAST(k AS INT) AS k FROM (SELECT user_id, c, row_number() OVER (PARTITION BY user_id ORDER BY round(p, 12) DESC, c) AS k FROM pi) WHERE k <= 2")
def top_comms(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import counters

    pi = counters.empirical_membership(counters.first_assignment(graphs.commerce(spark, sf_dir).docs, sql.C, sql.Z))
    return pi.select("user_id", "c", F.row_number().over(W.partitionBy("user_id").orderBy(F.round("p", 12).desc(), "c")).alias("k")).where("k <= 2")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")
def limit_offset(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20)


# Set operations

_DEDGES = "SELECT DISTINCT src_user AS src, dst_user AS dst FROM diffs"
for _name, _text in (("union", f"SELECT src, dst FROM friends UNION {_DEDGES}"), ("intersect", f"SELECT src, dst FROM friends INTERSECT {_DEDGES}"), ("except", f"SELECT src, dst FROM friends EXCEPT {_DEDGES}")):

    def _set(spark: SparkSession, sf_dir: str, _n=_name) -> DataFrame:
        g = graphs.commerce(spark, sf_dir)
        b = g.diffs.select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst"))
        return {"union": lambda: g.friends.unionByName(b).distinct(), "intersect": lambda: g.friends.intersect(b), "except": lambda: g.friends.subtract(b)}[_n]()

    _set.__name__ = f"edges_{_name}"
    query(_text)(_set)


# Functions


@query("SELECT p_partkey, upper(p_name) AS a, replace(p_name, ' ', '_') AS b, substr(p_brand, 7) AS c, length(p_name) AS d, levenshtein(p_name, 'red ring') AS e, md5(p_name) AS f, trim('  ' || p_type || ' ') AS g, regexp_extract(p_brand, '([0-9]+)', 1) AS h, p_name || '/' || p_type AS i, string_split(p_name, ' ')[1] AS j FROM part")
def str_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("p_name")
    return read(spark, sf_dir, "part").select(
        "p_partkey", F.upper(n).alias("a"), F.translate(n, " ", "_").alias("b"), F.expr("substr(p_brand, 7)").alias("c"), F.length(n).cast("bigint").alias("d"), F.levenshtein(n, F.lit("red ring")).cast("bigint").alias("e"),
        F.md5(n.cast("binary")).alias("f"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("g"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("h"), F.concat_ws("/", n, "p_type").alias("i"), F.split(n, " ")[0].alias("j"),
    )


@query("SELECT page_id, regexp_extract(url, '://([^/?#:]+)', 1) AS host, TRY_CAST(regexp_extract(url, '/([0-9]+)(?:[?#]|$)', 1) AS BIGINT) AS doc_id FROM pages")
def page_doc_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.regexp_extract("url", r"/([0-9]+)(?:[?#]|$)", 1).try_cast("bigint").alias("doc_id"))


@query("SELECT page_id, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n FROM pages")
def page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("bigint").alias("n"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate) AS m, year(o_orderdate) AS y, quarter(o_orderdate) AS q, dayofyear(o_orderdate) AS d, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) AS n, CAST(epoch(o_orderdate) AS BIGINT) AS u FROM orders")
def date_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = F.col("o_orderdate")
    return read(spark, sf_dir, "orders").select("o_orderkey", F.date_trunc("month", t).cast("timestamp_ntz").alias("m"), *(f(t).cast("bigint").alias(n) for n, f in (("y", F.year), ("q", F.quarter), ("d", F.dayofyear))), F.datediff(t, F.lit("1995-01-01").cast("date")).cast("bigint").alias("n"), F.unix_seconds(t.cast("timestamp")).alias("u"))


@query(f"SELECT p_partkey, round({sql.sigmoid('p_size / 10.0 - 2')}, 9) AS s, round({sql.psi('p_size / 10.0', '0.2')}, 9) AS l, round({sql.pg_mean('p_size / 10.0')}, 9) AS g FROM part")
def math_sigmoid(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = F.col("p_size") / 10.0
    return read(spark, sf_dir, "part").select("p_partkey", F.round(expressions.sigmoid(x - 2), 9).alias("s"), F.round(expressions.log_psi(x, F.lit(0.2)), 9).alias("l"), F.round(expressions.pg_mean(x), 9).alias("g"))


@query(f"SELECT p_partkey, round({sql.sigmoid('p_size / 10.0 - 2')}, 9) AS s, round({sql.pg_mean('p_size / 10.0')}, 9) AS g FROM part")
def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    expressions.register(spark)
    read(spark, sf_dir, "part").createOrReplaceTempView("part_v")
    return spark.sql("SELECT p_partkey, round(sigmoid(p_size / 10.0D - 2), 9) AS s, round(pg_mean(p_size / 10.0D), 9) AS g FROM part_v")


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top, len(embedding[1:8]) AS head FROM embeddings")
def arr_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = F.transform("embedding", lambda x: x.cast("double"))
    return read(spark, sf_dir, "embeddings").select(
        "vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("pos"),
        F.round(F.array_max(e), 6).alias("top"), F.size(F.slice("embedding", 1, 8)).cast("bigint").alias("head"),
    )


@query("SELECT event_type, CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY ALL")
def json_event_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int")["k"].alias("k")).groupBy("event_type", "k").agg(F.count("*").alias("n"))


@query("SELECT p_partkey, round(lgamma(p_size + 0.5), 9) AS v FROM part")
def lgamma_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "part").select("p_partkey", F.round(udfs.log_gamma(F.col("p_size") + 0.5), 9).alias("v"))


@query()
def pg_exact_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Means of exact draws, one for each ordered line at a score that its part gives, beside the closed form."""
    rows = read(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("id"), (F.pmod("l_partkey", F.lit(8)) * 0.75).alias("b"))
    drawn = rows.select("b", udfs.pg_draw(F.col("b"), F.col("id"), 5).alias("x"))
    return drawn.groupBy("b").agg(F.avg("x").alias("mean"), F.first(expressions.pg_mean(F.col("b"))).alias("expected"), F.count("*").alias("n"))


@query("SELECT c, round(max(p) + ln(sum(exp(p - m))), 6) - round(max(p) - any_value(m), 6) AS v FROM (SELECT c, p, max(p) OVER (PARTITION BY c) AS m FROM theta) GROUP BY c")
def logsumexp_udaf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _theta(spark, sf_dir).groupBy("c").agg(udfs.logsumexp_udaf("p").alias("v")).select("c", F.round("v", 6).alias("v"))


@query("SELECT p_partkey, CAST(generate_subscripts(w, 1) - 1 AS INT) AS pos, unnest(w) AS token FROM (SELECT p_partkey, string_split(lower(p_name), ' ') AS w FROM part)")
def tokenize_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    read(spark, sf_dir, "part").createOrReplaceTempView("part_v")
    return spark.sql("SELECT p_partkey, pos, token FROM part_v, LATERAL tokenize(p_name)")


@query("SELECT \"end\", id, count(*) AS n FROM (SELECT 'src' AS \"end\", src AS id FROM friends UNION ALL SELECT 'dst', dst FROM friends) GROUP BY ALL")
def expand_links_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    graphs.commerce(spark, sf_dir).friends.createOrReplaceTempView("friends_v")
    return spark.sql("SELECT end, id, count(*) AS n FROM friends_v, LATERAL expand_link(src, dst) GROUP BY end, id")


@query(f"SELECT o_orderkey FROM orders WHERE {sql.uniform('o_orderkey', 77)} < 0.25")
def sample_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "orders").where(expressions.uniform(F.col("o_orderkey"), 77) < 0.25).select("o_orderkey")


# Streams


@query("SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, CAST(CAST(json_extract_string(props, '$.k') AS INT) % 8 AS INT) AS z, count(*) AS n FROM events GROUP BY ALL")
def stream_popularity_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _plain(st.run(st.popularity_tumbling(st.event_stream(spark, sf_dir)), "complete"))


def _plain(df: DataFrame) -> DataFrame:
    return df.select(*(F.col(c).cast("timestamp_ntz").alias(c) if t == "timestamp" else F.col(c) for c, t in df.dtypes))


@query("SELECT CAST(to_timestamp((epoch(ts)::BIGINT // 21600 - o) * 21600) AT TIME ZONE 'UTC' AS TIMESTAMP) AS start, CAST(CAST(json_extract_string(props, '$.k') AS INT) % 8 AS INT) AS z, count(*) AS n FROM (SELECT *, floor(epoch(ts))::BIGINT AS e FROM events) CROSS JOIN (SELECT range AS o FROM range(4)) GROUP BY ALL".replace("epoch(ts)::BIGINT", "e"))
def stream_popularity_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _plain(st.run(st.popularity_sliding(st.event_stream(spark, sf_dir)), "complete"))


@query("""SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 12 HOUR AS "end", count(*) AS n FROM (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts > lag(ts) OVER w + INTERVAL 12 HOUR THEN 1 ELSE 0 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))) GROUP BY user_id, s""")
def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _plain(st.run(st.user_sessions(st.event_stream(spark, sf_dir)), "complete"))


@query("SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON json_extract_string(a.props, '$.k') = json_extract_string(b.props, '$.k') AND a.user_id <> b.user_id AND b.ts < a.ts AND a.ts <= b.ts + INTERVAL 6 HOUR")
def stream_diffusion_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.run(st.diffusion_links(st.event_stream(spark, sf_dir)))


@query("SELECT DISTINCT event_id, user_id FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.run(st.deduplicated(st.event_stream(spark, sf_dir))).select("event_id", "user_id")


@query()
def stream_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rounded before the stream's rows are written, which halves them."""
    return st.run(st.scored(st.candidate_pairs(st.event_stream(spark, sf_dir)), _profiles(spark, sf_dir), sql.NU).select("src", "dst", F.round("p", 6).alias("p")))


def _profiles(spark: SparkSession, sf_dir: str) -> dict:
    graph = graphs.prepared(spark, sf_dir, "activity")
    return st.static_profiles(graph, counters.first_assignment(graph.docs, sql.C, sql.Z), sql.C, sql.Z)


@query("SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON json_extract_string(a.props, '$.k') = json_extract_string(b.props, '$.k') AND a.user_id <> b.user_id AND b.ts < a.ts AND a.ts <= b.ts + INTERVAL 6 HOUR")
def stream_outer_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return st.run(st.diffusion_links(st.event_stream(spark, sf_dir), outer=True)).where("src IS NOT NULL")


def queries() -> dict[str, Query]:
    return _QUERIES


def oracle_sql() -> dict[str, str]:
    return _ORACLES
