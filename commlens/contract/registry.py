"""Queries of the profiling engine and the DuckDB statements they are compared with.

All model queries start from the commerce graph and the same hashed first assignment (6 communities, 8 topics), so that every step of a
sweep can be compared value by value. Doubles are rounded to six digits on both sides.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens.contract import oracles as sql
from commlens.contract.oracles import ALPHA, BETA, NU, RHO, C, Z
from commlens.functions import text
from commlens.functions.expressions import hashed, log_rising, pg_mean, sigmoid, uniform
from commlens.operators import counters, factors, measures, partition, ranking, sampling, views
from commlens.plans import baselines
from commlens.sources import graphs

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_ORACLES: dict[str, str] = {}


def query(oracle: str | None = None) -> Callable[[Query], Query]:
    """Registers a query under its function's name; ``oracle`` is a final SELECT over the expressions of ``oracles``."""

    def add(f: Query) -> Query:
        _QUERIES[f.__name__] = f
        if oracle:
            _ORACLES[f.__name__] = sql.statement(oracle)
        return f

    return add


def named(name: str, f: Query, oracle: str | None = None) -> None:
    f.__name__ = name
    query(oracle)(f)


def r6(c) -> F.Column:
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c.cast("double"), 6)


class Slice:
    """The commerce graph with its first assignment and what the model derives from it."""

    def __init__(self, spark: SparkSession, sf_dir: str) -> None:
        self.g = graphs.prepared(spark, sf_dir)
        self.assign = counters.first_assignment(self.g.docs, C, Z)

    @property
    def pi(self) -> DataFrame:
        return counters.empirical_membership(self.assign)

    @property
    def theta(self) -> DataFrame:
        return counters.empirical_topics(self.assign)

    def eta(self, norm: str = "per_community") -> DataFrame:
        return counters.eta(self.g.diffs, self.assign, norm)

    @property
    def tensor(self) -> DataFrame:
        return factors.tensor(self.theta, self.eta())

    def pop(self, scale: str = "share") -> DataFrame:
        return counters.popularity(counters.topic_time(self.assign, self.g.docs), scale)

    @property
    def features(self) -> DataFrame:
        return counters.user_features(self.g.docs, self.g.friends, self.g.diffs)

    @property
    def links(self) -> DataFrame:
        return factors.link_topics(self.g.diffs, self.assign)

    def scored(self, active: tuple[str, ...] = ("community", "topic", "individual")) -> DataFrame:
        return factors.diffusion_scores(self.links, self.pi, self.tensor, self.pop(), self.features, NU, active, cells=C * C * Z)

    @property
    def theta_s(self) -> DataFrame:
        return counters.smoothed_topics(counters.community_topic(self.assign), C, Z, ALPHA)

    @property
    def phi_s(self) -> DataFrame:
        return counters.smoothed_words(counters.topic_word(self.assign, self.g.tokens), self.g.tokens.select("word").distinct(), BETA)

    @property
    def pi_s(self) -> DataFrame:
        return counters.smoothed_membership(counters.user_community(self.assign), C, RHO)

    def ranked(self, top: int | None = None, normalise: bool = False) -> DataFrame:
        words = self.g.tokens.select(F.col("word").alias("q_id"), "word").distinct()
        return ranking.rank_communities(words, self.phi_s, ranking.reach(self.eta(), self.theta_s), top, normalise)

    def topic_scores(self) -> DataFrame:
        n_words = self.g.tokens.select("word").distinct().count()
        return sampling.topic_text_scores(self.assign, self.g.tokens, self.g.docs, C, Z, ALPHA, BETA, n_words)

    def sent(self) -> tuple:
        """Tensor and popularity as arrays."""
        bins = (self.g.docs.agg(F.max("tbin")).first()[0] or 0) + 1
        return sampling.sent(self.tensor, (Z, C, C), ["z", "c", "c2"], "g"), sampling.sent(self.pop(), (Z, bins), ["z", "tbin"], "pop")

    def topic_scores_full(self) -> DataFrame:
        terms = sampling.topic_link_arrays(self.g.diffs, self.assign, self.pi, *self.sent(), self.features, NU, ("community", "topic", "individual"))
        n_words = self.g.tokens.select("word").distinct().count()
        return sampling.spread(sampling.plus(sampling.topic_text_arrays(self.assign, self.g.tokens, self.g.docs, C, Z, ALPHA, BETA, n_words), terms), "z")

    def community_scores(self) -> DataFrame:
        return sampling.community_text_scores(self.assign, C, Z, ALPHA, RHO)

    def community_scores_full(self) -> DataFrame:
        friends = sampling.community_friend_arrays(self.assign, self.g.friends, self.pi, C)
        links = sampling.community_link_arrays(self.g.diffs, self.assign, self.pi, *self.sent(), self.features, NU, ("community", "topic", "individual"))
        return sampling.spread(sampling.plus(sampling.plus(sampling.community_text_arrays(self.assign, C, Z, ALPHA, RHO), friends), links), "c")


# Graph

_STATS = "count(DISTINCT user_id) AS n_users, count(*) AS n_docs, CAST(sum(n_tok) AS BIGINT) AS n_tokens"


@query("SELECT (SELECT count(DISTINCT user_id) FROM docs) AS n_users, (SELECT count(*) FROM docs) AS n_docs, (SELECT CAST(sum(n_tok) AS BIGINT) FROM docs) AS n_tokens, (SELECT count(*) FROM friends) AS n_friends, (SELECT count(*) FROM diffs) AS n_diffs, (SELECT count(*) FROM vocab) AS n_words")
def graph_stats_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.statistics(graphs.prepared(spark, sf_dir))


@query()
def graph_stats_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.corpus_statistics(spark, sf_dir)


for _name in ("web", "activity", "dialog"):
    named(f"graph_stats_{_name}", lambda spark, sf_dir, _make=_name: graphs.statistics(graphs.prepared(spark, sf_dir, _make)))

_ORACLES["graph_stats_activity"] = """
WITH e AS (SELECT event_id, user_id, ts, event_type, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events),
m AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) > 43200000000 THEN event_id END AS f FROM e WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, last_value(f IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS doc_id FROM m),
l AS (SELECT *, lag(doc_id) OVER w AS d2, lag(user_id) OVER w AS u2, epoch_us(ts) - epoch_us(lag(ts) OVER w) AS gap FROM s WINDOW w AS (PARTITION BY k ORDER BY ts, event_id))
SELECT count(DISTINCT user_id) AS n_users, count(DISTINCT doc_id) AS n_docs, CAST(2 * count(*) AS BIGINT) AS n_tokens,
 (SELECT count(*) FROM (SELECT DISTINCT user_id, u2 FROM l WHERE user_id <> u2 AND gap <= 3600000000)) AS n_friends,
 (SELECT count(*) FROM (SELECT DISTINCT doc_id, d2, user_id, u2, dayofmonth(ts) FROM l WHERE user_id <> u2 AND gap <= 21600000000)) AS n_diffs,
 (SELECT count(*) FROM (SELECT DISTINCT event_type FROM e UNION SELECT DISTINCT CAST(k AS VARCHAR) FROM e)) AS n_words FROM s"""


_ORACLES["graph_stats_corpus"] = r"""
WITH w AS (SELECT doc_id, concat_ws(':', source, lang) AS u, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS word FROM documents),
t AS (SELECT * FROM w WHERE length(word) >= 3), s AS (SELECT doc_id, u, count(*) AS n FROM t GROUP BY ALL HAVING count(*) >= 2),
l AS (SELECT DISTINCT doc_id, u, line FROM (SELECT doc_id, concat_ws(':', source, lang) AS u, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 30),
p AS (SELECT DISTINCT a.doc_id AS d1, b.doc_id AS d2, a.u AS u1, b.u AS u2 FROM l a JOIN l b ON a.line = b.line AND a.doc_id > b.doc_id)
SELECT (SELECT count(DISTINCT u) FROM s) AS n_users, (SELECT count(*) FROM s) AS n_docs, (SELECT CAST(sum(n) AS BIGINT) FROM s) AS n_tokens,
 (SELECT count(*) FROM (SELECT DISTINCT u1, u2 FROM p WHERE u1 <> u2)) AS n_friends, (SELECT count(*) FROM p) AS n_diffs, (SELECT count(DISTINCT word) FROM t SEMI JOIN s USING (doc_id)) AS n_words"""

_ORACLES["graph_stats_web"] = r"""
WITH r AS (SELECT page_id AS doc_id, regexp_extract(url, '^[a-zA-Z]+://([^/:?#]+)', 1) AS u, html, page_id // 50 AS tbin FROM pages),
w AS (SELECT doc_id, u, unnest(regexp_split_to_array(lower(regexp_extract(html, '<title>([^<]*)', 1)), '[^\p{L}]+')) AS word FROM r),
t AS (SELECT * FROM w WHERE word <> ''), s AS (SELECT doc_id, u, count(*) AS n FROM t GROUP BY ALL HAVING count(*) >= 2),
h AS (SELECT DISTINCT doc_id, u, tbin, target FROM (SELECT doc_id, u, tbin, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS target FROM r)),
g AS (SELECT doc_id, u, tbin, lag(doc_id) OVER o AS d2, lag(u) OVER o AS u2 FROM h WINDOW o AS (PARTITION BY target ORDER BY doc_id))
SELECT (SELECT count(DISTINCT u) FROM s) AS n_users, (SELECT count(*) FROM s) AS n_docs, (SELECT CAST(sum(n) AS BIGINT) FROM s) AS n_tokens,
 (SELECT count(*) FROM (SELECT DISTINCT a.u, b.u FROM (SELECT DISTINCT target, u FROM h) a JOIN (SELECT DISTINCT target, u FROM h) b ON a.target = b.target AND a.u <> b.u)) AS n_friends,
 (SELECT count(*) FROM (SELECT DISTINCT doc_id, d2, u, u2, tbin FROM g WHERE u <> u2)) AS n_diffs, (SELECT count(DISTINCT word) FROM t SEMI JOIN s USING (doc_id)) AS n_words"""

_ORACLES["graph_stats_dialog"] = r"""
WITH r AS (SELECT conv_id * 1000 + turn AS doc_id, conv_id, turn, role, text FROM conversations),
t AS (SELECT * FROM (SELECT doc_id, conv_id, role, unnest(regexp_split_to_array(lower(text), '[^\p{L}]+')) AS word FROM r) WHERE length(word) >= 3),
s AS (SELECT doc_id, conv_id, role, count(*) AS n FROM t GROUP BY ALL HAVING count(*) >= 2), m AS (SELECT DISTINCT conv_id, role FROM r),
g AS (SELECT doc_id, role, lag(doc_id) OVER o AS d2, lag(role) OVER o AS r2 FROM r WINDOW o AS (PARTITION BY conv_id ORDER BY turn))
SELECT (SELECT count(*) FROM (SELECT DISTINCT conv_id, role FROM s)) AS n_users, (SELECT count(*) FROM s) AS n_docs, (SELECT CAST(sum(n) AS BIGINT) FROM s) AS n_tokens,
 (SELECT count(*) FROM m a JOIN m b ON a.conv_id = b.conv_id AND a.role <> b.role) AS n_friends, (SELECT count(*) FROM (SELECT DISTINCT * FROM g WHERE role <> r2)) AS n_diffs, (SELECT count(DISTINCT word) FROM t SEMI JOIN s USING (doc_id)) AS n_words"""


def _preprocess_sql() -> str:
    stop = ", ".join(f"'{w}'" for w in text.STOP_WORDS)
    word = "w"
    for pattern, by in text.ENDINGS[:-1]:
        word = f"regexp_replace({word}, '{pattern}', '{by.replace('$1', chr(92) + '1')}')"
    return rf"""SELECT doc_id, term, count(*) AS n FROM (SELECT doc_id, CASE WHEN w LIKE '#%' THEN w WHEN regexp_matches(s, '{text.ENDINGS[-1][0]}') THEN left(s, length(s) - 1) ELSE s END AS term
 FROM (SELECT doc_id, w, {word} AS s FROM (SELECT doc_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '{text.WORD}')) AS w FROM documents)
 WHERE w LIKE '#%' OR NOT (w IN ({stop}) OR regexp_matches(w, '{text.OTHER_KINDS}') OR regexp_matches(w, '^[\p{{N}}_]+$'))))
 WHERE doc_id IN (SELECT doc_id FROM (SELECT doc_id, unnest(regexp_extract_all(lower(coalesce(text, '')), '{text.WORD}')) AS w FROM documents) WHERE w LIKE '#%' OR NOT (w IN ({stop}) OR regexp_matches(w, '{text.OTHER_KINDS}') OR regexp_matches(w, '^[\p{{N}}_]+$')) GROUP BY doc_id HAVING count(*) >= 2) GROUP BY ALL"""


@query()
def preprocess_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = graphs.read(spark, sf_dir, "documents").select("doc_id", F.xxhash64("source", "lang").alias("user_id"), "text")
    return text.preprocessed(docs).select("doc_id", F.explode("words").alias("term")).groupBy("doc_id", "term").agg(F.count("*").alias("n"))


_ORACLES["preprocess_terms"] = _preprocess_sql()


@query("SELECT doc_id, user_id, ts, tbin, n_tok FROM docs")
def docs_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.commerce(spark, sf_dir).docs


@query("SELECT doc_id, user_id, word, cnt FROM tokens")
def tokens_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.commerce(spark, sf_dir).tokens


@query("SELECT src, dst FROM friends")
def friends_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.commerce(spark, sf_dir).friends


@query("SELECT src_doc, dst_doc, src_user, dst_user, tbin FROM diffs")
def diffs_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.commerce(spark, sf_dir).diffs


@query("SELECT word, word_id, df, cf FROM vocab")
def vocab_commerce(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.commerce(spark, sf_dir).vocab()


@query("SELECT user_id, round(popularity, 6) AS popularity, round(activeness, 6) AS activeness FROM feat")
def user_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).features.select("user_id", r6("popularity").alias("popularity"), r6("activeness").alias("activeness"))


# Counters and estimates


@query("SELECT doc_id, user_id, c, z FROM assign")
def init_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).assign


@query("SELECT user_id, c, n FROM uc")
def user_comm_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counters.user_community(Slice(spark, sf_dir).assign)


@query("SELECT c, z, n FROM ct")
def comm_topic_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return counters.community_topic(Slice(spark, sf_dir).assign)


@query("SELECT z, word, n FROM tw")
def topic_word_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return counters.topic_word(s.assign, s.g.tokens)


for _name, _scale in (("topic_popularity", "raw"), ("topic_popularity_log", "log1p"), ("topic_popularity_share", "share")):
    named(_name, lambda spark, sf_dir, _s=_scale: Slice(spark, sf_dir).pop(_s).select("z", "tbin", r6("pop").alias("pop")), f"SELECT z, tbin, round(pop, 6) AS pop FROM pop_{_scale}")

for _name, _view, _keys in (("pi_hat", "pi", ("user_id", "c")), ("theta_hat", "theta", ("c", "z")), ("pi_smoothed", "pi_s", ("user_id", "c")), ("theta_smoothed", "theta_s", ("c", "z")), ("phi_smoothed", "phi_s", ("z", "word"))):
    named(_name, lambda spark, sf_dir, _v=_view, _k=_keys: getattr(Slice(spark, sf_dir), _v).select(*_k, r6("p").alias("p")), f"SELECT {', '.join(_keys)}, round(p, 6) AS p FROM {_view}")

for _name, _norm, _view in (("eta_per_community", "per_community", "eta"), ("eta_joint", "joint", "eta_joint"), ("eta_per_pair_topic", "per_pair_topic", "eta_pair")):
    named(_name, lambda spark, sf_dir, _n=_norm: Slice(spark, sf_dir).eta(_n).select("c", "c2", "z", r6("p").alias("p")), f"SELECT c, c2, z, round(p, 6) AS p FROM {_view}")


# Link probabilities


@query(f"SELECT src, dst, round({sql.sigmoid('x')}, 6) AS p FROM fscore")
def friend_prob(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return factors.friend_probabilities(s.g.friends, s.pi).select("src", "dst", r6("p").alias("p"))


@query(f"SELECT src, dst, round({sql.pg_mean('x')}, 6) AS lam FROM fscore")
def lambda_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return factors.augmentation_means(factors.friend_scores(s.g.friends, s.pi), "x", "lam").select("src", "dst", r6("lam").alias("lam"))


@query("SELECT src_doc, dst_doc, round(y, 6) AS y FROM yc")
def community_factor(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return factors.community_factor(s.links, s.pi, s.tensor, ["src_doc", "dst_doc"], C * C * Z).select("src_doc", "dst_doc", r6("y").alias("y"))


@query("SELECT src_doc, dst_doc, round(y, 6) AS y FROM yi")
def individual_factor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).scored(("individual",)).select("src_doc", "dst_doc", r6("y").alias("y"))


_WAYS = {"diffusion_prob": (("community", "topic", "individual"), "y"), "diffusion_prob_comm_only": (("community",), "y_c"), "diffusion_prob_no_topic": (("community", "individual"), "y_c + y_i")}
for _name, (_active, _sum) in _WAYS.items():
    named(_name, lambda spark, sf_dir, _a=_active: Slice(spark, sf_dir).scored(_a).select("src_doc", "dst_doc", r6(sigmoid(F.col("y"))).alias("p")), f"SELECT src_doc, dst_doc, round({sql.sigmoid(_sum)}, 6) AS p FROM ys")


@query(f"SELECT d.src_doc, d.dst_doc, round({sql.sigmoid('coalesce(sum(a.p * b.p), 0)')}, 6) AS p FROM diffs d LEFT JOIN pi a ON a.user_id = src_user LEFT JOIN pi b ON b.user_id = dst_user AND b.c = a.c GROUP BY ALL")
def diffusion_prob_similarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return factors.similarity_scores(s.g.diffs, s.pi).select("src_doc", "dst_doc", r6(sigmoid(F.col("y"))).alias("p"))


@query(f"SELECT src_doc, dst_doc, round({sql.pg_mean('y')}, 6) AS delta FROM ys")
def delta_mean(spark: SparkSession, sf_dir: str) -> DataFrame:
    return factors.augmentation_means(Slice(spark, sf_dir).scored(), "y", "delta").select("src_doc", "dst_doc", r6("delta").alias("delta"))


# Sampler


@query("SELECT doc_id, z, round(score, 6) AS score FROM ttext")
def topic_scores_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).topic_scores().select("doc_id", "z", r6("score").alias("score"))


@query("SELECT doc_id, z, round(score, 6) AS score FROM tfull")
def topic_scores_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).topic_scores_full().select("doc_id", "z", r6("score").alias("score"))


@query("SELECT doc_id, c, round(score, 6) AS score FROM ctext")
def comm_scores_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).community_scores().select("doc_id", "c", r6("score").alias("score"))


@query("SELECT doc_id, c, round(term, 6) AS term FROM cfriend")
def comm_scores_friend(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return sampling.community_friend_scores(s.assign, s.g.friends, s.pi, C).select("doc_id", "c", r6("term").alias("term"))


@query("SELECT doc_id, c, round(score, 6) AS score FROM cfull")
def comm_scores_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).community_scores_full().select("doc_id", "c", r6("score").alias("score"))


@query("SELECT doc_id, arg_max(z, (round(score, 9), -z)) AS z FROM ttext GROUP BY doc_id")
def draw_argmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.draw(Slice(spark, sf_dir).topic_scores(), "z", "argmax")


@query(f"SELECT doc_id, CAST(min(z) AS INT) AS z FROM (SELECT *, sum(w) OVER (PARTITION BY doc_id ORDER BY z ROWS UNBOUNDED PRECEDING) AS upto, sum(w) OVER (PARTITION BY doc_id) AS every FROM (SELECT doc_id, z, exp(score - max(score) OVER (PARTITION BY doc_id)) AS w FROM ttext)) WHERE upto >= {sql.uniform('doc_id', 303)} * every GROUP BY doc_id")
def draw_inverse_cdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.draw(Slice(spark, sf_dir).topic_scores(), "z", "inverse", portable=True)


@query(f"SELECT doc_id, arg_max(z, (round(score, 9) - ln(-ln({sql.uniform('doc_id * 1009 + z', 404)})), -z)) AS z FROM ttext GROUP BY doc_id")
def draw_gumbel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sampling.draw(Slice(spark, sf_dir).topic_scores(), "z", "gumbel", portable=True)


@query("SELECT t.doc_id, t.z, k.c FROM (SELECT doc_id, arg_max(z, (round(score, 9), -z)) AS z FROM tfull GROUP BY doc_id) t JOIN (SELECT doc_id, arg_max(c, (round(score, 9), -c)) AS c FROM cfull GROUP BY doc_id) k USING (doc_id)")
def sweep1_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return sampling.draw(s.topic_scores_full(), "z", "argmax").join(sampling.draw(s.community_scores_full(), "c", "argmax"), "doc_id").select("doc_id", "z", "c")


@query("""SELECT (SELECT round(sum(lgamma(n + %r) - lgamma(%r)), 4) FROM uc) - (SELECT round(sum(lgamma(n_docs + %r) - lgamma(%r)), 4) FROM nd) AS users,
 (SELECT round(sum(lgamma(n + %r) - lgamma(%r)), 4) FROM ct) - (SELECT round(sum(lgamma(nc + %r) - lgamma(%r)), 4) FROM ctot) AS communities,
 (SELECT round(sum(lgamma(n + 0.1) - lgamma(0.1)), 3) FROM tw) - (SELECT round(sum(lgamma(nz + n_words * 0.1) - lgamma(n_words * 0.1)), 3) FROM tz, nw) AS topics""" % (RHO, RHO, C * RHO, C * RHO, ALPHA, ALPHA, Z * ALPHA, Z * ALPHA))
def log_joint_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.plans.profiler import log_joint_terms as terms

    s = Slice(spark, sf_dir)
    return terms(s.assign, s.g.tokens, C, Z, ALPHA, RHO, BETA)


@query(f"""SELECT round(sum((label - {sql.sigmoid('y')}) * f1), 4) AS g1, round(sum((label - {sql.sigmoid('y')}) * f2), 4) AS g2, round(sum((label - {sql.sigmoid('y')}) * f3), 4) AS g3, round(sum((label - {sql.sigmoid('y')}) * f4), 4) AS g4
 FROM (SELECT 1 AS label, y, fs.popularity AS f1, fs.activeness AS f2, fd.popularity AS f3, fd.activeness AS f4 FROM ys LEFT JOIN feat fs ON fs.user_id = src_user LEFT JOIN feat fd ON fd.user_id = dst_user)""")
def nu_gradient_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.plans.profiler import nu_gradient

    s = Slice(spark, sf_dir)
    g = nu_gradient(s.scored().withColumn("label", F.lit(1)), s.features)
    return g.select(*(F.round(f"g{i}", 4).alias(f"g{i}") for i in range(1, 5)))


@query("""SELECT (SELECT round(sum(-ln(1 + exp(-x))), 4) FROM fscore) AS friends, (SELECT round(sum(-ln(1 + exp(-y))), 4) FROM ys) AS diffusions""")
def log_joint_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The parts of the log joint that observed links add to ``log_joint_terms``."""
    from commlens.plans.profiler import log_joint_links

    s = Slice(spark, sf_dir)
    return log_joint_links(factors.friend_scores(s.g.friends, s.pi), s.scored()).select(F.round("friends", 4).alias("friends"), F.round("diffusions", 4).alias("diffusions"))


@query()
def non_diff_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.plans.profiler import negative_links

    return negative_links(graphs.prepared(spark, sf_dir), 7)


@query()
def auc_diffusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """AUC of the averaged three-factor probability on links and as many document pairs that are none."""
    from commlens.operators import diffusion

    s = Slice(spark, sf_dir)
    pairs = s.g.diffs.withColumn("label", F.lit(1)).unionByName(non_diff_links(spark, sf_dir).withColumn("label", F.lit(0)))
    p = diffusion.score_pairs(pairs, diffusion.topic_posterior(s.g.tokens, s.phi_s, Z), s.pi, s.tensor, s.pop(), s.features, NU, Z, keep=("label",), communities=C)
    return measures.auc(p.select(F.round("p", 9).alias("score"), "label")).select(r6("auc").alias("auc"), "n_pos", "n_neg")


# Segments


@query("SELECT user_id, CAST(arg_max(z, (n, -z)) AS INT) AS seg FROM (SELECT user_id, z, count(*) AS n FROM assign GROUP BY ALL) GROUP BY user_id")
def segment_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.segment_users(Slice(spark, sf_dir).assign)


_LOAD = """SELECT seg, CAST(sum(3 * coalesce(nd, 0) + coalesce(nf, 0) + 2 * coalesce(ne, 0)) AS DOUBLE) AS load FROM (SELECT user_id, arg_max(z, (n, -z)) AS seg FROM (SELECT user_id, z, count(*) AS n FROM assign GROUP BY ALL) GROUP BY user_id)
 LEFT JOIN (SELECT user_id, count(*) AS nd FROM docs GROUP BY ALL) USING (user_id) LEFT JOIN (SELECT src AS user_id, count(*) AS nf FROM friends GROUP BY ALL) USING (user_id) LEFT JOIN (SELECT src_user AS user_id, count(*) AS ne FROM diffs GROUP BY ALL) USING (user_id) GROUP BY seg"""


@query(_LOAD)
def segment_load(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return partition.segment_load(partition.segment_users(s.assign), s.g, (3.0, 1.0, 2.0))


@query()
def knapsack_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.placement(segment_load(spark, sf_dir), 4)


@query()
def balance_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    load = segment_load(spark, sf_dir)
    return partition.balance(load, partition.placement(load, 4))


@query(f"""SELECT seg, CAST(worker AS INT) AS worker FROM (WITH RECURSIVE o AS (SELECT seg, load, row_number() OVER (ORDER BY load DESC, seg) AS i FROM ({_LOAD})),
 r AS (SELECT 0::BIGINT AS i, [0.0::DOUBLE, 0.0, 0.0, 0.0] AS sums, NULL::INT AS seg, NULL::BIGINT AS worker
 UNION ALL SELECT o.i, list_transform(r.sums, lambda x, j: CASE WHEN j = list_position(r.sums, list_min(r.sums)) THEN x + o.load ELSE x END), o.seg, list_position(r.sums, list_min(r.sums)) - 1 FROM r JOIN o ON o.i = r.i + 1) SELECT seg, worker FROM r WHERE seg IS NOT NULL)""")
def knapsack_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partition.placement(segment_load(spark, sf_dir), 4, "greedy")


# Applications


@query("SELECT q_id, c, round(score, 9) AS score, rank FROM rank")
def rank_communities(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).ranked().select("q_id", "c", F.round("score", 9).alias("score"), F.col("rank").cast("bigint").alias("rank"))


@query("SELECT q_id, c, round(sum(r * a), 6) AS score FROM (SELECT q_id, z, p / sum(p) OVER (PARTITION BY q_id) AS a FROM qws JOIN phi_s USING (word)) JOIN rcz USING (z) GROUP BY ALL")
def rank_communities_normalised(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Slice(spark, sf_dir).ranked(normalise=True).select("q_id", "c", r6("score").alias("score"))


@query("SELECT word, CAST(sum(cnt) AS BIGINT) AS freq FROM tokens WHERE doc_id IN (SELECT src_doc FROM diffs) AND word NOT IN (SELECT word FROM vocab ORDER BY cf DESC, word LIMIT 3) GROUP BY word HAVING sum(cnt) > 100")
def query_select(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graphs.prepared(spark, sf_dir)
    return ranking.select_queries(g.tokens, g.diffs, 100, 3)


@query("WITH w AS (SELECT word, CAST(sum(cnt) AS BIGINT) AS freq FROM tokens WHERE doc_id IN (SELECT src_doc FROM diffs) GROUP BY word HAVING sum(cnt) > 100) SELECT word, freq, CAST(least(floor((freq - (SELECT min(freq) FROM w)) * 5 / greatest((SELECT max(freq) - min(freq) FROM w), 1)) + 1, 5) AS INT) AS band FROM w".replace("WITH w AS (", "SELECT * FROM (WITH w AS (", 1) + ")")
def query_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graphs.prepared(spark, sf_dir)
    return ranking.frequency_bands(ranking.select_queries(g.tokens, g.diffs, 100))


@query(f"""SELECT src_user, dst_doc, round(sum(w * {sql.sigmoid('yz.y_c + coalesce(pop, 0) + yi.y')}) / any_value(ws), 6) AS p FROM (
 SELECT d.src_user, d.src_doc, d.dst_doc, d.tbin, zs.z, coalesce(tp.p, 0) AS w, 1 AS ws FROM diffs d CROSS JOIN zs LEFT JOIN (SELECT doc_id, z, e / sum(e) OVER (PARTITION BY doc_id) AS p FROM (
   SELECT doc_id, z, exp(l - max(l) OVER (PARTITION BY doc_id)) AS e FROM (SELECT doc_id, z, sum(cnt * ln(p)) AS l FROM tokens JOIN phi_s USING (word) GROUP BY ALL))) tp ON tp.doc_id = d.dst_doc AND tp.z = zs.z) x
 JOIN yz USING (src_doc, dst_doc, z) JOIN yi USING (src_doc, dst_doc) LEFT JOIN pop_share ps ON ps.z = x.z AND ps.tbin = x.tbin GROUP BY src_user, src_doc, dst_doc""")
def score_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.operators import diffusion

    s = Slice(spark, sf_dir)
    topics = diffusion.topic_posterior(s.g.tokens, s.phi_s, Z)
    return diffusion.score_pairs(s.g.diffs, topics, s.pi, s.tensor, s.pop(), s.features, NU, Z, communities=C).select("src_user", "dst_doc", r6("p").alias("p"))


@query("SELECT c, c2, round(p, 6) AS w FROM eta WHERE z = 3")
def diffusion_edges_topic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.diffusion_edges(Slice(spark, sf_dir).eta(), 3).select("c", "c2", r6("w").alias("w"))


@query("SELECT c, c2, round(sum(p), 6) AS w FROM eta GROUP BY ALL")
def diffusion_edges_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.diffusion_edges(Slice(spark, sf_dir).eta()).select("c", "c2", r6("w").alias("w"))


@query("SELECT c, c2, round(w, 6) AS w FROM (SELECT *, avg(w) OVER () AS m FROM (SELECT c, c2, sum(p) AS w FROM eta GROUP BY ALL)) WHERE round(w, 9) >= round(m, 9)")
def edges_above_average(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.prune_edges(views.diffusion_edges(Slice(spark, sf_dir).eta())).select("c", "c2", r6("w").alias("w"))


@query("SELECT c, round(1 - sum(CASE WHEN c = c2 THEN p ELSE 0 END) / sum(p), 6) AS openness FROM eta GROUP BY c")
def openness(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.openness(Slice(spark, sf_dir).eta()).select("c", r6("openness").alias("openness"))


@query("SELECT z, count(DISTINCT c) AS n_communities FROM eta GROUP BY z")
def generality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.generality(Slice(spark, sf_dir).eta())


@query("SELECT z, word, CAST(rank AS INT) AS rank FROM (SELECT z, word, row_number() OVER (PARTITION BY z ORDER BY round(p, 12) DESC, word) AS rank FROM phi_s) WHERE rank <= 5")
def top_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.top_words(Slice(spark, sf_dir).phi_s, 5)


@query("""SELECT c, string_agg(word, ' ' ORDER BY rank) AS label FROM (SELECT c, word, row_number() OVER (PARTITION BY c ORDER BY round(sum(t.p * f.p), 12) DESC, word) AS rank FROM theta_s t JOIN phi_s f USING (z) GROUP BY c, word) WHERE rank <= 3 GROUP BY c""")
def community_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return views.community_labels(s.theta_s, s.phi_s, 3)


@query("SELECT c, c2, z, round(p, 6) AS p FROM (SELECT *, row_number() OVER (PARTITION BY c, c2 ORDER BY round(p, 12) DESC, z) AS k FROM eta WHERE (c = 0 AND c2 = 1) OR (c = 1 AND c2 = 0)) WHERE k <= 3")
def exchange_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.exchange(Slice(spark, sf_dir).eta(), 0, 1, 3).select("c", "c2", "z", r6("p").alias("p"))


@query("""SELECT round(covar_samp(n_docs, n_out) / nullif(stddev_samp(n_docs) * stddev_samp(n_out), 0), 6) AS corr_made, round(covar_samp(popularity, n_in) / nullif(stddev_samp(popularity) * stddev_samp(n_in), 0), 6) AS corr_received FROM (SELECT user_id, count(*) AS n_docs FROM docs GROUP BY ALL) LEFT JOIN feat USING (user_id)
 LEFT JOIN (SELECT src_user AS user_id, count(*) AS n_out0 FROM diffs GROUP BY ALL) USING (user_id) LEFT JOIN (SELECT dst_user AS user_id, count(*) AS n_in0 FROM diffs GROUP BY ALL) USING (user_id), LATERAL (SELECT coalesce(n_out0, 0) AS n_out, coalesce(n_in0, 0) AS n_in)""")
def individual_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return views.individual_study(s.g, s.features).select(r6("corr_made").alias("corr_made"), r6("corr_received").alias("corr_received"))


@query("SELECT z, round(covar_samp(n, coalesce(e, 0)) / nullif(stddev_samp(n) * stddev_samp(coalesce(e, 0)), 0), 6) AS corr FROM tt LEFT JOIN (SELECT z, tbin, count(*) AS e FROM lk GROUP BY ALL) USING (z, tbin) GROUP BY z")
def topic_time_corr(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return views.topic_time_study(s.assign, s.g).select("z", r6("corr").alias("corr"))


@query("SELECT c, o.c_mktsegment AS value, round(sum(p) / sum(sum(p)) OVER (PARTITION BY c), 6) AS share FROM pi_s JOIN customer o ON o.c_custkey = user_id GROUP BY c, o.c_mktsegment")
def community_attribute_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    customers = graphs.read(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("value"))
    return views.attribute_profile(Slice(spark, sf_dir).pi_s, customers).select("c", "value", r6("share").alias("share"))


# Measures


@query("""WITH und AS (SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM friends), m AS (SELECT * FROM top5)
 SELECT c, CAST(sum((ina <> inb)::INT) AS BIGINT) AS cut, CAST(sum(ina::INT + inb::INT) AS BIGINT) AS vol, round(CASE WHEN least(sum(ina::INT + inb::INT), 2 * count(*) - sum(ina::INT + inb::INT)) > 0 THEN sum((ina <> inb)::INT) / least(sum(ina::INT + inb::INT), 2 * count(*) - sum(ina::INT + inb::INT)) ELSE 0 END, 6) AS conductance
 FROM (SELECT cs.c, EXISTS (SELECT 1 FROM m WHERE m.user_id = a AND m.c = cs.c) AS ina, EXISTS (SELECT 1 FROM m WHERE m.user_id = b AND m.c = cs.c) AS inb FROM und CROSS JOIN cs) GROUP BY c""".replace("WITH und", "SELECT * FROM (WITH und", 1) + ")")
def conductance_top5(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return measures.conductance(s.g.friends, ranking.top_memberships(s.pi_s)).select("c", "cut", "vol", r6("conductance").alias("conductance"))


def _negatives(rounds: int = 12) -> str:
    """Picks by hash, drawn again for links whose pick was no use; a pair goes to the link of least target."""
    parts = ["tgt AS (SELECT row_number() OVER (ORDER BY id) - 1 AS i, id FROM (SELECT DISTINCT user_id AS id FROM docs))", "got0 AS (SELECT src, dst, dst AS to_ FROM friends WHERE false)"]
    for k in range(rounds):
        spot = f"CAST({sql.hashed('(src * 1000003 + dst) % 2147483647', 11 + 7919 * k)} // 16 % (SELECT count(*) FROM tgt) AS BIGINT)"
        left = f"(SELECT src, dst, {spot} AS i FROM friends f WHERE NOT EXISTS (SELECT 1 FROM got{k} g WHERE g.src = f.src AND g.dst = f.dst))"
        fresh = f"SELECT p.src, min(p.dst) AS dst, t.id AS to_ FROM {left} p JOIN tgt t USING (i) WHERE p.src <> t.id AND NOT EXISTS (SELECT 1 FROM friends f WHERE f.src = p.src AND f.dst = t.id) AND NOT EXISTS (SELECT 1 FROM got{k} g WHERE g.src = p.src AND g.to_ = t.id) GROUP BY p.src, t.id"
        parts.append(f"got{k + 1} AS MATERIALIZED (SELECT src, dst, to_ FROM got{k} UNION ALL SELECT src, dst, to_ FROM ({fresh}))")
    return ", ".join([*parts, f"neg AS (SELECT src, to_ AS dst FROM got{rounds})"])


_NEG = _negatives()


@query(f"SELECT * FROM (WITH {_NEG} SELECT src, dst FROM neg)")
def non_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graphs.prepared(spark, sf_dir)
    return measures.non_links(g.friends, measures.numbered(g.docs, "user_id"))


@query(f"""SELECT * FROM (WITH {_NEG}, sc AS (SELECT src, dst, x, 1 AS label FROM fscore UNION ALL SELECT n.src, n.dst, coalesce(sum(a.p * b.p), 0), 0 FROM neg n LEFT JOIN pi a ON a.user_id = src LEFT JOIN pi b ON b.user_id = dst AND b.c = a.c GROUP BY ALL),
 h AS (SELECT round(x, 9) AS s, sum(label) AS p, sum(1 - label) AS n FROM sc GROUP BY ALL), r AS (SELECT *, sum(n) OVER (ORDER BY s) - n AS lower FROM h)
 SELECT round(sum(p * (lower + n / 2)) / sum(p) / sum(n), 6) AS auc, CAST(sum(p) AS BIGINT) AS n_pos, CAST(sum(n) AS BIGINT) AS n_neg FROM r)""")
def auc_friend(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    negative = measures.non_links(s.g.friends, measures.numbered(s.g.docs, "user_id"))
    scored = factors.friend_scores(s.g.friends, s.pi).withColumn("label", F.lit(1)).union(factors.friend_scores(negative, s.pi).withColumn("label", F.lit(0)))
    return measures.auc(scored.select(F.round("x", 9).alias("score"), "label")).select(r6("auc").alias("auc"), "n_pos", "n_neg")


@query(f"SELECT fold, count(*) AS n FROM (SELECT CAST({sql.hashed('(src * 1000003 + dst) % 2147483647', 5)} // 128 % 10 AS INT) AS fold FROM friends) GROUP BY fold")
def fold_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.prepared(spark, sf_dir).friends.groupBy(measures.fold_of(10, 5, F.col("src"), F.col("dst")).alias("fold")).agg(F.count("*").alias("n"))


def _pr(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return ranking.precision_recall(s.ranked(5), ranking.top_memberships(s.pi_s), ranking.relevant_users(s.g.tokens, s.g.diffs), 5)


@query("SELECT q_id, CAST(k AS INT) AS k, round(n_hit / n_u, 6) AS precision, round(n_hit / n_rel, 6) AS recall FROM prk")
def pr_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pr(spark, sf_dir).select("q_id", "k", r6("precision").alias("precision"), r6("recall").alias("recall"))


@query("""SELECT CAST(k AS INT) AS k, round(avg(ap), 6) AS map, round(avg(ar), 6) AS mar, round(2 * avg(ap) * avg(ar) / (avg(ap) + avg(ar)), 6) AS maf
 FROM (SELECT q_id, k, avg(n_hit / n_u) OVER w AS ap, avg(n_hit / n_rel) OVER w AS ar FROM prk WINDOW w AS (PARTITION BY q_id ORDER BY k)) GROUP BY k""")
def maf_at_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ranking.averages(_pr(spark, sf_dir)).select("k", *(r6(x).alias(x) for x in ("map", "mar", "maf")))


@query("""SELECT q_id, CAST(k AS INT) AS k, round(ap, 6) AS map, round(ar, 6) AS mar, round(2 * ap * ar / (ap + ar), 6) AS maf FROM (SELECT q_id, k, avg(n_hit / n_u) OVER w AS ap, avg(n_hit / n_rel) OVER w AS ar FROM prk WINDOW w AS (PARTITION BY q_id ORDER BY k)) WHERE q_id = 'ring'""")
def single_query_case(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ranking.averages(_pr(spark, sf_dir).where("q_id = 'ring'"), by_query=True).select("q_id", "k", *(r6(x).alias(x) for x in ("map", "mar", "maf")))


@query("""SELECT round((a.m - b.m) / b.m, 6) AS gain FROM (SELECT avg(p) AS m FROM phi_s) a, (SELECT avg(p) AS m FROM theta_s) b""")
def relative_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    from commlens.plans.experiments import relative_gain as gain

    s = Slice(spark, sf_dir)
    ours, other = (x.agg(F.avg("p").alias("m")) for x in (s.phi_s, s.theta_s))
    return ours.crossJoin(other.withColumnRenamed("m", "n")).select(r6(gain(F.col("m"), F.col("n"))).alias("gain"))


@query("""SELECT round(exp(-sum(ll) / sum(n)), 6) AS perplexity, CAST(sum(n) AS BIGINT) AS n_tokens FROM (SELECT doc_id, any_value(n) AS n, max(m) + ln(sum(w * exp(l - m))) AS ll FROM (SELECT *, max(l) OVER (PARTITION BY doc_id) AS m FROM (
 SELECT doc_id, user_id, z, sum(cnt * ln(p)) AS l, sum(cnt) AS n FROM tokens JOIN phi_s USING (word) GROUP BY ALL)) JOIN (SELECT user_id, z, sum(a.p * t.p) AS w FROM pi_s a JOIN theta_s t USING (c) GROUP BY ALL) USING (user_id, z) GROUP BY doc_id)""")
def perplexity_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return measures.perplexity(s.g.tokens, s.pi_s, s.theta_s, s.phi_s).select(r6("perplexity").alias("perplexity"), "n_tokens")


@query("""SELECT round(exp(-sum(cnt * ln(q)) / sum(cnt)), 6) AS perplexity, CAST(sum(cnt) AS BIGINT) AS n_tokens FROM (SELECT doc_id, word, any_value(cnt) AS cnt, sum(w * p) AS q FROM tokens JOIN phi_s USING (word)
 JOIN (SELECT user_id, z, sum(a.p * t.p) AS w FROM pi_s a JOIN theta_s t USING (c) GROUP BY ALL) USING (user_id, z) GROUP BY ALL)""")
def perplexity_word(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return measures.perplexity(s.g.tokens, s.pi_s, s.theta_s, s.phi_s, "word_mix").select(r6("perplexity").alias("perplexity"), "n_tokens")


@query("""SELECT * FROM (WITH d AS (SELECT CAST(f % 10 AS INT) AS fold, avg(x) AS a FROM (SELECT src % 10 AS f, x FROM fscore) GROUP BY ALL) SELECT round((avg(a) - 0.1) / (stddev_samp(a) / sqrt(count(*))), 6) AS t, count(*) - 1 AS df FROM d)""")
def paired_t_stat(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    folds = factors.friend_scores(s.g.friends, s.pi).groupBy((F.col("src") % 10).alias("fold")).agg(F.avg("x").alias("a"))
    return folds.agg(r6((F.avg("a") - 0.1) / (F.stddev_samp("a") / F.sqrt(F.count("*")))).alias("t"), (F.count("*") - 1).alias("df"))


@query("SELECT round(sum(n / t * ln(n * t / ra / rb)) / sqrt(any_value(ha) * any_value(hb)), 6) AS nmi FROM (SELECT *, (SELECT -sum(k / t * ln(k / t)) FROM (SELECT count(*) AS k, (SELECT count(*) FROM assign) AS t FROM assign GROUP BY c)) AS ha, (SELECT -sum(k / t * ln(k / t)) FROM (SELECT count(*) AS k, (SELECT count(*) FROM assign) AS t FROM assign GROUP BY z)) AS hb FROM (SELECT c, z, n, sum(n) OVER (PARTITION BY c) AS ra, sum(n) OVER (PARTITION BY z) AS rb, sum(n) OVER () AS t FROM ct))")
def nmi_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.mutual_information(Slice(spark, sf_dir).assign, "c", "z").select(r6("nmi").alias("nmi"))


# Baselines


@query("SELECT c, z, round(sum(p * m) / sum(sum(p * m)) OVER (PARTITION BY c), 6) AS p FROM pi JOIN (SELECT user_id, z, count(*) / any_value(n_docs) AS m FROM assign JOIN nd USING (user_id) GROUP BY user_id, z) USING (user_id) GROUP BY c, z")
def agg_content_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return baselines.aggregate_content(s.pi, baselines.hard_topics(s.assign)).select("c", "z", r6("p").alias("p"))


@query("SELECT c, c2, z, round(w / sum(w) OVER (PARTITION BY c), 6) AS p FROM (SELECT a.c, b.c AS c2, l.z, sum(a.p * b.p) AS w FROM lk l JOIN assign t ON t.doc_id = dst_doc AND t.z = l.z JOIN pi a ON a.user_id = src_user JOIN pi b ON b.user_id = dst_user GROUP BY ALL)")
def agg_diffusion_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return baselines.aggregate_diffusion(s.pi, baselines.hard_topics(s.assign), s.g.diffs).select("c", "c2", "z", r6("p").alias("p"))


@query("SELECT l.z, round(count(*) / any_value(nz * nz) * 1000, 6) AS rate FROM lk l JOIN assign t ON t.doc_id = dst_doc AND t.z = l.z JOIN (SELECT z, count(*) AS nz FROM assign GROUP BY z) m ON m.z = l.z GROUP BY l.z")
def topiclink_em_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return baselines.topic_link_rates(baselines.hard_topics(s.assign), s.g.diffs).select("z", r6(F.col("rate") * 1000).alias("rate"))


@query("""SELECT d.src_doc, d.dst_doc, CAST(EXISTS (SELECT 1 FROM friends f WHERE f.src = src_user AND f.dst = dst_user) AS INT) AS friend, round(fs.activeness, 6) AS s_activeness, round(fd.popularity, 6) AS d_popularity
 FROM diffs d LEFT JOIN feat fs ON fs.user_id = src_user LEFT JOIN feat fd ON fd.user_id = dst_user""")
def userfeature_design(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    got = baselines.link_design(s.g, s.g.diffs, s.features)
    return got.select("src_doc", "dst_doc", "friend", r6("s_activeness").alias("s_activeness"), r6("d_popularity").alias("d_popularity"))


@query("SELECT a.c, b.c AS c2, round(sum(a.p * b.p), 6) AS n FROM friends JOIN pi a ON a.user_id = src JOIN pi b ON b.user_id = dst GROUP BY ALL")
def roleblock_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return baselines.block_counts(s.pi, s.g.friends).select("c", "c2", r6("n").alias("n"))


@query("SELECT c, c2, z, round(n / sum(n) OVER (PARTITION BY z), 6) AS strength FROM eta_n")
def strengthblock_strength(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = Slice(spark, sf_dir)
    return baselines.strengths(s.g.diffs, s.assign).select("c", "c2", "z", r6("strength").alias("strength"))


_MIX = f"""th0 AS (SELECT doc_id, user_id, z, w / sum(w) OVER (PARTITION BY doc_id) AS p FROM (SELECT doc_id, user_id, z, {sql.uniform('doc_id * 1009 + z', 505)} + 0.5 AS w FROM docs CROSS JOIN zs)),
ph0 AS (SELECT z, word, n / sum(n) OVER (PARTITION BY z) AS p FROM (SELECT z, word, CAST(n AS DOUBLE) AS n FROM tw)),
nr AS (SELECT doc_id, user_id, z, word, cnt * h / sum(h) OVER (PARTITION BY doc_id, word) AS h FROM (SELECT t.doc_id, t.user_id, z, t.word, cnt, a.p * b.p AS h FROM tokens t JOIN th0 a USING (doc_id) JOIN ph0 b USING (z, word)))"""
_Q = """lq AS (SELECT src_doc, dst_doc, z, w / sum(w) OVER (PARTITION BY src_doc, dst_doc) AS q FROM (SELECT src_doc, dst_doc, a.z, a.p * b.p + 1e-12 AS w FROM diffs JOIN th0 a ON a.doc_id = src_doc JOIN th0 b ON b.doc_id = dst_doc AND b.z = a.z))"""
_FRESH = "SELECT doc_id, z, round((n + 0.1) / (sum(n) OVER (PARTITION BY doc_id) + 0.1 * %d), 6) AS p FROM (SELECT t.doc_id, t.z, coalesce(sum(n), 0) AS n FROM th0 t LEFT JOIN (%s) USING (doc_id, z) GROUP BY ALL)"


def _mixture_step(spark: SparkSession, sf_dir: str, links: bool) -> tuple[DataFrame, DataFrame]:
    s = Slice(spark, sf_dir)
    theta, _ = baselines.first_mixtures(s.g.docs, s.g.tokens, Z)
    tw = counters.topic_word(s.assign, s.g.tokens)
    phi = tw.select("z", "word", (F.col("n") / F.sum("n").over(W.partitionBy("z"))).alias("p"))
    rate = spark.range(Z).select(F.col("id").cast("int").alias("z"), F.lit(1.0).alias("rate"))
    n_words = s.g.tokens.select("word").distinct().count()
    return baselines.mixture_step(s.g.tokens, theta, phi, Z, 0.1, BETA, n_words, s.g.diffs if links else None, rate if links else None)


@query("SELECT * FROM (WITH " + _MIX + " " + _FRESH % (Z, "SELECT doc_id, z, h AS n FROM nr") + ")")
def lda_step_mixtures(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _mixture_step(spark, sf_dir, False)[0].select("doc_id", "z", r6("p").alias("p"))


@query("SELECT * FROM (WITH " + _MIX + " SELECT z, word, round((sum(h) + 0.1) / (sum(sum(h)) OVER (PARTITION BY z) + 0.1 * (SELECT count(DISTINCT word) FROM tokens)), 6) AS p FROM nr GROUP BY z, word)")
def lda_step_topics(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _mixture_step(spark, sf_dir, False)[1].select("z", "word", r6("p").alias("p"))


@query("SELECT * FROM (WITH " + _MIX + ", " + _Q + " " + _FRESH % (Z, "SELECT doc_id, z, h AS n FROM nr UNION ALL SELECT src_doc, z, q FROM lq UNION ALL SELECT dst_doc, z, q FROM lq") + ")")
def topiclink_step_mixtures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One step of the mixtures that words and diffusion links share."""
    return _mixture_step(spark, sf_dir, True)[0].select("doc_id", "z", r6("p").alias("p"))


_SBM = f"""q0 AS (SELECT user_id, b, w / sum(w) OVER (PARTITION BY user_id) AS p FROM (SELECT user_id, range::INT AS b, {sql.uniform('user_id * 1009 + range', 707)} + 0.5 AS w FROM (SELECT DISTINCT user_id FROM docs) CROSS JOIN range(4))),
sz AS (SELECT b, sum(p) AS m FROM q0 GROUP BY b), el AS (SELECT 0 AS kind, src, dst FROM friends UNION ALL SELECT 1, src_user, dst_user FROM diffs),
cn AS (SELECT kind, a.b, c.b AS b2, sum(a.p * c.p) AS n FROM el JOIN q0 a ON a.user_id = src JOIN q0 c ON c.user_id = dst GROUP BY ALL),
rt AS (SELECT t.kind, x.b, y.b AS b2, (coalesce(n, 0) + 0.01) / (x.m * y.m + 1) AS rate FROM (VALUES (0), (1)) t(kind) CROSS JOIN sz x CROSS JOIN sz y LEFT JOIN cn ON cn.kind = t.kind AND cn.b = x.b AND cn.b2 = y.b)"""


def _role_start(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list[DataFrame]]:
    g = graphs.prepared(spark, sf_dir)
    w = g.docs.select("user_id").distinct().select("user_id", F.explode(F.sequence(F.lit(0), F.lit(3))).alias("b")).withColumn("w", uniform(F.col("user_id") * 1009 + F.col("b"), 707) + 0.5)
    q = w.select("user_id", "b", (F.col("w") / F.sum("w").over(W.partitionBy("user_id"))).alias("p"))
    return q, [g.friends.select("src", "dst"), g.diffs.select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst"))]


@query("SELECT * FROM (WITH " + _SBM + " SELECT kind, b, b2, round(rate, 9) AS rate FROM rt)")
def roleblock_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, links = _role_start(spark, sf_dir)
    both = [baselines.block_rates(q, e).select(F.lit(k).alias("kind"), "b", "b2", F.round("rate", 9).alias("rate")) for k, e in enumerate(links)]
    return both[0].union(both[1])


@query("SELECT * FROM (WITH " + _SBM + """, lg AS (SELECT kind, b, b2, ln(rate) AS l, rate FROM rt),
 pull AS (SELECT src AS user_id, lg.b, sum(p * l) AS v FROM el JOIN q0 ON q0.user_id = dst JOIN lg ON lg.kind = el.kind AND lg.b2 = q0.b GROUP BY ALL UNION ALL SELECT dst, lg.b2, sum(p * l) FROM el JOIN q0 ON q0.user_id = src JOIN lg ON lg.kind = el.kind AND lg.b = q0.b GROUP BY ALL),
 bs AS (SELECT b, sum(v) AS v FROM (SELECT b, ln(m / (SELECT sum(m) FROM sz) + 1e-9) AS v FROM sz UNION ALL SELECT lg.b, -sum(rate * m) FROM lg JOIN sz ON sz.b = lg.b2 GROUP BY lg.b UNION ALL SELECT lg.b2, -sum(rate * m) FROM lg JOIN sz ON sz.b = lg.b GROUP BY lg.b2) GROUP BY b),
 xs AS (SELECT u.user_id, bs.b, any_value(bs.v) + coalesce(sum(pull.v), 0) AS x FROM (SELECT DISTINCT user_id FROM q0) u CROSS JOIN bs LEFT JOIN pull ON pull.user_id = u.user_id AND pull.b = bs.b GROUP BY ALL),
 ex AS (SELECT user_id, b, exp(x - max(x) OVER (PARTITION BY user_id)) AS e FROM xs) SELECT user_id, b, round(e / sum(e) OVER (PARTITION BY user_id), 6) AS p FROM ex)""")
def roleblock_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One mean-field step of the (community, role) blocks over both kinds of links."""
    q, links = _role_start(spark, sf_dir)
    return baselines.role_step(q, links, [baselines.block_rates(q, e) for e in links]).select("user_id", "b", r6("p").alias("p"))


@query(f"SELECT p_partkey, round({sql.pg_mean('(p_size - 1) / 4')}, 9) AS mean FROM part")
def pg_mean_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.read(spark, sf_dir, "part").select("p_partkey", F.round(pg_mean((F.col("p_size") - 1) / 4.0), 9).alias("mean"))


@query("SELECT p_partkey, round(lgamma(p_size + 2.5) - lgamma(2.5), 6) AS v FROM part")
def log_rising_factorial(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graphs.read(spark, sf_dir, "part").select("p_partkey", F.round(log_rising(F.lit(2.5), F.col("p_size")), 6).alias("v"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Communities ranked for the word ``ring``, after one slice of the model."""
    return Slice(spark, sf_dir).ranked().where("q_id = 'ring'")


def queries() -> dict[str, Query]:
    from commlens.contract import engine

    return _QUERIES | engine.queries()


def oracle_sql() -> dict[str, str]:
    from commlens.contract import engine

    return _ORACLES | engine.oracle_sql()
