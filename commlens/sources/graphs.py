"""Social graphs from the given tables: users, short documents with words, friendship links, diffusion links.

Every adapter returns a ``SocialGraph`` of the same shapes:

  docs(doc_id, user_id, ts, tbin, n_tok)   tokens(doc_id, user_id, word, cnt)
  friends(src, dst)                        diffs(src_doc, dst_doc, src_user, dst_user, tbin)

A diffusion link points from the diffusing document to the earlier one. Links that two rows of a group imply are made by equi-joins on the
group and, of large groups, on pairs of blocks of at most ``BLOCK`` members or so: every group gives all its pairs, however large it is, and no
task gets more than two blocks of it at once. The rows of links grow with the square of a group.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens import scratch

BLOCK = 1000


@dataclass
class SocialGraph:
    docs: DataFrame
    tokens: DataFrame
    friends: DataFrame
    diffs: DataFrame

    def users(self) -> DataFrame:
        return self.docs.select("user_id").distinct()

    def vocab(self) -> DataFrame:
        """(word, word_id, df, cf); ids number the words in order."""
        words = self.tokens.groupBy("word").agg(F.count("*").alias("df"), F.sum("cnt").alias("cf"))
        return numbered(words, "word", "word_id")

    def cached(self) -> SocialGraph:
        return SocialGraph(*(df.persist() for df in (self.docs, self.tokens, self.friends, self.diffs)))

    def written(self) -> SocialGraph:
        """The same graph from tables in the shared folder, each derived once."""
        return SocialGraph(*(scratch.written(df) for df in (self.docs, self.tokens, self.friends, self.diffs)))


def numbered(rows: DataFrame, key: str, name: str = "i") -> DataFrame:
    """The rows with their place, from zero, in the order of a column of distinct values. Ranges are sorted side by side and written; a count per
    range gives the places before it, so no task sees all rows."""
    parts = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = rows.repartitionByRange(parts, key).withColumn("__part", F.spark_partition_id())
    order = scratch.written(order.withColumn("__at", F.row_number().over(W.partitionBy("__part").orderBy(key)) - 1))
    sizes = order.groupBy("__part").agg(F.count("*").alias("n"))
    before = sizes.select("__part", (F.sum("n").over(W.orderBy("__part")) - F.col("n")).alias("__before"))
    return order.join(F.broadcast(before), "__part").withColumn(name, (F.col("__before") + F.col("__at")).cast("bigint")).drop("__part", "__at", "__before")


_prepared: dict[tuple, SocialGraph] = {}


def prepared(spark: SparkSession, sf_dir: str, name: str = "commerce") -> SocialGraph:
    """A graph of the given tables, derived and written once for all that the session asks of it; derived anew when a table has changed."""
    tables = {"commerce": ["orders", "lineitem", "part"], "corpus": ["documents"], "web": ["pages"], "activity": ["events"], "dialog": ["conversations"]}[name]
    key = (spark.sparkContext.applicationId, name, scratch.stamp(spark, [f"{sf_dir}/{t}.parquet" for t in tables]))
    if key not in _prepared:
        _prepared[key] = ADAPTERS[name](spark, sf_dir).written()
    return _prepared[key]


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def _blocked(members: DataFrame, group: list[str], member: str, block: int) -> tuple[DataFrame, DataFrame]:
    """Both sides of a self-join on the columns of ``group`` and (block_l, block_r). Each ordered pair of members of a group of two or
    more meets once; members of large groups are dealt over blocks by a hash."""
    sizes = members.groupBy(*group).agg(F.count("*").alias("n")).where("n > 1").select(*group, F.ceil(F.col("n") / block).cast("int").alias("blocks"))
    dealt = members.join(sizes, group).withColumn("mine", F.pmod(F.xxhash64(member), F.col("blocks")).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    left = dealt.withColumn("block_r", every).withColumnRenamed("mine", "block_l").drop("blocks")
    right = dealt.withColumn("block_l", every).withColumnRenamed("mine", "block_r").drop("blocks")
    return left, right


def _pairs(members: DataFrame, group: list[str], user: str, block: int = BLOCK) -> DataFrame:
    """Ordered pairs of distinct users that share a group."""
    left, right = _blocked(members.select(*group, user).distinct(), group, user, block)
    return left.withColumnRenamed(user, "src").join(right.withColumnRenamed(user, "dst"), [*group, "block_l", "block_r"]).where("src <> dst").select("src", "dst").distinct()


def word_counts(texts: DataFrame, min_words: int = 2) -> tuple[DataFrame, DataFrame]:
    """(tokens, sizes) from (doc_id, user_id, words ARRAY<STRING>); documents with fewer words are left out."""
    words = texts.select("doc_id", "user_id", F.explode("words").alias("word")).where("word <> ''")
    tokens = words.groupBy("doc_id", "user_id", "word").agg(F.count("*").alias("cnt"))
    sizes = tokens.groupBy("doc_id").agg(F.sum("cnt").alias("n_tok")).where(F.col("n_tok") >= min_words)
    return tokens.join(sizes.select("doc_id"), "doc_id", "left_semi"), sizes


def commerce(spark: SparkSession, sf_dir: str, horizon: int = 14) -> SocialGraph:
    """Customers and their orders. Words are those of the ordered parts; customers who bought the same part from the same supplier are friends;
    an order diffuses the order before it of the same part, by another customer, at most ``horizon`` days earlier."""
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("doc_id"), F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts"))
    lines = read(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("doc_id"), "l_partkey", "l_suppkey", "l_linenumber")
    parts = read(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), F.split(F.lower(F.concat_ws(" ", "p_name", "p_brand", "p_type")), " ").alias("words"))
    bought = lines.join(orders, "doc_id")
    tokens, sizes = word_counts(bought.join(parts, "l_partkey").select("doc_id", "user_id", "words"))
    months = ((F.year("ts") - 1995) * 12 + F.month("ts") - 1).cast("int")
    docs = orders.join(sizes, "doc_id").select("doc_id", "user_id", "ts", months.alias("tbin"), "n_tok")
    friends = _pairs(bought, ["l_partkey", "l_suppkey"], "user_id")
    order = W.partitionBy("l_partkey").orderBy("ts", "doc_id", "l_linenumber")
    before = {c: F.lag(c).over(order) for c in ("doc_id", "user_id", "ts")}
    near = bought.select("doc_id", "user_id", "ts", *(v.alias(f"p_{k}") for k, v in before.items()))
    near = near.where((F.col("user_id") != F.col("p_user_id")) & F.datediff("ts", "p_ts").between(0, horizon))
    diffs = near.select(F.col("doc_id").alias("src_doc"), F.col("p_doc_id").alias("dst_doc"), F.col("user_id").alias("src_user"), F.col("p_user_id").alias("dst_user"), months.alias("tbin")).distinct()
    return SocialGraph(docs, tokens, friends, diffs)


def _corpus_parts(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(docs, tokens, lines) of ``corpus``; lines (doc_id, user_id, tbin, line) are each document's distinct ones, as digests."""
    rows = read(spark, sf_dir, "documents").select("doc_id", "text", F.concat_ws(":", "source", "lang").alias("author"))
    rows = rows.withColumn("user_id", F.xxhash64("author")).withColumn("tbin", F.floor(F.col("doc_id") / 50).cast("int"))
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: F.length(w) >= 3)
    tokens, sizes = word_counts(rows.select("doc_id", "user_id", words.alias("words")))
    docs = rows.join(sizes, "doc_id").select("doc_id", "user_id", F.timestamp_seconds(F.col("tbin") * 86400).alias("ts"), "tbin", "n_tok")
    lines = rows.select("doc_id", "user_id", "tbin", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")).where(F.length("line") >= 30).withColumn("line", F.md5("line"))
    return docs, tokens, lines.distinct()


def corpus(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Authors are (source, language); a document's words of three letters or more are all its words. A line of 30 or more characters that documents
    share, however many, links the later document to each earlier one, and so their authors."""
    docs, tokens, lines = _corpus_parts(spark, sf_dir)
    late, early = _blocked(lines, ["line"], "doc_id", BLOCK)
    late = late.withColumnRenamed("doc_id", "src_doc").withColumnRenamed("user_id", "src_user")
    early = early.select("line", "block_l", "block_r", F.col("doc_id").alias("dst_doc"), F.col("user_id").alias("dst_user"))
    pairs = late.join(early, ["line", "block_l", "block_r"]).where("src_doc > dst_doc").select("src_doc", "dst_doc", "src_user", "dst_user", "tbin").distinct()
    return SocialGraph(docs, tokens, pairs.where("src_user <> dst_user").select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst")).distinct(), pairs)


def line_link_counts(lines: DataFrame, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """One row (n_friends) and one (n_diffs): how many links of users and of documents ``corpus`` makes of (doc_id, user_id, line), without making them.

    Lines that the same documents have are one (two 64-bit digests of the set of documents). A document's lines stand in the order of how many have them; two
    documents count at the first line that both have, which is where the lines before it have none in common. Documents of a line with the same lines before it
    are therefore counted together, and only such groups of a line meet."""
    lines = lines.where("doc_id is not null").select("doc_id", "user_id", "line")
    sets = [F.bit_xor(F.xxhash64("doc_id", "user_id", F.lit(i))).alias(f"s{i}") for i in (1, 2)]
    shared = lines.groupBy("line").agg(F.count("*").alias("n"), *sets).where("n > 1")
    at = scratch.written(lines.join(shared, "line").select("doc_id", "user_id", (-F.col("n")).alias("n"), "s1", "s2").distinct())
    own = scratch.written(at.groupBy("doc_id", "user_id").agg(F.sort_array(F.collect_list(F.struct("n", "s1", "s2"))).alias("own")))
    each = own.select("own", F.posexplode("own").alias("i", "line")).select("line.s1", "line.s2", F.transform(F.slice("own", 1, F.col("i")), lambda x: x["s1"]).alias("before"))
    groups = scratch.written(each.groupBy("s1", "s2", "before").agg(F.count("*").alias("m")))
    left, right = _blocked(groups, ["s1", "s2"], "before", block)
    left, right = left.select("s1", "s2", "block_l", "block_r", F.col("before").alias("a"), F.col("m").alias("m_a")), right.select("s1", "s2", "block_l", "block_r", F.col("before").alias("b"), F.col("m").alias("m_b"))
    met = left.join(right, ["s1", "s2", "block_l", "block_r"]).where("a < b and not arrays_overlap(a, b)").agg(F.sum(F.col("m_a") * F.col("m_b")).alias("n"))
    first = groups.where("size(before) = 0").agg(F.sum((F.col("m") * (F.col("m") - 1) / 2).cast("bigint")).alias("n"))
    ids = own.select("doc_id", F.col("user_id").alias("u"), F.transform("own", lambda x: x["s1"]).alias("in_u"))
    one_id = ids.join(ids.select("doc_id", F.col("u").alias("v"), F.col("in_u").alias("in_v")), "doc_id").where("u < v and arrays_overlap(in_u, in_v)").agg((-F.count("*")).alias("n"))
    diffs = met.union(first).union(one_id).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("n_diffs"))
    ends = at.groupBy("s1", "s2", "user_id").agg(F.max("doc_id").alias("last"), F.min("doc_id").alias("first"))
    left, right = _blocked(ends, ["s1", "s2"], "user_id", block)
    left, right = left.select("s1", "s2", "block_l", "block_r", F.col("user_id").alias("src"), "last"), right.select("s1", "s2", "block_l", "block_r", F.col("user_id").alias("dst"), "first")
    friends = left.join(right, ["s1", "s2", "block_l", "block_r"]).where("src <> dst and last > first").select("src", "dst").distinct().agg(F.count("*").alias("n_friends"))
    return friends, diffs


def corpus_statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``statistics`` of ``corpus``, whose links of documents are counted, not made: they grow with the square of the documents of a line."""
    docs, tokens, lines = _corpus_parts(spark, sf_dir)
    return _one_row(docs, tokens, *line_link_counts(lines))


def web(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Hosts and their pages' titles; a page diffuses the page before it with the same link target; hosts with a shared target are friends."""
    rows = read(spark, sf_dir, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), "html")
    rows = rows.select(F.col("page_id").alias("doc_id"), F.xxhash64("host").alias("user_id"), F.floor(F.col("page_id") / 50).cast("int").alias("tbin"), "html")
    title = F.split(F.lower(F.regexp_extract("html", r"<title>([^<]*)", 1)), r"[^\p{L}]+")
    tokens, sizes = word_counts(rows.select("doc_id", "user_id", title.alias("words")))
    docs = rows.join(sizes, "doc_id").select("doc_id", "user_id", F.timestamp_seconds(F.col("tbin") * 86400).alias("ts"), "tbin", "n_tok")
    targets = rows.select("doc_id", "user_id", "tbin", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'), F.lit(1)))).alias("target"))
    friends = _pairs(targets, ["target"], "user_id")
    order = W.partitionBy("target").orderBy("doc_id")
    near = targets.select(F.col("doc_id").alias("src_doc"), F.lag("doc_id").over(order).alias("dst_doc"), F.col("user_id").alias("src_user"), F.lag("user_id").over(order).alias("dst_user"), "tbin")
    diffs = near.where("dst_user is not null and src_user <> dst_user").distinct()
    return SocialGraph(docs, tokens, friends, diffs)


def sessions(spark: SparkSession, sf_dir: str, gap_hours: int = 12) -> DataFrame:
    """Events with the session they lie in: (event_id, user_id, ts, k, event_type, doc_id); a session has the id of its first event."""
    rows = read(spark, sf_dir, "events").select("event_id", "user_id", F.col("ts").cast("timestamp").alias("ts"), "event_type", F.get_json_object("props", "$.k").cast("int").alias("k"))
    order = W.partitionBy("user_id").orderBy("ts", "event_id")
    start = F.lag("ts").over(order).isNull() | (F.unix_micros("ts") - F.unix_micros(F.lag("ts").over(order)) > gap_hours * 3_600_000_000)
    marked = rows.withColumn("first", F.when(start, F.col("event_id")))
    return marked.withColumn("doc_id", F.last("first", ignorenulls=True).over(order)).drop("first")


def activity(spark: SparkSession, sf_dir: str, reach_hours: int = 6, friend_hours: int = 1) -> SocialGraph:
    """Users and their sessions. An event diffuses the event before it of the same key by another user within ``reach_hours``; within
    ``friend_hours`` the users are friends."""
    rows = sessions(spark, sf_dir)
    words = F.array("event_type", F.concat(F.lit("k"), F.col("k").cast("string")))
    tokens, sizes = word_counts(rows.select("doc_id", "user_id", words.alias("words")))
    first = rows.where("event_id = doc_id").select("doc_id", "user_id", "ts", F.dayofmonth("ts").alias("tbin"))
    docs = first.join(sizes, "doc_id").select("doc_id", "user_id", "ts", "tbin", "n_tok")
    order = W.partitionBy("k").orderBy("ts", "event_id")
    near = rows.select(
        F.col("doc_id").alias("src_doc"), F.lag("doc_id").over(order).alias("dst_doc"), F.col("user_id").alias("src_user"), F.lag("user_id").over(order).alias("dst_user"),
        F.dayofmonth("ts").alias("tbin"), (F.unix_micros("ts") - F.unix_micros(F.lag("ts").over(order))).alias("gap"),
    ).where("src_user <> dst_user")
    diffs = near.where(F.col("gap") <= reach_hours * 3_600_000_000).drop("gap").distinct()
    close = near.where(F.col("gap") <= friend_hours * 3_600_000_000).select(F.col("src_user").alias("src"), F.col("dst_user").alias("dst"))
    return SocialGraph(docs, tokens, close.distinct(), diffs)


def dialog(spark: SparkSession, sf_dir: str) -> SocialGraph:
    """Speakers are (conversation, role); a turn diffuses the turn before it by another speaker; speakers of one conversation are friends."""
    rows = read(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), F.xxhash64("conv_id", "role").alias("user_id"), "conv_id", "turn", "text")
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: F.length(w) >= 3)
    tokens, sizes = word_counts(rows.select("doc_id", "user_id", words.alias("words")))
    docs = rows.join(sizes, "doc_id").select("doc_id", "user_id", F.timestamp_seconds(F.col("turn") * 60).alias("ts"), F.col("turn").cast("int").alias("tbin"), "n_tok")
    order = W.partitionBy("conv_id").orderBy("turn")
    near = rows.select(F.col("doc_id").alias("src_doc"), F.lag("doc_id").over(order).alias("dst_doc"), F.col("user_id").alias("src_user"), F.lag("user_id").over(order).alias("dst_user"), F.col("turn").cast("int").alias("tbin"))
    return SocialGraph(docs, tokens, _pairs(rows, ["conv_id"], "user_id"), near.where("src_user <> dst_user").distinct())


ADAPTERS = {"commerce": commerce, "corpus": corpus, "web": web, "activity": activity, "dialog": dialog}


def _one_row(docs: DataFrame, tokens: DataFrame, n_friends: DataFrame, n_diffs: DataFrame) -> DataFrame:
    out = docs.agg(F.countDistinct("user_id").alias("n_users"), F.count("*").alias("n_docs"), F.sum("n_tok").cast("bigint").alias("n_tokens"))
    for p in (n_friends, n_diffs, tokens.agg(F.countDistinct("word").alias("n_words"))):
        out = out.crossJoin(p)
    return out


def statistics(graph: SocialGraph) -> DataFrame:
    """One row: users, friendship links, diffusion links, documents, words."""
    return _one_row(graph.docs, graph.tokens, graph.friends.agg(F.count("*").alias("n_friends")), graph.diffs.agg(F.count("*").alias("n_diffs")))
