"""Near-duplicates by SimHash fingerprints, linked through a grid over segment bit counts.

A fingerprint is embedded as the bit counts of its 32 segments of two bits. The Manhattan distance of two
embeddings never exceeds the Hamming distance of the fingerprints, so fingerprints within RADIUS bits
lie within RADIUS unit moves of each other's grid cells. Counts are kept thermometer-coded in one
64-bit number: the Manhattan distance is then the bit count of an exclusive or.

The range join: moves of RADIUS units touch at most RADIUS groups of segments, so each fingerprint is put
in the cells that are left when RADIUS of the groups are masked, and pairs in a cell are filtered by the
Manhattan bound, then by the exact distance. The number of groups grows with the number of
distinct fingerprints, so that unrelated fingerprints rarely share a cell.

Members of cells of more than PAIRS (a text with thousands of near copies) go to the next finer grid of FINER, where the same join is
made among them: a pair that shares a crowded cell shares a finer one too, so no link is lost on the way. Only what still
crowds the finest grid, which leaves no segment but two unmasked, is linked without pairs, through the 65 points within one bit of
each: two fingerprints differ in two bits or fewer exactly if they have such a point in common, and members that share a point
are joined to the least of them. (This holds for RADIUS 2, the only one offered.)

Exact copies share a fingerprint and count once from the start.

``keep_one_of_each`` asks for more than fingerprints reach: two texts are near copies if the sets of their five-word shingles (64-bit hashes)
have a Jaccard similarity of 0.8 or more. Fingerprints of these shingles give the first candidates, by the range join above, each checked by
the whole sets. All other pairs are found by keys: such sets of a and b shingles differ in (a + b) // 9 shingles at most. Sets of like size deal their shingles
over half as many buckets; buckets with equal contents have equal keys, and at most as many buckets differ as shingles do. In any one order of all
keys, two near copies therefore share one of the first (a + b) // 9 + 1 keys of each; fullest buckets come first, so unrelated texts with a shingle
in common have no key in common. Keys of small sets are their shingles, those common in a sample last. A set whose shingles leave too few buckets
filled is compared with all sets of its size. Sets of a key are compared with STARS of them first, and then only pairs that
are not yet connected are compared. A parity sketch of the sets, which differs in no more bits than the sets do in shingles, spares most whole comparisons.

Cases: null text is empty text, which has fingerprint zero; null doc_ids are linked like others but are no
component's id unless it has no other (then it is null); repeated rows each get a row in ``link_documents``; an empty table gives an
empty table; other columns are ignored by ``link_documents`` and passed through by ``keep_one_of_each``.
"""

from __future__ import annotations

import bisect
import itertools
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from commlens.llm.common import Scratch, column_bytes, limit_batches, slices
from commlens.llm.graph import components

RADIUS = 2
SHINGLE = 3
SEED = 42
#: The most members of a cell whose pairs are compared one by one.
PAIRS = 32
#: Groups of segments of the finer grids for crowded cells.
FINER = (16, 32)
#: Near copies of ``keep_one_of_each``: words of a shingle; members that the others of a key are compared with first; texts whose common shingles set the order, how many of them must have a shingle, and shingles sent to the tasks.
COPY_SHINGLE = 5
STARS = 3
ORDER_TEXTS, ORDER_LEAST, ORDER_SHINGLES = 4_000, 3, 100_000
#: Least sizes of the classes of sets; near copies are of one class or of two neighbours. Smaller sets than 4 have no near copy but themselves.
EDGES = [4, 5]
while EDGES[-1] < 1 << 34:
    EDGES.append((EDGES[-1] - 1) * 5 // 4 + 1)
#: Classes from this size on deal shingles over buckets; 64-bit numbers of a parity sketch.
BUCKETED, SKETCH = 32, 8
_SEGMENTS = 32
#: The chance that two random segments of two bits have equal counts.
_SAME = 0.375


def shingle_hashes(raw: bytes, shingle: int = SHINGLE, seed: int = SEED) -> np.ndarray:
    """The hash of each shingle of a UTF-8 text; a text of fewer words is one shingle, one without words has none."""
    words = raw.lower().split()
    if not words:
        return np.zeros(0, dtype="<u8")
    joined = b" ".join(words)
    n = len(words) - shingle + 1
    digest = xxhash.xxh64_intdigest
    if n <= 1:
        return np.array([digest(joined, seed)], dtype="<u8")
    stops = list(itertools.accumulate(map(len, words), lambda a, b: a + b + 1))
    starts = [0, *(s + 1 for s in stops[: n - 1])]
    return np.array([digest(joined[a:b], seed) for a, b in zip(starts, stops[shingle - 1 :], strict=True)], dtype="<u8")


def fingerprint(raw: bytes, shingle: int = SHINGLE, seed: int = SEED) -> int:
    """The 64-bit SimHash of a UTF-8 text, unsigned."""
    return majority(shingle_hashes(raw, shingle, seed))


def majority(h: np.ndarray) -> int:
    """The bits set in over half of the hashes."""
    n = len(h)
    if n <= 1:
        return int(h[0]) if n else 0
    ones = np.zeros(64, dtype=np.int64)
    for i in range(0, n, 1 << 14):
        ones += np.unpackbits(h[i : i + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n, bitorder="little").tobytes(), "little")


def shingle_set(raw: bytes) -> np.ndarray:
    """The distinct five-word shingles of a text, as signed numbers in order."""
    return np.unique(shingle_hashes(raw, COPY_SHINGLE).view(np.int64))


def set_key(raw: bytes) -> int:
    """The same 64-bit number for all texts with the same shingles."""
    return xxhash.xxh64_intdigest(shingle_set(raw).tobytes(), SEED)


def with_fingerprint(docs: DataFrame, name: str, text_col: str = "text", of: Callable[[bytes], int] = fingerprint) -> DataFrame:
    """The input's columns and the fingerprint (or another 64-bit number of the text) as a signed number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, text_col):
                got = np.array([of(raw) for raw in column_bytes(part, text_col)], dtype=np.uint64).view(np.int64)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(got)], [*part.schema.names, name])

    limit_batches(docs.sparkSession)
    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, T.StructField(name, T.LongType())]))


def embedding(fp: Column) -> Column:
    """Thermometer-coded counts: the low bit of a segment is set from one bit on, the high bit at two."""
    low = F.lit(0x5555555555555555)
    next_bit = F.shiftrightunsigned(fp, 1)
    return fp.bitwiseOR(next_bit).bitwiseAND(low).bitwiseOR(F.shiftleft(fp.bitwiseAND(next_bit).bitwiseAND(low), 1))


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def groups_for(n: int) -> int:
    """Groups of segments such that a fingerprint has about one unrelated neighbour in its cells, at most."""
    for g in range(4, 12):
        if math.comb(g, RADIUS) * n * _SAME ** (_SEGMENTS * (1 - RADIUS / g)) <= 2:
            return g
    return 12


def masks(groups: int) -> list[int]:
    """For each choice of RADIUS groups, the bits of all others."""
    edges = [round(i * _SEGMENTS / groups) * 2 for i in range(groups + 1)]
    spans = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in itertools.pairwise(edges)]
    whole = (1 << 64) - 1
    return [_signed(whole & ~sum(out)) for out in itertools.combinations(spans, RADIUS)]


def grid_pairs(scratch: Scratch, fps: DataFrame, groups: int, pair_limit: int = PAIRS) -> tuple[DataFrame, DataFrame]:
    """(a, b) of pairs within RADIUS bits that share a cell of at most ``pair_limit`` members of a grid, and (fp) of the members of larger cells."""
    cells = F.array(*(F.struct(F.lit(i).alias("mask"), embedding(F.col("fp")).bitwiseAND(F.lit(m)).alias("cell")) for i, m in enumerate(masks(groups))))
    placed = fps.select("fp", F.inline(cells))
    shared = placed.groupBy("mask", "cell").agg(F.count("*").alias("n")).where("n > 1")
    members = scratch.table(placed.join(shared, ["mask", "cell"]))
    few = members.where(F.col("n") <= pair_limit)
    left, right = few.select("mask", "cell", F.col("fp").alias("a")), few.select("mask", "cell", F.col("fp").alias("b"))
    bound = F.bit_count(embedding(F.col("a")).bitwiseXOR(embedding(F.col("b")))) <= RADIUS
    exact = F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= RADIUS
    pairs = left.join(right, ["mask", "cell"]).where(F.col("a") < F.col("b")).where(bound).where(exact).select("a", "b").distinct()
    return pairs, members.where(F.col("n") > pair_limit).select("fp").distinct()


def near_links(scratch: Scratch, fps: DataFrame, pair_limit: int = PAIRS) -> DataFrame:
    """(a, b): links that connect the distinct fingerprints of column ``fp`` as all pairs within RADIUS bits do."""
    coarse = groups_for(fps.count())
    links, crowd = grid_pairs(scratch, fps, coarse, pair_limit)
    for groups in (g for g in FINER if g > coarse):
        crowd = scratch.table(crowd)
        if crowd.isEmpty():
            return links
        pairs, crowd = grid_pairs(scratch, crowd, groups, pair_limit)
        links = links.union(pairs)
    near = F.array(F.col("fp"), *(F.col("fp").bitwiseXOR(F.lit(_signed(1 << i))) for i in range(64)))
    points = crowd.select("fp", F.explode(near).alias("point"))
    least = points.groupBy("point").agg(F.min("fp").alias("b"), F.count("*").alias("n")).where("n > 1").select("point", "b")
    return links.union(points.join(least, "point").where("fp > b").select(F.col("b").alias("a"), F.col("fp").alias("b")).distinct())


def common_shingles(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that several of a sample of distinct texts have, in order, and in how many."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([shingle_set(raw) for raw in column_bytes(part, "text")]))], ["s"])

    limit_batches(docs.sparkSession)
    top = 1 << 30
    limit = min(top, top * ORDER_TEXTS // max(1, docs.count()) + 1)
    some = docs.select("text").where(F.pmod(F.xxhash64("text"), F.lit(top)) < limit).distinct()
    counts = some.mapInArrow(run, "s bigint").groupBy("s").agg(F.count("*").alias("n")).where(F.col("n") >= ORDER_LEAST)
    rows = counts.orderBy(F.desc("n"), "s").limit(ORDER_SHINGLES).toArrow()
    s, n = (rows.column(c).to_numpy() for c in ("s", "n"))
    order = np.argsort(s)
    return s[order], n[order]


def sketch(found: np.ndarray) -> np.ndarray:
    """Parities of the shingles in each of 64 * SKETCH parts: two sketches differ in no more bits than the sets do in shingles."""
    odd = np.bincount((found & (64 * SKETCH - 1)).astype(np.int64), minlength=64 * SKETCH) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def keys_of(found: np.ndarray, common: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, bool]:
    """The keys of a set of shingles in its own class and, as the larger of a pair, in the class below; and whether they are too few to be sure of a shared one."""
    n, out, odd = len(found), [], False
    own = bisect.bisect_right(EDGES, n) - 1
    if own < 0:
        return np.zeros(0, dtype=np.int64), odd
    for scheme, largest in ((own, n * 5 // 4), (own - 1, EDGES[own] - 1)):
        if scheme < 0:
            continue
        apart = (n + largest) // 9
        x = (found.view(np.uint64) + np.uint64(scheme)) * np.uint64(0x9E3779B97F4A7C15)
        keys = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        if EDGES[scheme] < BUCKETED:
            rank = np.zeros(n, dtype=np.int64)
            if len(common[0]):
                at = np.minimum(np.searchsorted(common[0], found), len(common[0]) - 1)
                rank = np.where(common[0][at] == found, common[1][at], 0)
        else:
            bucket = (keys >> np.uint64(20)) % np.uint64(EDGES[scheme] // 2)
            order = np.argsort(bucket, kind="stable")
            starts = np.flatnonzero(np.diff(bucket[order], prepend=np.uint64(1 << 63)))
            keys = np.add.reduceat(keys[order], starts)
            rank = -np.diff(starts, append=n)
        out.append(keys[np.lexsort((keys, rank))][: apart + 1].view(np.int64))
        odd |= len(keys) <= apart
    return np.concatenate(out), bool(odd)


def shingle_sets(docs: DataFrame, common: tuple[np.ndarray, np.ndarray] | None = None) -> DataFrame:
    """(doc_id, fp, n, some) of each row: the number of its set of shingles, the set's size and all its shingles; where common shingles are given, its keys instead, then
    (sim, parity, odd): the fingerprint over its shingles, the sketch of the set, and whether its keys are too few."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def lists(arrays: list[np.ndarray]) -> pa.Array:
        return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, arrays)], dtype=np.int32)), pa.array(np.concatenate(arrays)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                hashes = [shingle_hashes(raw, COPY_SHINGLE) for raw in column_bytes(part, "text")]
                found = [np.unique(h.view(np.int64)) for h in hashes]
                fps = np.array([xxhash.xxh64_intdigest(f.tobytes(), SEED) for f in found], dtype=np.uint64).view(np.int64)
                columns = {"doc_id": part.column("doc_id"), "fp": pa.array(fps), "n": pa.array([len(f) for f in found], pa.int32())}
                if common is None:
                    columns["some"] = lists(found)
                else:
                    keys = [keys_of(f, common) for f in found]
                    columns["some"] = lists([k for k, _ in keys])
                    columns["sim"] = pa.array(np.array([majority(h) for h in hashes], dtype=np.uint64).view(np.int64))
                    columns["parity"] = lists([sketch(f) for f in found])
                    columns["odd"] = pa.array([o for _, o in keys])
                yield pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

    limit_batches(docs.sparkSession)
    more = "" if common is None else ", sim bigint, parity array<bigint>, odd boolean"
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, fp bigint, n int, some array<bigint>{more}")


def copy_links(scratch: Scratch, docs: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b): links that connect the distinct sets of shingles of ``docs`` as all pairs of Jaccard similarity 0.8 or more do.
    ``sets`` is ``shingle_sets`` with keys, one row of each fp. Each join or window deals rows out anew, in a task for each partition, so candidates of all kinds are checked together."""
    sizes = "5 * n_a >= 4 * n_b and 5 * n_b >= 4 * n_a"
    within = 9 * sum(F.bit_count(F.col("p_a")[i].bitwiseXOR(F.col("p_b")[i])) for i in range(SKETCH)) <= F.col("n_a") + F.col("n_b")

    def alike(pairs: DataFrame) -> DataFrame:
        marks = [sets.select(F.col("fp").alias(x), F.col("n").alias(f"n_{x}"), F.col("parity").alias(f"p_{x}")) for x in "ab"]
        pairs = scratch.table(pairs.distinct().join(marks[0], "a").join(marks[1], "b").where(sizes).where(within).select("a", "b"))
        scratch.release()
        if pairs.isEmpty():
            return pairs
        ends = pairs.select(F.explode(F.array("a", "b")).alias("fp"))
        rows = scratch.table(sets.select("fp", "doc_id").join(ends, "fp", "left_semi"))
        ids = rows.select("doc_id")
        texts = docs.join(ids, "doc_id", "left_semi").select("doc_id", "text").union(docs.where("doc_id is null").select("doc_id", "text"))
        whole = scratch.table(shingle_sets(texts).join(rows.select("fp"), "fp", "left_semi").groupBy("fp").agg(F.first("some").alias("some")))
        left, right = whole.select(F.col("fp").alias("a"), F.col("some").alias("in_a")), whole.select(F.col("fp").alias("b"), F.col("some").alias("in_b"))
        both = F.size(F.array_intersect("in_a", "in_b"))
        out = scratch.table(pairs.join(left, "a").join(right, "b").where(9 * both >= 4 * (F.size("in_a") + F.size("in_b"))).select("a", "b"))
        for used in (whole, rows, pairs):
            scratch.drop(used)
        scratch.release()
        return out

    def by_fingerprints() -> DataFrame:
        """Pairs of sets with one fingerprint, and of fingerprints that the range join links, each by its least set."""
        sims = sets.where(f"n >= {EDGES[0]}").select("fp", "sim")
        least = scratch.table(sims.groupBy("sim").agg(F.min("fp").alias("b")))
        same = sims.join(least, "sim").where("fp <> b").select(F.col("b").alias("a"), F.col("fp").alias("b"))
        near = near_links(scratch, least.select(F.col("sim").alias("fp"))).toDF("sim_a", "sim_b")
        near = near.join(least.select(F.col("sim").alias("sim_a"), F.col("b").alias("a")), "sim_a").join(least.select(F.col("sim").alias("sim_b"), "b"), "sim_b")
        return same.union(near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")))

    group = W.partitionBy("s")
    posts = sets.select("fp", F.explode("some").alias("s"))
    hubs = F.array(*(F.min(F.struct(F.xxhash64("fp", F.lit(turn)).alias("spot"), "fp")).over(group)["fp"] for turn in range(STARS)))
    members = scratch.table(posts.select("s", "fp", F.count("*").over(group).alias("m"), hubs.alias("hubs")).where("m > 1").select("s", "fp", "hubs"))
    scratch.release()
    stars = members.select("fp", F.explode("hubs").alias("hub")).where("fp <> hub")
    links = alike(scratch.table(by_fingerprints()).union(stars.select(F.least("fp", "hub").alias("a"), F.greatest("fp", "hub").alias("b"))))
    rooted = components(scratch, links).withColumnRenamed("node", "fp")
    now = members.join(rooted, "fp", "left").select("s", "fp", F.coalesce("root", "fp").alias("root"))
    # keys whose sets are not all connected
    crowd = scratch.table(now.withColumn("low", F.min("root").over(group)).withColumn("high", F.max("root").over(group)).where("low < high").drop("low", "high"))
    scratch.drop(members)
    scratch.release()
    marked = crowd.join(sets.select("fp", "n", "parity"), "fp")
    left, right = (marked.select("s", F.col("fp").alias(x), F.col("n").alias(f"n_{x}"), F.col("parity").alias(f"p_{x}"), F.col("root").alias(f"root_{x}")) for x in "ab")
    rest = left.join(right, "s").where("a < b and root_a <> root_b").where(sizes).where(within).select("a", "b")
    odd = sets.where("odd").select(F.col("fp").alias("f"), F.col("n").alias("n_a"))
    if not odd.isEmpty():
        others = odd.join(sets.select(F.col("fp").alias("g"), F.col("n").alias("n_b")), F.expr(f"f <> g and {sizes}"))
        rest = rest.union(others.select(F.least("f", "g").alias("a"), F.greatest("f", "g").alias("b")))
    return links.union(alike(rest))


def _classes(scratch: Scratch, prints: DataFrame, links: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(fp, component_id) of each distinct fingerprint in (doc_id, fp), connected by the ``links`` of column fp."""
    reps = scratch.table(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    rooted = scratch.table(components(scratch, links(reps.select("fp"))))
    linked = reps.join(rooted, F.col("fp") == F.col("node"), "left").select("fp", "rep", F.coalesce("root", "fp").alias("root"))
    many = rooted.join(reps, F.col("node") == F.col("fp")).groupBy("root").agg(F.min("rep").alias("first"))
    return linked.join(many, "root", "left").select("fp", F.when(F.col("first").isNotNull(), F.col("first")).otherwise(F.col("rep")).alias("component_id"), "root")


def link_documents(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every document."""
    scratch = Scratch(docs.sparkSession)
    prints = scratch.table(with_fingerprint(docs.select("doc_id", "text"), "fp").select("doc_id", "fp"))
    found = _classes(scratch, prints, lambda fps: near_links(scratch, fps))
    return prints.join(found, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one_of_each(docs: DataFrame) -> DataFrame:
    """One row of each group that near copies (five-word shingles, similarity of 0.8 or more) connect, all columns as they are: that with the least doc_id (null ids
    last), of equal ids that of the least set number, of equal texts the first by its other columns. Rows of one doc_id with different texts are documents of their own."""
    scratch = Scratch(docs.sparkSession, tidy=True)
    key, nth = "__near_fp", "__near_nth"
    # the keys are by far the largest columns: they are written once, for distinct sets
    sets = scratch.table(shingle_sets(docs, common_shingles(docs)).groupBy("fp").agg(F.min("doc_id").alias("doc_id"), *(F.first(c).alias(c) for c in ("n", "some", "sim", "parity", "odd"))))
    scratch.release()
    rooted = components(scratch, copy_links(scratch, docs, sets)).toDF("fp", "root")
    found = sets.select("fp", "doc_id").join(rooted, "fp", "left").groupBy(F.coalesce("root", "fp").alias("root"))
    kept = found.agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "fp")).alias("k"))
    kept = scratch.table(kept.select("k.doc_id", F.col("k.fp").alias(key)))
    scratch.drop(sets)
    often = scratch.table(docs.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1 or doc_id is null").select("doc_id"))
    scratch.release()
    if often.isEmpty():
        return docs.join(kept.select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    once = docs.join(kept.join(often, "doc_id", "left_anti").where("doc_id is not null").select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    rest = with_fingerprint(docs.join(often, "doc_id", "left_semi").select(*docs.columns).unionByName(docs.where("doc_id is null")), key, of=set_key)
    rest = rest.join(kept.withColumnRenamed("doc_id", "__near_id"), key).where(F.col("doc_id").eqNullSafe(F.col("__near_id")))
    order = [F.col(c) for c in ["text", *(c for c in docs.columns if c not in ("doc_id", "text"))]]
    rest = rest.withColumn(nth, F.row_number().over(W.partitionBy(key).orderBy(*order))).where(F.col(nth) == 1)
    return once.unionByName(rest.select(*docs.columns))
