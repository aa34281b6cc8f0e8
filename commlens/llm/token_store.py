"""Token-id files with Elias-Fano document boundaries.

A store is a Parquet table in the order of doc_id. A row is a segment: a blob of the concatenated ids
of some documents (16 bits each where the vocabulary allows, else 32) and their boundaries as an
Elias-Fano sequence, with samples of every 64th set bit for ``select``. No table of 64-bit offsets
is kept: n boundaries below u take about n * (2 + log2(u / n)) bits. A segment knows the ids before it in its
range of documents; one total per range gives the rest, so nothing that grows with the documents
meets in one place.

Cases: null text is empty text (it has the end id alone); null doc_ids come first; rows of equal doc_id
follow each other in the order of a hash of their texts, so that however many there are they spread over ranges; an empty table gives an empty store; other columns of
the input are ignored.
"""

from __future__ import annotations

import functools
import os
import struct
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from commlens.llm.common import Scratch, claim, limit_batches, slices

#: Ids in a segment, but for a document that has more.
SEGMENT_IDS = 1 << 17
#: Words kept with their ids in each worker, some 20 bytes each, and pieces of uneven texts. When full, the half of the words that came last goes:
#: common words come early.
KEPT_WORDS, KEPT_PIECES = 1_500_000, 50_000
#: Signs that may follow a word's letters; none of them is a letter, a digit, white space or an apostrophe.
_SIGNS = "".join(c for c in map(chr, range(33, 127)) if not c.isalnum() and c != "'")
#: Texts that are not words parted by single spaces and line ends: empty, two in a row, at an end, or other white space.
_UNEVEN = r"^$|[ \n][ \n]|\A[ \n]|[ \n]\z|[\t\x0b\f\r\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"
_SAMPLE = 64
_HEAD = struct.Struct("<4sBBHQQ")
_MAGIC = b"EFID"

# Fixed value: the published pre-tokenisation pattern of this byte-level vocabulary.
_PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


#: Set bits of each byte value, and the place of each of them (from the low end).
_ONES = np.bitwise_count(np.arange(256, dtype=np.uint8)).astype(np.int64)
_PLACE = np.argsort(1 - np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1, bitorder="little"), axis=1, kind="stable")


class EliasFano:
    """A non-decreasing sequence of integers in near-minimal space, with ``select`` of one or many places and ``values`` of all."""

    def __init__(self, n: int, low_bits: int, lows: np.ndarray, highs: np.ndarray, samples: np.ndarray) -> None:
        self.n, self.low_bits, self.lows, self.highs, self.samples = n, low_bits, lows, highs, samples

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        v = np.asarray(values, dtype=np.uint64)
        n = len(v)
        top = int(v[-1]) if n else 0
        k = max(0, int(np.floor(np.log2(max(1, top) / max(1, n))))) if n else 0
        ones = ((v >> np.uint64(k)) + np.arange(n, dtype=np.uint64)).astype(np.int64)
        bits = np.zeros(int(ones[-1]) + 1 if n else 0, dtype=np.uint8)
        bits[ones] = 1
        low = ((v[:, None] >> np.arange(k, dtype=np.uint64)) & np.uint64(1)).astype(np.uint8) if k else np.zeros(0, np.uint8)
        return cls(n, k, np.packbits(low.ravel(), bitorder="little"), np.packbits(bits, bitorder="little"), ones[::_SAMPLE].astype("<u4"))

    def to_bytes(self) -> bytes:
        return struct.pack("<QBII", self.n, self.low_bits, len(self.lows), len(self.highs)) + self.lows.tobytes() + self.highs.tobytes() + self.samples.tobytes()

    @classmethod
    def from_bytes(cls, raw: memoryview) -> tuple[EliasFano, int]:
        """The sequence and the bytes that it took."""
        n, k, n_low, n_high = struct.unpack_from("<QBII", raw)
        at = struct.calcsize("<QBII")
        lows = np.frombuffer(raw, np.uint8, n_low, at)
        highs = np.frombuffer(raw, np.uint8, n_high, at + n_low)
        n_samples = -(-n // _SAMPLE)
        samples = np.frombuffer(raw, "<u4", n_samples, at + n_low + n_high)
        return cls(n, k, lows, highs, samples), at + n_low + n_high + 4 * n_samples

    def select(self, i: int) -> int:
        """The i-th value, read from a sample on."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at, left = int(self.samples[i // _SAMPLE]), i % _SAMPLE
        while left:
            at += 1
            left -= int(self.highs[at >> 3]) >> (at & 7) & 1
        low = 0
        for b in range(self.low_bits):
            j = i * self.low_bits + b
            low |= (int(self.lows[j >> 3]) >> (j & 7) & 1) << b
        return (at - i) << self.low_bits | low

    def select_many(self, places: np.ndarray) -> np.ndarray:
        """The values at places (in any order): all at once from their samples on, a byte of high bits at a time."""
        i = np.asarray(places, dtype=np.int64)
        if len(i) and not 0 <= int(i.min()) <= int(i.max()) < self.n:
            raise IndexError("place out of range")
        at = self.samples[i // _SAMPLE].astype(np.int64)
        byte, left = at >> 3, i % _SAMPLE + 1
        bits = self.highs[byte] & (0xFF << (at & 7) & 0xFF).astype(np.uint8)
        open_ = np.arange(len(i))
        while len(open_):
            open_ = open_[_ONES[bits[open_]] < left[open_]]
            left[open_] -= _ONES[bits[open_]]
            byte[open_] += 1
            bits[open_] = self.highs[byte[open_]]
        high = (byte << 3) + _PLACE[bits, left - 1] - i
        low = np.zeros(len(i), np.int64)
        for b in range(self.low_bits):
            j = i * self.low_bits + b
            low |= ((self.lows[j >> 3] >> (j & 7).astype(np.uint8)) & 1).astype(np.int64) << b
        return high << self.low_bits | low

    def values(self) -> np.ndarray:
        ones = np.flatnonzero(np.unpackbits(self.highs, bitorder="little"))
        out = (ones - np.arange(self.n)).astype(np.int64) << self.low_bits
        if self.low_bits:
            low = np.unpackbits(self.lows, bitorder="little")[: self.n * self.low_bits].reshape(self.n, self.low_bits)
            out |= low.astype(np.int64) @ (1 << np.arange(self.low_bits, dtype=np.int64))
        return out


def pack_segment(ids: list[np.ndarray], width: int) -> bytes:
    bounds = np.concatenate([[0], np.cumsum([len(x) for x in ids])])
    flat = np.concatenate(ids).astype(f"<u{width}")
    return _HEAD.pack(_MAGIC, 1, width, 0, len(ids), len(flat)) + EliasFano.of(bounds).to_bytes() + flat.tobytes()


def read_segment(raw: bytes) -> tuple[EliasFano, np.ndarray]:
    """Boundaries and ids of a segment."""
    magic, version, width, _, _, total = _HEAD.unpack_from(raw)
    if (magic, version) != (_MAGIC, 1):
        raise ValueError("not a segment of this format")
    view = memoryview(raw)
    bounds, taken = EliasFano.from_bytes(view[_HEAD.size :])
    return bounds, np.frombuffer(raw, f"<u{width}", total, _HEAD.size + taken)


class WordStore:
    """Words with their ids, as Arrow and numpy arrays: a tenth of the memory of a dictionary, asked for whole arrays at once."""

    def __init__(self, kind: str) -> None:
        self.words = pa.array([], pa.string())
        self.starts, self.sizes = np.zeros(0, np.int32), np.zeros(0, np.int32)
        self.pool = np.zeros(0, kind)

    def __len__(self) -> int:
        return len(self.words)

    def find(self, words: pa.Array) -> np.ndarray:
        """The place of each word, -1 where it is not known."""
        return pc.fill_null(pc.index_in(words, value_set=self.words), -1).to_numpy(zero_copy_only=False).copy()

    def ids_of(self, i: int) -> bytes:
        return self.pool[self.starts[i] : self.starts[i] + self.sizes[i]].tobytes()

    def add(self, words: list[str], ids: list[bytes]) -> None:
        sizes = np.fromiter(map(len, ids), dtype=np.int32, count=len(ids)) // self.pool.itemsize
        self.words = pa.concat_arrays([self.words, pa.array(words, pa.string())])
        self.starts = np.concatenate([self.starts, len(self.pool) + np.cumsum(sizes, dtype=np.int32) - sizes])
        self.sizes = np.concatenate([self.sizes, sizes])
        self.pool = np.concatenate([self.pool, np.frombuffer(b"".join(ids), self.pool.dtype)])

    def trim(self, most: int) -> None:
        if len(self) > most:
            n = most // 2
            self.words = pa.concat_arrays([self.words.slice(0, n), pa.array([], pa.string())])
            self.starts, self.sizes = self.starts[:n].copy(), self.sizes[:n].copy()
            self.pool = self.pool[: int(self.starts[-1] + self.sizes[-1])].copy()


class PieceEncoder:
    """A byte-level tokenizer of the tokenizers library with a store of words already encoded: the
    library works on the pattern's pieces one by one, so a run of whole pieces has the same ids wherever it
    stands. Where single spaces and line ends alone part a text's words, no piece crosses from a word to the next
    space; a word after a space, and a word after a line end, are then such runs. Arrow numbers the distinct words of
    many texts at once, so that the store is asked once for each. Other texts go by pieces."""

    def __init__(self, path: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.width = 2 if self.tokenizer.get_vocab_size() <= 1 << 16 else 4
        self.kind = f"<u{self.width}"
        self._cut = regex.compile(_PIECES.replace("[^\\s", "[^\\p{White_Space}").replace("\\s", "\\p{White_Space}").replace("\\S", "\\P{White_Space}")).findall
        self._words = WordStore(self.kind)
        self._pieces: dict[str, bytes] = {}
        self._signs: dict[str, bytes] = {}

    def _raw(self, texts: list[str]) -> list[bytes]:
        code = "H" if self.width == 2 else "I"
        return [array(code, got.ids).tobytes() for got in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, new: list[str], seen: pa.Array, found: np.ndarray) -> None:
        """Adds words to the store, in order. Those that begin with a line end stand as they are, others after a space. Letters
        with signs after them are two pieces: the letters' ids and the signs' ids; letters are looked for among the words at hand (``seen``,
        at ``found`` in the store)."""
        store, signs = self._words, self._signs
        ended = {w: base for w in new if not w.isalpha() and (base := w.rstrip(_SIGNS)) is not w and base.isalpha()}
        new_signs = list({w[len(base) :] for w, base in ended.items()}.difference(signs))
        signs.update(zip(new_signs, self._raw(new_signs), strict=True))
        bases = list(set(ended.values()))
        at = pc.index_in(pa.array(bases, pa.string()), value_set=seen).to_pylist()
        known = {base: store.ids_of(found[i]) for base, i in zip(bases, at, strict=True) if i is not None and found[i] >= 0}
        plain = [w for w in new if w not in ended]
        extra = list(set(bases).difference(known).difference(plain))
        known.update(zip([*plain, *extra], self._raw([w if w[0] == "\n" else " " + w for w in [*plain, *extra]]), strict=True))
        store.add([*new, *extra], [known[w] if w not in ended else known[ended[w]] + signs[w[len(ended[w]) :]] for w in [*new, *extra]])

    def _by_pieces(self, text: str) -> np.ndarray:
        pieces, kept = self._cut(text), self._pieces
        new = list(set(pieces).difference(kept))
        kept.update(zip(new, self._raw(new), strict=True))
        return np.frombuffer(b"".join(map(kept.__getitem__, pieces)), self.kind)

    def _by_words(self, texts: pa.Array) -> list[np.ndarray]:
        lined = pc.binary_join_element_wise("\n", pc.replace_substring(texts, "\n", " \n"), "")
        lists = pc.split_pattern(lined, " ")
        coded = lists.flatten().dictionary_encode()
        store = self._words
        found = store.find(coded.dictionary)
        new = np.flatnonzero(found < 0)
        if len(new):
            first = len(store)
            self._learn(coded.dictionary.take(pa.array(new)).to_pylist(), coded.dictionary, found)
            found[new] = np.arange(first, first + len(new), dtype=found.dtype)
        size = store.sizes[found]
        at = coded.indices.to_numpy()
        each = size[at]
        stop = np.cumsum(each, dtype=np.int32)
        spot = np.repeat(store.starts[found][at] - stop + each, each)
        spot += np.arange(stop[-1], dtype=np.int32)
        flat = store.pool[spot]
        ends = stop[lists.offsets.to_numpy()[1:] - lists.offsets[0].as_py() - 1].tolist()
        return [flat[a + 1 : b] for a, b in zip([0, *ends[:-1]], ends, strict=True)]

    def encode(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text; null is empty."""
        self._words.trim(KEPT_WORDS)
        for kept in (self._pieces, self._signs):
            if len(kept) > KEPT_PIECES:
                kept.clear()
        texts = pc.fill_null(texts.cast(pa.string()), "")
        odd = pc.match_substring_regex(texts, _UNEVEN)
        for mark in self.special:
            odd = pc.or_(odd, pc.match_substring(texts, mark))
        odd = odd.to_numpy(zero_copy_only=False)
        out: list = [None] * len(texts)
        even = np.flatnonzero(~odd)
        if len(even):
            for i, ids in zip(even.tolist(), self._by_words(texts.take(pa.array(even))), strict=True):
                out[i] = ids
        for i in np.flatnonzero(odd).tolist():
            text = texts[i].as_py()
            out[i] = np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.kind) if any(m in text for m in self.special) else self._by_pieces(text)
        return out


_loaded = functools.lru_cache(maxsize=1)(PieceEncoder)


def piece_encoder(path: str) -> PieceEncoder:
    """One encoder per process."""
    claim("token_store", _loaded.cache_clear)
    return _loaded(path)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def segments(docs: DataFrame, path: str | None = None, end_id: int = 2, segment_ids: int = SEGMENT_IDS) -> DataFrame:
    """The rows of a store: (part, seq, before, n_ids, doc_ids, blob). ``part`` numbers ranges of doc_id upwards,
    ``before`` counts the ids of the same part that come earlier."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encoder = piece_encoder(path or default_path())
        part, seq, before = TaskContext.get().partitionId(), 0, 0
        keys: list = []
        held: list[np.ndarray] = []
        size = 0
        end = np.array([end_id], dtype=f"<u{encoder.width}")

        def flush() -> pa.RecordBatch:
            nonlocal seq, before, keys, held, size
            row = pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int32()), pa.array([seq], pa.int32()), pa.array([before], pa.int64()), pa.array([size], pa.int64()), pa.array([keys], pa.list_(pa.int64())), pa.array([pack_segment(held, encoder.width)], pa.binary())],
                ["part", "seq", "before", "n_ids", "doc_ids", "blob"],
            )
            seq, before, keys, held, size = seq + 1, before + size, [], [], 0
            return row

        for batch in batches:
            for some in slices(batch, "text", 4096, 12 << 20):
                for key, ids in zip(some.column("doc_id").to_pylist(), encoder.encode(some.column("text")), strict=True):
                    if size and size + len(ids) + 1 > segment_ids:
                        yield flush()
                    keys.append(key)
                    held.append(np.concatenate([ids, end]))
                    size += len(ids) + 1
        if keys:
            yield flush()

    limit_batches(docs.sparkSession)
    key = [F.col("doc_id").asc_nulls_first(), F.col("tie")]
    ordered = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text", F.xxhash64("text").alias("tie")).repartitionByRange(*key).sortWithinPartitions(*key).drop("tie")
    return ordered.mapInArrow(run, "part int, seq int, before bigint, n_ids bigint, doc_ids array<bigint>, blob binary")


def write_store(docs: DataFrame, where: str, path: str | None = None, end_id: int = 2) -> None:
    segments(docs, path, end_id).write.parquet(where)


def located(store: DataFrame) -> DataFrame:
    """Segments with ``start``, the ids of the whole store before each. One row per part is added up."""
    totals = store.groupBy("part").agg(F.max(F.col("before") + F.col("n_ids")).alias("n"))
    bases = totals.select("part", (F.sum("n").over(W.orderBy("part")) - F.col("n")).alias("base"))
    return store.join(F.broadcast(bases), "part").withColumn("start", F.col("base") + F.col("before"))


def read_documents(store: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of each document, from the blobs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for keys, start, raw in zip(batch.column("doc_ids"), batch.column("start").to_pylist(), batch.column("blob"), strict=True):
                bounds, ids = read_segment(raw.as_py())
                v = bounds.select_many(np.arange(bounds.n))
                wide = ids.astype("<u4")
                crc = [zlib.crc32(wide[a:b]) for a, b in zip(v[:-1].tolist(), v[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([keys.values, pa.array(v[:-1] + start), pa.array(np.diff(v)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    return located(store).select("doc_ids", "start", "blob").mapInArrow(run, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def round_trip(spark: SparkSession, docs: DataFrame, path: str | None = None, end_id: int = 2) -> DataFrame:
    """Writes a store in the shared folder and reads every document back from it."""
    return read_documents(Scratch(spark).table(segments(docs, path, end_id)))
