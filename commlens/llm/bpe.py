"""Byte-pair encoding by backtracking over longest matches, and decoding by an offset table.

A text is normalised and cut into words as the tokenizer file says. In a word, an Aho-Corasick
automaton over all vocabulary entries gives the longest entry at each start. The encoder takes the
longest entry that may stand after the one before, steps back to a shorter entry where nothing fits,
and never enters a dead position twice, so its work is linear in the word. Whether two entries may
stand together is a property of the pair: no merge across their border may come before the merges
that hide the border's symbols; the answers are kept in a table. The result is what applying merges in
the order of their ranks gives.

Decoding takes entry bytes from one blob by an offset table.

Cases: null text is empty text and has no tokens; repeated rows each get a row; an empty table gives an
empty table; other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import functools
import hashlib
import itertools
import json
import re
import sys
import unicodedata
from itertools import islice

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from tokenizers import Regex
from tokenizers.normalizers import NFC, Lowercase, Sequence
from tokenizers.pre_tokenizers import Split

from commlens.llm.common import claim, column_text, map_batches

#: Words kept with their tokens in each worker. When full, the half that came last goes: common words come early.
KEPT_WORDS = 350_000
#: Added to the code of a word's last symbol, which is another symbol than the same byte elsewhere.
_LAST = 0x1000
_NEVER = 1 << 40


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte: itself where visible, else the next code from 256 on."""
    visible = [b for lo, hi in ((33, 126), (161, 172), (174, 255)) for b in range(lo, hi + 1)]
    hidden = [b for b in range(256) if b not in visible]
    chars = {b: chr(b) for b in visible} | {b: chr(256 + i) for i, b in enumerate(hidden)}
    return [chars[b] for b in range(256)]


@functools.lru_cache(maxsize=2)
def _own_class(kind: str) -> str:
    """Ranges, as in a character class, of the letters (L) or numbers (N) that the library's pattern engine knows."""
    ours = regex.findall(rf"\p{{{kind}}}", "".join(chr(c) for c in range(sys.maxunicode + 1) if not 0xD800 <= c < 0xE000))
    newer = "".join(c for c in ours if unicodedata.category(c) == "Cn")
    known = {c for c, _ in Split(Regex(rf"\p{{{kind}}}"), "removed", invert=True).pre_tokenize_str(newer)}
    codes = [ord(c) for c in ours if c in known or unicodedata.category(c) != "Cn"]
    runs = (list(g) for _, g in itertools.groupby(enumerate(codes), lambda x: x[1] - x[0]))
    return "".join(f"\\U{g[0][1]:08x}-\\U{g[-1][1]:08x}" for g in runs)


@functools.lru_cache(maxsize=1)
def _table_gaps() -> tuple[frozenset[str], dict[int, str], re.Pattern]:
    """Where the Unicode versions of ``regex``, of Python and of the library's normaliser part: the characters concerned, the lower case
    of capitals that Python does not know yet, and a pattern of marks that the library's older composition tables pass over."""
    normal = Sequence([NFC(), Lowercase()]).normalize_str
    chars = [chr(c) for c in range(sys.maxunicode + 1) if not 0xD800 <= c < 0xE000]
    new = [c for c in regex.findall(r"[\p{L}\p{N}]", "".join(chars)) if unicodedata.category(c) == "Cn"]
    lower = {ord(c): normal(c) for c in new if normal(c) != c}
    marks = {c for c in chars if unicodedata.category(c)[0] == "M" and any(NFC().normalize_str(s) != unicodedata.normalize("NFC", s) for s in (c + "\u0301", c + "\u0323", "\u0301" + c, "\u0345" + c))}
    for c in chars:
        if unicodedata.decomposition(c) and "<" not in unicodedata.decomposition(c):
            whole = unicodedata.normalize("NFD", c)
            if NFC().normalize_str(whole) != unicodedata.normalize("NFC", whole):
                marks |= {c, *whole[1:]}
    return frozenset([*new, *marks]), lower, re.compile("([" + "".join(map(re.escape, sorted(marks))) + "])")


class WordBpe:
    """The tokenizer of a word-end BPE file: ``encode`` text to ids, ``decode`` ids to text."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab: dict[str, int] = spec["model"]["vocab"]
        end = spec["model"]["end_of_word_suffix"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self._cut = regex.compile("|".join(map(regex.escape, self.special)))
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        split = split.replace("\\s", "\\p{White_Space}")
        self._words = regex.compile(split)
        self._newer, self._lower, self._apart = _table_gaps()
        self._own_words = regex.compile(split.replace("[\\p{L}]", "[" + _own_class("L") + "]").replace("\\p{L}", _own_class("L")).replace("\\p{N}", _own_class("N")))
        symbols = byte_symbols()
        self._to_symbols = {b: ord(c) for b, c in enumerate(symbols)}
        self._latin = {b: c for b, c in enumerate(symbols)}

        size = max([*vocab.values(), *self.special.values()]) + 1
        spelled: list[str | None] = [None] * size
        self.rank = [-1] * size
        self.left, self.right = [-1] * size, [-1] * size
        for c in symbols:
            spelled[vocab[c]] = c
            spelled[vocab[c + end]] = chr(ord(c) + _LAST)
        self.pairs: dict[tuple[int, int], int] = {}
        for rank, merge in enumerate(spec["model"]["merges"]):
            a, b = merge.split(" ") if isinstance(merge, str) else merge
            x, y, t = vocab[a], vocab[b], vocab[a + b]
            self.pairs.setdefault((x, y), rank)
            if spelled[t] is None:
                spelled[t], self.rank[t], self.left[t], self.right[t] = spelled[x] + spelled[y], rank, x, y
        self._fits: dict[int, bool] = {}
        self.size = size
        self.length = [len(s or "") for s in spelled]
        sound = {s: t for t, s in enumerate(spelled) if s and (self.rank[t] < 0 or self._first_crossing(self.left[t], self.right[t]) == self.rank[t])}
        self._automaton = ahocorasick.Automaton()
        for s, t in sound.items():
            self._automaton.add_word(s, t)
        self._automaton.make_automaton()
        self.shorter = [-1] * size
        for s, t in sound.items():
            self.shorter[t] = next((sound[s[:k]] for k in range(len(s) - 1, 0, -1) if s[:k] in sound), -1)

        names = {i: s for s, i in (vocab | self.special).items()}
        raw = [names.get(i, "").encode() + b" " for i in range(size)]
        self.blob = np.frombuffer(b"".join(raw), dtype=np.uint8)
        self.offset = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
        self._kept: dict[str, bytes] = {}

    def _first_crossing(self, a: int, b: int) -> int:
        """The rank of the first merge over the border of a and b, if any comes before its symbols are hidden."""
        first, hidden_a = _NEVER, _NEVER
        while True:
            y, hidden_b = b, _NEVER
            while True:
                r = self.pairs.get((a, y), _NEVER)
                if r < first and r < hidden_a and r <= hidden_b:
                    first = r
                if self.rank[y] < 0:
                    break
                hidden_b, y = self.rank[y], self.left[y]
            if self.rank[a] < 0:
                return first
            hidden_a, a = self.rank[a], self.right[a]

    def fits(self, a: int, b: int) -> bool:
        key = a * self.size + b
        known = self._fits.get(key)
        if known is None:
            if len(self._fits) > 500_000:
                self._fits.clear()
            known = self._fits[key] = self._first_crossing(a, b) == _NEVER
        return known

    def _encode_word(self, word: str) -> bytes:
        raw = word.encode()
        text = "".join(map(self._latin.__getitem__, raw))
        text = text[:-1] + chr(ord(text[-1]) + _LAST)
        n, length = len(text), self.length
        longest = [-1] * (n + 1)
        for at, t in self._automaton.iter(text):
            longest[at + 1 - length[t]] = t
        dead, out, pos, take = bytearray(n + 1), [], 0, longest[0]
        while pos < n:
            while take >= 0:
                to = pos + length[take]
                if not dead[to] and (not out or self.fits(out[-1], take)):
                    break
                take = self.shorter[take]
            if take >= 0:
                out.append(take)
                pos = to
                take = longest[pos]
            else:
                dead[pos] = 1
                last = out.pop()
                pos -= length[last]
                take = self.shorter[last]
        return np.array(out, dtype="<u4").tobytes()

    def words(self, text: str) -> list[str]:
        """The words of a text without special tokens, normalised."""
        if text.isascii():
            return self._words.findall(text.lower())
        if self._newer.isdisjoint(text):
            return self._words.findall(unicodedata.normalize("NFC", text).replace("Σ", "σ").lower())
        parts = self._apart.split(text)
        parts[::2] = [unicodedata.normalize("NFC", p) for p in parts[::2]]
        return self._own_words.findall("".join(parts).replace("Σ", "σ").lower().translate(self._lower))

    def _plain(self, text: str) -> bytes:
        words, kept = self.words(text), self._kept
        try:
            return b"".join(map(kept.__getitem__, words))
        except KeyError:
            if len(kept) > KEPT_WORDS:
                kept = self._kept = dict(islice(kept.items(), KEPT_WORDS // 2))
            for w in words:
                if w not in kept:
                    kept[w] = self._encode_word(w)
            return b"".join(map(kept.__getitem__, words))

    def encode(self, text: str) -> np.ndarray:
        """Ids of a text, 32 bits each."""
        if "<|" not in text:
            return np.frombuffer(self._plain(text), dtype="<u4")
        parts, at = [], 0
        for m in self._cut.finditer(text):
            parts += [self._plain(text[at : m.start()]), self.special[m.group()].to_bytes(4, "little")]
            at = m.end()
        return np.frombuffer(b"".join([*parts, self._plain(text[at:])]), dtype="<u4")

    def decode_bytes(self, ids: np.ndarray, block: int = 1 << 16) -> bytes:
        """UTF-8 of the decoded text: the entries' names, parted by spaces."""
        parts = []
        for i in range(0, len(ids), block):
            some = ids[i : i + block].astype(np.int64)
            start = self.offset[some]
            size = self.offset[some + 1] - start
            stop = np.cumsum(size)
            at = np.arange(stop[-1], dtype=np.int64) + np.repeat(start - stop + size, size)
            parts.append(self.blob[at].tobytes())
        return b"".join(parts)[:-1]


_loaded = functools.lru_cache(maxsize=1)(WordBpe)


def word_bpe(path: str) -> WordBpe:
    """One tokenizer per process."""
    claim("bpe", _loaded.cache_clear)
    return _loaded(path)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode_documents(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids): the ids of each whole text as an array."""

    def make():
        bpe = word_bpe(path or default_path())

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            ids = [bpe.encode(t) for t in column_text(batch, text_col)]
            flat = pa.array(np.concatenate(ids).astype(np.int32))
            offsets = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32))
            n = pa.array([len(x) for x in ids], pa.int64())
            return pa.RecordBatch.from_arrays([batch.column(id_col), n, pa.ListArray.from_arrays(offsets, flat)], ["doc_id", "n_tokens", "ids"])

        return step

    kind = docs.schema[id_col].dataType.simpleString()
    return map_batches(docs.select(id_col, text_col), make, f"doc_id {kind}, n_tokens bigint, ids array<int>", text_col)


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text): the decoded text of each id array."""

    def make():
        bpe = word_bpe(path or default_path())

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [bpe.decode_bytes(np.asarray(x or [], dtype=np.int64)).decode() for x in batch.column("ids").to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

        return step

    kind = encoded.schema["doc_id"].dataType.simpleString()
    return encoded.select("doc_id", "ids").mapInArrow(lambda batches: map(make(), batches), f"doc_id {kind}, text string")


def round_trip_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): each text encoded, then decoded from its ids, in one pass."""

    def make():
        bpe = word_bpe(path or default_path())

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            n, of_ids, of_text = [], [], []
            for text in column_text(batch, "text"):
                ids = bpe.encode(text)
                n.append(len(ids))
                of_ids.append(hashlib.sha256(ids.tobytes()).hexdigest())
                of_text.append(hashlib.sha256(bpe.decode_bytes(ids)).hexdigest())
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(of_ids), pa.array(of_text)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

        return step

    kind = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(docs.select("doc_id", "text"), make, f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string")


def encode_with_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, source, n_tokens, ids, ids_sha256, decoded_sha256) of each whole text."""

    def make():
        bpe = word_bpe(path or default_path())

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            ids = [bpe.encode(t) for t in column_text(batch, "text")]
            flat = pa.array(np.concatenate(ids).astype(np.int32))
            offsets = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32))
            columns = [
                batch.column("doc_id"), batch.column("source"), pa.array([len(x) for x in ids], pa.int64()), pa.ListArray.from_arrays(offsets, flat),
                pa.array([hashlib.sha256(x.tobytes()).hexdigest() for x in ids]), pa.array([hashlib.sha256(bpe.decode_bytes(x)).hexdigest() for x in ids]),
            ]
            return pa.RecordBatch.from_arrays(columns, ["doc_id", "source", "n_tokens", "ids", "ids_sha256", "decoded_sha256"])

        return step

    kinds = {f.name: f.dataType.simpleString() for f in docs.schema.fields}
    return map_batches(docs.select("doc_id", "source", "text"), make, f"doc_id {kinds['doc_id']}, source {kinds['source']}, n_tokens bigint, ids array<int>, ids_sha256 string, decoded_sha256 string")
