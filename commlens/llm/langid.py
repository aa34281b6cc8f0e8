"""Language identification by unigram piece models, summed over all segmentations.

Each language has a probability for each piece of one fixed public vocabulary. A word's probability under
a language is the sum over all its segmentations into pieces, by a forward recursion; a text's is the product over its words.
Piece probabilities come from expectation-maximisation (forward-backward) on labelled words. Any
single character is also a piece of at least floor probability, so every word has a segmentation.

Words are runs of letters, lower-cased, with the vocabulary's word mark before. Words of one length are scored together as
arrays, and scores of words already seen are kept in each worker. Runs of more than CHUNK characters are scored one by one, the recursion
rescaled as it goes, so that they too are summed over all segmentations.

Bounds: at most TRAIN_DOCS labelled documents of a language, whole, train its model (where runs of more than CHUNK
characters are counted in chunks); every document is scored over its whole text.

Cases: null text, empty text and text without a letter give ``und`` with score zero; repeated rows each
get a row; with no labelled rows every document is ``und``; an empty table gives an empty table; other columns
are ignored by ``predict_documents`` and passed through by ``keep_recognised``.
"""

from __future__ import annotations

import functools
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens.llm.common import bounded_sample, claim, column_text, limit_batches, map_batches, slices

TRAIN_DOCS = 600
ROUNDS = 3
CHUNK = 24
#: Characters of a long run whose spans are looked up at once.
STRETCH = 4096
FLOOR = 1e-7
KEPT_WORDS = 350_000
MARK = "▁"
_LETTERS = re.compile(r"[^\W\d_]+")
_BASE = np.uint64(0x100000001B3)


def letter_words(text: str) -> list[str]:
    return _LETTERS.findall(text.lower())


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class PieceTable:
    """Numbers of the vocabulary's lower-case pieces, found by rolling hashes of whole arrays of words."""

    def __init__(self, path: str) -> None:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        every = (model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i)))
        self.pieces = sorted({p for p in every if len(p) <= CHUNK and p == p.lower()})
        self.longest = max(map(len, self.pieces))
        keys = np.array([self._hash(p) for p in self.pieces], dtype=np.uint64)
        self._order = np.argsort(keys)
        self._keys = keys[self._order]
        self._power = np.array([pow(int(_BASE), k, 1 << 64) for k in range(CHUNK + 2)], dtype=np.uint64)
        slots = 1 << 19
        self._shift = np.uint64(64 - 19)
        first = np.full(slots, -1, dtype=np.int64)
        at = self._slot(self._keys)
        first[at[::-1]] = np.arange(len(keys))[::-1]
        self._first = first
        self._crowded = np.zeros(slots, dtype=bool)
        self._crowded[at[first[at] != np.arange(len(keys))]] = True

    def _hash(self, s: str) -> int:
        h = 0
        for c in s:
            h = (h * int(_BASE) + ord(c) + 1) % (1 << 64)
        return h

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> self._shift).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The piece of each hash, or -1."""
        slot = self._slot(keys)
        at = self._first[slot]
        hit = (at >= 0) & (self._keys[at] == keys)
        crowd = self._crowded[slot] & ~hit
        out = np.where(hit, self._order[at], -1)
        if crowd.any():
            some = keys[crowd]
            pos = np.minimum(np.searchsorted(self._keys, some), len(self._keys) - 1)
            out[crowd] = np.where(self._keys[pos] == some, self._order[pos], -1)
        return out

    def lattice(self, words: list[str]) -> dict[tuple[int, int], np.ndarray]:
        """For words of one length: the piece of each span (start, stop), -1 where there is none."""
        n = len(words[0])
        codes = np.frombuffer("".join(words).encode("utf-32-le"), dtype="<u4").reshape(len(words), n).astype(np.uint64) + np.uint64(1)
        prefix = np.zeros((n + 1, len(words)), dtype=np.uint64)
        for i in range(n):
            prefix[i + 1] = prefix[i] * _BASE + codes[:, i]
        spans = [(i, j) for j in range(1, n + 1) for i in range(max(0, j - self.longest), j)]
        keys = np.stack([prefix[j] - prefix[i] * self._power[j - i] for i, j in spans])
        return dict(zip(spans, self.find(keys.ravel()).reshape(keys.shape), strict=True))


    def ends(self, text: str, first: int, last: int) -> np.ndarray:
        """(places, lengths): the piece that ends before each place from first + 1 to last of a text, for each length up to the longest; -1 where there is none."""
        low = max(0, first - self.longest)
        codes = np.frombuffer(text[low:last].encode("utf-32-le"), dtype="<u4").astype(np.uint64) + np.uint64(1)
        out = np.full((last - first, self.longest), -1, dtype=np.int64)
        for k in range(1, self.longest + 1):
            start = np.arange(max(low, first + 1 - k), last + 1 - k)
            if len(start):
                key = np.zeros(len(start), np.uint64)
                for i in range(k):
                    key = key * _BASE + codes[start - low + i]
                out[start + k - 1 - first, k - 1] = self.find(key)
        return out


@functools.lru_cache(maxsize=2)
def piece_table(path: str) -> PieceTable:
    return PieceTable(path)


def chunks(word: str) -> list[str]:
    marked = MARK + word
    return [marked[i : i + CHUNK] for i in range(0, len(marked), CHUNK)]


def _by_length(items: list[str]) -> dict[int, list[str]]:
    out: dict[int, list[str]] = {}
    for x in items:
        out.setdefault(len(x), []).append(x)
    return out


def forward_logs(table: PieceTable, probs: np.ndarray, words: list[str], block: int = 1 << 13) -> np.ndarray:
    """(words, languages): the log of each chunk's probability. ``probs`` has a row per piece and a last row for unknown characters."""
    out = np.zeros((len(words), probs.shape[1]))
    where = {w: i for i, w in enumerate(words)}
    for n, same in _by_length(words).items():
        for at in range(0, len(same), block):
            some = same[at : at + block]
            lattice = table.lattice(some)
            alpha = np.zeros((n + 1, len(some), probs.shape[1]))
            alpha[0] = 1.0
            for (i, j), piece in lattice.items():
                if j - i == 1:
                    alpha[j] += alpha[i] * probs[piece]
                else:
                    got = np.flatnonzero(piece >= 0)
                    if len(got):
                        alpha[j, got] += alpha[i, got] * probs[piece[got]]
            out[[where[w] for w in some]] = np.log(alpha[n])
    return out


def long_log(table: PieceTable, probs: np.ndarray, text: str) -> np.ndarray:
    """The log probability of one long run under each language: the same recursion, rescaled every few characters."""
    back, total = table.longest, np.zeros(probs.shape[1])
    alpha = np.zeros((STRETCH + back, probs.shape[1]))
    alpha[back - 1] = 1.0
    for first in range(0, len(text), STRETCH):
        last = min(len(text), first + STRETCH)
        piece = table.ends(text, first, last)
        p = np.where(piece[:, :, None] >= 0, probs[piece], 0.0)
        p[:, 0] = np.where(piece[:, 0, None] >= 0, p[:, 0], probs[-1])
        p = np.ascontiguousarray(p[:, ::-1])
        for j in range(last - first):
            alpha[back + j] = (p[j] * alpha[j : back + j]).sum(axis=0)
            if j % 8 == 7 or j == last - first - 1:
                scale = alpha[back + j].copy()
                alpha[j + 1 : back + j + 1] /= scale
                total += np.log(scale)
        alpha[:back] = alpha[last - first : last - first + back].copy()
    return total


def learn(table: PieceTable, counts: Counter, rounds: int = ROUNDS) -> np.ndarray:
    """Piece probabilities of one language from its chunk counts, by expectation-maximisation."""
    size = len(table.pieces)
    p = np.full(size + 1, 1.0 / size)
    p[size] = FLOOR
    groups = [(n, np.array([counts[w] for w in words], dtype=float), table.lattice(words)) for n, words in _by_length(list(counts)).items()]
    for _ in range(rounds):
        got = np.zeros(size)
        for n, weight, lattice in groups:
            prob = {s: np.where(piece >= 0, p[piece], p[size] if s[1] - s[0] == 1 else 0.0) for s, piece in lattice.items()}
            alpha = [np.ones(len(weight))] + [np.zeros(len(weight)) for _ in range(n)]
            beta = [np.zeros(len(weight)) for _ in range(n)] + [np.ones(len(weight))]
            for (i, j), q in prob.items():
                alpha[j] += alpha[i] * q
            for (i, j), q in sorted(prob.items(), key=lambda x: -x[0][1]):
                beta[i] += q * beta[j]
            scale = weight / alpha[n]
            for (i, j), q in prob.items():
                piece = lattice[i, j]
                known = piece >= 0
                got += np.bincount(piece[known], (alpha[i] * q * beta[j] * scale)[known], size)
        p = np.append((got + 1e-3) / (got.sum() + 1e-3 * size), FLOOR)
    return p


class LanguageModel:
    """``languages`` and a probability for each piece (last row: an unknown character)."""

    def __init__(self, path: str, languages: list[str], probs: np.ndarray) -> None:
        self.path, self.languages, self.probs = path, languages, probs

    @classmethod
    def train(cls, path: str, texts: dict[str, list[str]]) -> LanguageModel:
        table, languages, columns = piece_table(path), sorted(texts), []
        for lang in languages:
            words = Counter(w for t in texts[lang] for w in letter_words(t))
            parts: Counter = Counter()
            for w, n in words.items():
                for c in chunks(w):
                    parts[c] += n
            columns.append(learn(table, parts))
        return cls(path, languages, np.stack(columns, axis=1) if columns else np.zeros((len(table.pieces) + 1, 0)))


class Scorer:
    """Scores texts in a worker; keeps the words it has seen."""

    def __init__(self, model: LanguageModel) -> None:
        self.model = model
        self._table = piece_table(model.path)
        self._start()

    def _start(self) -> None:
        self._index: dict[str, int] = {}
        self._logs = np.zeros((1 << 12, len(self.model.languages)))

    def _learn_words(self, new: list[str]) -> None:
        parts = sorted(MARK + w for w in new if len(w) < CHUNK)
        at = {c: i for i, c in enumerate(parts)}
        logs = forward_logs(self._table, self.model.probs, parts)
        need = len(self._index) + len(new)
        if need > len(self._logs):
            grown = np.zeros((max(need, 2 * len(self._logs)), self._logs.shape[1]))
            grown[: len(self._index)] = self._logs[: len(self._index)]
            self._logs = grown
        for w in new:
            i = self._index[w] = len(self._index)
            self._logs[i] = logs[at[MARK + w]] if len(w) < CHUNK else long_log(self._table, self.model.probs, MARK + w)

    def predict(self, texts: list[str]) -> list[tuple[str, float]]:
        out = []
        for at in range(0, len(texts), 256):
            words = [letter_words(t) for t in texts[at : at + 256]]
            if len(self._index) > KEPT_WORDS:
                # Common words come early; the half that came last goes.
                self._index = dict(islice(self._index.items(), KEPT_WORDS // 2))
            new = list(set().union(*words) - self._index.keys())
            if new and self.model.languages:
                self._learn_words(new)
            for w in words:
                if not w or not self.model.languages:
                    out.append(("und", 0.0))
                    continue
                total = self._logs[np.fromiter(map(self._index.__getitem__, w), dtype=np.int64, count=len(w))].sum(axis=0)
                odds = np.exp(total - total.max())
                best = int(total.argmax())
                out.append((self.model.languages[best], float(odds[best] / odds.sum())))
        return out


_scorers: dict[int, Scorer] = {}


def scorer(model: LanguageModel) -> Scorer:
    """One scorer per model in a process."""
    key = zlib.crc32(model.probs.tobytes() + repr(model.languages).encode())
    claim("langid", _scorers.clear)
    if key not in _scorers:
        _scorers.clear()
        _scorers[key] = Scorer(model)
    return _scorers[key]


def held_out() -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def fit(docs: DataFrame, path: str | None = None, size: int = TRAIN_DOCS) -> LanguageModel:
    """A model from labelled rows that are not held out."""
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    texts: dict[str, list[str]] = {}
    for lang, text in bounded_sample(rows.select("doc_id", "lang", "text"), "doc_id", size, "lang").select("lang", "text").collect():
        texts.setdefault(lang, []).append(text)
    return LanguageModel.train(path or default_path(), texts)


def predict_documents(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) of every document."""

    def make():
        judge = scorer(model)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            lang, score = zip(*judge.predict(column_text(batch, "text")), strict=True)
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(lang, pa.string()), pa.array(score, pa.float64())], ["doc_id", "lang_pred", "score"])

        return step

    kind = docs.schema["doc_id"].dataType.simpleString()
    got = map_batches(docs.select("doc_id", "text"), make, f"doc_id {kind}, lang_pred string, score double")
    return got.select("doc_id", held_out().alias("held_out"), "lang_pred", "score")


def keep_recognised(docs: DataFrame, model: LanguageModel, least: float = 0.5) -> DataFrame:
    """The rows, as they are, of documents whose language is recognised with at least that score."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = scorer(model)
        for batch in batches:
            for part in slices(batch, "text"):
                yield part.filter(pa.array([lang != "und" and s >= least for lang, s in judge.predict(column_text(part, "text"))]))

    limit_batches(docs.sparkSession)
    return docs.mapInArrow(run, docs.schema)
