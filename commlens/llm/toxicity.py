"""Toxicity by a bidirectional gated recurrent network with attention pooling, trained here in numpy.

A word enters as the join of a word vector (hashed) and the mean of the vectors of its character n-grams (hashed),
so that unseen forms of known stems are caught. Two gated recurrent layers read a window of WINDOW
words in both directions; attention pools their states to one logit. A text is scored over all windows of
WINDOW words that start every STRIDE words, overlapping, the last one ending with the text; its score is the largest.

Labels are of whole texts, so training chooses windows: first by a ratio of word and n-gram counts of the labelled classes,
then again and again by the network's own scores (the best of toxic texts, the worst and some others of clean ones).

Bounds: at most TRAIN_DOCS toxic and CLEAN_DOCS clean labelled texts, whole, train the network; every document is scored over its
whole text. Windows overlap by WINDOW - STRIDE words, so a passage of up to that many words and one lies whole in one of them.

Cases: null and empty texts are scored as one empty window; repeated rows each get a row; contradicting or
null labels are left out; without both classes every score is the share of toxic labels (0 if none); an
empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens.llm.common import bounded_sample, claim, column_text, map_batches

TRAIN_DOCS, CLEAN_DOCS = 1_200, 3_000
WINDOW, STRIDE = 32, 24
THRESHOLD = 0.3
HIDDEN, WIDTH = 12, 10
SLOTS = 1 << 13
#: Passes over the chosen windows; small sets get as many as give LEAST_STEPS steps.
EPOCHS, LEAST_STEPS, BATCH, RATE = 7, 100, 256, 0.01
#: Shares of word vectors and of n-gram vectors left out of a training step at random, so that forms not seen are judged by their parts.
DROP_WORDS, DROP_GRAMS = 0.3, 0.1
KEPT_WORDS = 200_000
_WORD = re.compile(r"\w+")
#: The word number of padding.
PAD = 0


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def grams_of(word: str) -> list[int]:
    """Slots of the character n-grams, of three to five letters, of a marked word."""
    marked = f"<{word}>".encode()
    n = len(marked)
    return [zlib.crc32(marked[i : i + k]) % SLOTS for k in (3, 4, 5) for i in range(max(0, n - k) + 1)]


class Vocabulary:
    """Words numbered from one; number zero is padding. ``word`` is a word's slot, its n-gram slots lie in one long array."""

    def __init__(self) -> None:
        self.index: dict[str, int] = {}
        self.word = array("i", [0])
        self.grams = array("i", [0])
        self.stop = array("q", [0, 1])

    def slots(self, first: int, last: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Word slots, flat n-gram slots and their counts, of the words numbered from first to before last."""
        stop = np.array(self.stop[first : last + 1])
        return np.array(self.word[first:last]), np.array(self.grams[stop[0] : stop[-1]]), np.diff(stop)

    def add(self, words: list[str]) -> np.ndarray:
        out = np.empty(len(words), dtype=np.int64)
        index = self.index
        for k, w in enumerate(words):
            i = index.get(w)
            if i is None:
                i = index[w] = len(self.word)
                self.word.append(1 + zlib.crc32(w.encode()) % (SLOTS - 1))
                self.grams.extend(grams_of(w))
                self.stop.append(len(self.grams))
            out[k] = i
        return out


def windows(ids: np.ndarray) -> np.ndarray:
    """All windows of a text's word numbers, one row each; a short text is padded."""
    n = len(ids)
    if n <= WINDOW:
        row = np.full((1, WINDOW), PAD, dtype=np.int64)
        row[0, :n] = ids
        return row
    starts = np.append(np.arange(0, n - WINDOW, STRIDE), n - WINDOW)
    return ids[starts[:, None] + np.arange(WINDOW)]


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1.0 / (1.0 + np.exp(-x))


def _pooled_bag(table: np.ndarray, flat: np.ndarray, counts: np.ndarray) -> np.ndarray:
    starts = np.concatenate([[0], np.cumsum(counts)[:-1]])
    return np.add.reduceat(table[flat], starts, axis=0) / counts[:, None].astype(np.float32)


def _of(slots: tuple[np.ndarray, np.ndarray, np.ndarray], numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The slots of some of all words."""
    word, grams, every = slots
    counts = every[numbers]
    start = (np.cumsum(every) - every)[numbers]
    ends = np.cumsum(counts)
    return word[numbers], grams[np.arange(ends[-1]) + np.repeat(start - ends + counts, counts)], counts


def _sum_by(at: np.ndarray, rows: np.ndarray, size: int) -> np.ndarray:
    """Sums of the rows of each place."""
    return np.stack([np.bincount(at, rows[:, k], size) for k in range(rows.shape[1])], axis=1).astype(np.float32)


class Network:
    """Parameters, forward pass and gradients. Per direction: ``x`` input weights (2 * WIDTH, 3 * HIDDEN), ``h`` state
    weights (HIDDEN, 3 * HIDDEN) and ``b``; the thirds are update gate, reset gate and candidate."""

    def __init__(self, seed: int = 5) -> None:
        rng = np.random.default_rng(seed)
        near = lambda *shape: (rng.standard_normal(shape) * 0.3 / np.sqrt(shape[0])).astype(np.float32)
        self.p: dict[str, np.ndarray] = {"word": near(SLOTS, WIDTH) * 20, "gram": near(SLOTS, WIDTH) * 20}
        for d in ("f", "r"):
            self.p |= {f"x{d}": near(2 * WIDTH, 3 * HIDDEN) * 3, f"h{d}": near(HIDDEN, 3 * HIDDEN) * 2, f"b{d}": np.zeros(3 * HIDDEN, np.float32)}
        self.p |= {"att": near(2 * HIDDEN, HIDDEN) * 3, "key": near(HIDDEN, 1) * 3, "out": near(2 * HIDDEN, 1) * 3, "bias": np.zeros(1, np.float32)}

    def inputs(self, word: np.ndarray, flat: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Vectors of words, from their slots."""
        x = np.concatenate([self.p["word"][word], _pooled_bag(self.p["gram"], flat, counts)], axis=1)
        x[word == 0] = 0
        return x

    def _read(self, pre: np.ndarray, h: np.ndarray, back: bool, keep: list | None) -> np.ndarray:
        """States of one direction; ``pre`` (windows, WINDOW, 3 * HIDDEN)."""
        n, H = pre.shape[0], HIDDEN
        states = np.empty((n, WINDOW, H), np.float32)
        s = np.zeros((n, H), np.float32)
        for t in range(WINDOW - 1, -1, -1) if back else range(WINDOW):
            u = s @ h
            zr = _sigmoid(pre[:, t, : 2 * H] + u[:, : 2 * H])
            z, r = zr[:, :H], zr[:, H:]
            c = np.tanh(pre[:, t, 2 * H :] + r * u[:, 2 * H :])
            if keep is not None:
                keep.append((t, s, z, r, c, u[:, 2 * H :]))
            s = c + z * (s - c)
            states[:, t] = s
        return states

    def forward(self, pre_f: np.ndarray, pre_r: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Logits of windows from the input parts of both directions."""
        p, f, r = self.p, None, None
        if keep is not None:
            f, r = keep["f"], keep["r"] = [], []
        h = np.concatenate([self._read(pre_f, p["hf"], False, f), self._read(pre_r, p["hr"], True, r)], axis=2)
        a = np.tanh(h @ p["att"])
        e = (a @ p["key"])[:, :, 0]
        w = np.exp(e - e.max(axis=1, keepdims=True))
        w /= w.sum(axis=1, keepdims=True)
        pooled = np.einsum("nt,nth->nh", w, h)
        if keep is not None:
            keep |= {"h": h, "a": a, "w": w, "pooled": pooled}
        return (pooled @ p["out"])[:, 0] + p["bias"][0]

    def parts(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return x @ self.p["xf"] + self.p["bf"], x @ self.p["xr"] + self.p["br"]

    def _unread(self, steps: list, dstates: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Gradients of ``pre`` and ``h`` of one direction."""
        H = HIDDEN
        dpre = np.zeros((*dstates.shape[:2], 3 * H), np.float32)
        dh, ds = np.zeros_like(h), np.zeros_like(dstates[:, 0])
        for t, s, z, r, c, uc in reversed(steps):
            ds = ds + dstates[:, t]
            dc = ds * (1 - z) * (1 - c * c)
            dz = ds * (s - c) * z * (1 - z)
            dr = dc * uc * r * (1 - r)
            dpre[:, t] = np.concatenate([dz, dr, dc], axis=1)
            du = np.concatenate([dz, dr, dc * r], axis=1)
            dh += s.T @ du
            ds = ds * z + du @ h.T
        return dpre, dh

    def gradients(self, slots: tuple[np.ndarray, np.ndarray, np.ndarray], rows: np.ndarray, y: np.ndarray, rng: np.random.Generator | None = None) -> dict[str, np.ndarray]:
        p, keep = self.p, {}
        numbers, at = np.unique(rows, return_inverse=True)
        at = at.reshape(rows.shape)
        word, flat, counts = _of(slots, numbers)
        x = self.inputs(word, flat, counts)
        kept = np.ones_like(x)
        if rng is not None:
            kept[:, :WIDTH] = (rng.random((len(x), 1)) >= DROP_WORDS) / (1 - DROP_WORDS)
            kept[:, WIDTH:] = (rng.random((len(x), 1)) >= DROP_GRAMS) / (1 - DROP_GRAMS)
            x = x * kept
        pre_f, pre_r = self.parts(x)
        logit = self.forward(pre_f[at], pre_r[at], keep)
        d = ((_sigmoid(logit) - y) / len(y)).astype(np.float32)
        g = {"bias": d.sum(keepdims=True), "out": keep["pooled"].T @ d[:, None]}
        dpool = d[:, None] * p["out"][:, 0]
        h, a, w = keep["h"], keep["a"], keep["w"]
        dh = w[:, :, None] * dpool[:, None, :]
        dw = np.einsum("nth,nh->nt", h, dpool)
        de = w * (dw - (w * dw).sum(axis=1, keepdims=True))
        g["key"] = np.einsum("nth,nt->h", a, de)[:, None]
        da = de[:, :, None] * p["key"][:, 0] * (1 - a * a)
        g["att"] = np.einsum("nti,ntj->ij", h, da)
        dh += da @ p["att"].T
        dx = np.zeros_like(x)
        for k, part, side in (("f", dh[:, :, :HIDDEN], pre_f), ("r", dh[:, :, HIDDEN:], pre_r)):
            dpre, g[f"h{k}"] = self._unread(keep[k], part, p[f"h{k}"])
            per_word = _sum_by(at.ravel(), dpre.reshape(-1, 3 * HIDDEN), len(side))
            g[f"x{k}"], g[f"b{k}"] = x.T @ per_word, per_word.sum(axis=0)
            dx += per_word @ p[f"x{k}"].T
        dx[numbers == PAD] = 0
        dx *= kept
        g["word"] = _sum_by(word, dx[:, :WIDTH], SLOTS)
        g["gram"] = _sum_by(flat, np.repeat(dx[:, WIDTH:] / counts[:, None].astype(np.float32), counts, axis=0), SLOTS)
        return g

    def logits(self, pre: tuple[np.ndarray, np.ndarray], rows: np.ndarray, block: int = 1024) -> np.ndarray:
        """Logits of windows, given the input parts of every word number."""
        out = np.empty(len(rows), np.float32)
        for i in range(0, len(rows), block):
            some = rows[i : i + block]
            out[i : i + block] = self.forward(pre[0][some], pre[1][some])
        return out


def _first_scores(slots: tuple[np.ndarray, np.ndarray, np.ndarray], rows: list[np.ndarray], y: np.ndarray) -> np.ndarray:
    """A score per word number: smoothed log ratio of the texts of either class with the word's slot and with its best n-gram slot."""
    seen = np.zeros((2, 2, SLOTS))
    for ids, label in zip(rows, y.astype(int).tolist(), strict=True):
        if len(ids):
            word, flat, _ = _of(slots, np.unique(ids))
            seen[label, 0, np.unique(word)] += 1
            seen[label, 1, np.unique(flat)] += 1
    n = np.array([(y == 0).sum(), (y == 1).sum()])
    ratio = np.log((seen[1] + 1) / (n[1] + 2)) - np.log((seen[0] + 1) / (n[0] + 2))
    word, grams, counts = slots
    out = ratio[0][word] + np.maximum.reduceat(ratio[1][grams], np.cumsum(counts) - counts)
    out[PAD] = 0
    return out


def train(texts: list[str], labels: list[int], epochs: int = EPOCHS, seed: int = 5) -> Network | None:
    """A network for texts with labels 0 and 1; none if a class is missing."""
    y = np.array(labels, dtype=np.float32)
    if not len(y) or y.min() == y.max():
        return None
    rng, vocab, net = np.random.default_rng(seed), Vocabulary(), Network(seed)
    ids = [vocab.add(words_of(t)) for t in texts]
    sets = [windows(i) for i in ids]
    rows = np.concatenate(sets)
    stops = np.cumsum([len(s) for s in sets])
    starts = stops - [len(s) for s in sets]
    slots = vocab.slots(0, len(vocab.word))
    value = _first_scores(slots, ids, y)[rows].max(axis=1)
    mean = {k: np.zeros_like(v) for k, v in net.p.items()}
    square = {k: np.zeros_like(v) for k, v in net.p.items()}
    step = 0
    epochs = max(epochs, -(-LEAST_STEPS // -(-int((3 - 2 * y).sum()) // BATCH)))
    for epoch in range(epochs):
        chosen, target = [], []
        for a, b, label in zip(starts, stops, y, strict=True):
            best = a + int(value[a:b].argmax())
            picks = [best] if label else [best, *rng.integers(a, b, 2)]
            chosen += picks
            target += [label] * len(picks)
        order = rng.permutation(len(chosen))
        chosen_rows, target_rows = rows[np.array(chosen)[order]], np.array(target, dtype=np.float32)[order]
        for i in range(0, len(order), BATCH):
            step += 1
            for k, g in net.gradients(slots, chosen_rows[i : i + BATCH], target_rows[i : i + BATCH], rng).items():
                mean[k] += 0.1 * (g - mean[k])
                square[k] += 0.001 * (g * g - square[k])
                net.p[k] -= RATE * (1 - epoch / (epochs + 1)) * (mean[k] / (1 - 0.9**step)) / (np.sqrt(square[k] / (1 - 0.999**step)) + 1e-8)
        if epoch + 1 < epochs:
            value = net.logits(net.parts(net.inputs(*slots)), rows)
    return net


class Scorer:
    """Scores texts in a worker; keeps the input parts of words it has seen."""

    def __init__(self, net: Network) -> None:
        self.net = net
        self._start()

    def _start(self) -> None:
        self.vocab = Vocabulary()
        self.done = 0
        self.pre = [np.zeros((1 << 12, 3 * HIDDEN), np.float32) for _ in range(2)]

    def _extend(self) -> None:
        n = len(self.vocab.word)
        if n == self.done:
            return
        if n > len(self.pre[0]):
            self.pre = [np.concatenate([p[: self.done], np.zeros((max(n, 2 * len(p)) - self.done, p.shape[1]), np.float32)]) for p in self.pre]
        for i in range(self.done, n, 1 << 14):
            last = min(n, i + (1 << 14))
            for whole, part in zip(self.pre, self.net.parts(self.net.inputs(*self.vocab.slots(i, last))), strict=True):
                whole[i:last] = part
        self.done = n

    def score(self, texts: list[str]) -> list[float]:
        out: list[float] = []
        for at in range(0, len(texts), 128):
            if len(self.vocab.word) > KEPT_WORDS:
                self._start()
            sets = [windows(self.vocab.add(words_of(t))) for t in texts[at : at + 128]]
            self._extend()
            logits = self.net.logits((self.pre[0], self.pre[1]), np.concatenate(sets))
            starts = np.cumsum([0, *(len(s) for s in sets[:-1])])
            out += _sigmoid(np.maximum.reduceat(logits, starts).astype(float)).tolist()
        return out


_scorers: dict[int, Scorer] = {}


def scorer(net: Network) -> Scorer:
    """One scorer per network in a process."""
    key = zlib.crc32(b"".join(v.tobytes() for v in net.p.values()))
    claim("toxicity", _scorers.clear)
    if key not in _scorers:
        _scorers.clear()
        _scorers[key] = Scorer(net)
    return _scorers[key]


def held_out() -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame) -> tuple[Network | None, float]:
    """A network from labelled documents that are not held out, and the share of toxic ones among them."""
    agreed = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out()).groupBy("doc_id").agg(F.min("toxic").alias("toxic"), F.max("toxic").alias("top")).where("toxic = top").select("doc_id", "toxic")
    some = [r for value, size in ((1, TRAIN_DOCS), (0, CLEAN_DOCS)) for r in bounded_sample(agreed.where(F.col("toxic") == value), "doc_id", size, "toxic").collect()]
    if not some:
        return None, 0.0
    picked = docs.sparkSession.createDataFrame([(int(i), int(t)) for i, t in some], "doc_id bigint, toxic int")
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").where("text is not null").orderBy("doc_id", "text").limit(2 * (TRAIN_DOCS + CLEAN_DOCS)).collect()
    share = sum(t for _, t in some) / len(some)
    return train([r.text for r in rows], [r.toxic for r in rows]), share


def score_documents(docs: DataFrame, net: Network | None, share: float = 0.0, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""

    def make():
        judge = scorer(net) if net else None

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = judge.score(column_text(batch, "text")) if judge else [share] * batch.num_rows
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(got, pa.float64())], ["doc_id", "score"])

        return step

    kind = docs.schema["doc_id"].dataType.simpleString()
    got = map_batches(docs.select("doc_id", "text"), make, f"doc_id {kind}, score double")
    return got.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
