import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from commlens.llm import bpe, token_store

ODD = ["", "  ", "<|endoftext|> a <|startoftext|>b", "ΑΣ ΣΑΣ ǅ İstanbul naïve é ﬁ", "hello 'S it's WE'LL 123 ½ ٣ 你好 👍🏽‍ x y\x1c z\x85w", "a" * 400 + "!" * 90 + "</w> w>", "a  b　c", "x. y, .. z's, 5, ., , .a", "a\nb.\nc, d", " a\n\nb "]


def made(n=300, seed=1):
    rng = random.Random(seed)
    parts = ["th", "er", "ing", "Ño", "é", "ß", "x9", "###", "'s", ".", " ", "\n", "  ", "ZZ", "12", "schön"]
    return ["".join(rng.choice(parts) for _ in range(rng.randint(0, 60))) for _ in range(n)]


def test_word_bpe_is_exact():
    tok, own = Tokenizer.from_file(bpe.default_path()), bpe.word_bpe(bpe.default_path())
    for text in [*ODD, *made()]:
        want = tok.encode(text, add_special_tokens=False).ids
        got = own.encode(text)
        assert got.tolist() == want, text
        assert own.decode_bytes(got).decode() == tok.decode(want, skip_special_tokens=False)


def test_word_bpe_over_newer_characters():
    """Code points on which the Unicode versions of Python, regex and the library differ, and all others up to U+2FFF."""
    tok, own = Tokenizer.from_file(bpe.default_path()), bpe.word_bpe(bpe.default_path())
    chars = sorted({*own._newer, *map(chr, range(0x80, 0x3000))})
    assert len(chars) > 20_000
    for shape in ("a%sb", "1%s2%s", "a%s\u0301", "\u0915\u0323%s\u0301x"):
        texts = [shape.replace("%s", c) for c in chars]
        for text, want in zip(texts, tok.encode_batch(texts, add_special_tokens=False), strict=True):
            assert own.encode(text).tolist() == want.ids, text


def test_round_trip_rows(spark, documents, texts):
    tok = Tokenizer.from_file(bpe.default_path())
    got = sorted((r.doc_id is None, r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.round_trip_digests(documents).collect())
    want = []
    for i, t in texts:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        want.append((i is None, i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(tok.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert got == sorted(want)
    assert bpe.round_trip_digests(documents.limit(0)).count() == 0
    decoded = {r.doc_id: r.text for r in bpe.decode_documents(bpe.encode_documents(documents)).collect()}
    assert decoded[4] == "" and decoded[1].startswith("the</w> quick</w>")


@pytest.mark.parametrize("values", [[0], [0, 0, 0], [0, 5, 5, 9, 1 << 33], [0] * 300 + [1 << 20] * 200, list(range(0, 5000, 7))])
def test_elias_fano(values):
    ef = token_store.EliasFano.of(np.array(values))
    back, used = token_store.EliasFano.from_bytes(memoryview(ef.to_bytes()))
    assert used == len(ef.to_bytes())
    assert back.values().tolist() == values
    assert [back.select(i) for i in range(len(values))] == values
    assert back.select_many(np.arange(len(values))[::-1]).tolist() == values[::-1]
    with pytest.raises(IndexError):
        back.select_many(np.array([0, len(values)]))
    with pytest.raises(IndexError):
        back.select(len(values))


def test_piece_encoder_is_exact():
    tok, own = Tokenizer.from_file(token_store.default_path()), token_store.piece_encoder(token_store.default_path())
    texts = [*ODD, *made(400, 2), None]
    for text, got in zip(texts, own.encode(pa.array(texts)), strict=True):
        assert got.tolist() == tok.encode(text or "", add_special_tokens=False).ids, text


def test_store_round_trip(spark, documents, texts):
    tok = Tokenizer.from_file(token_store.default_path())
    got = token_store.round_trip(spark, documents).collect()
    start, want = 0, []
    for i, t in sorted(texts, key=lambda x: (x[0] is not None, x[0] or 0, x[1] or "")):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((i, start, len(ids), zlib.crc32(ids)))
        start += len(ids)
    assert sorted(map(tuple, got), key=lambda r: r[1]) == want
    assert token_store.round_trip(spark, documents.limit(0)).count() == 0
