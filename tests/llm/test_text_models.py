import random
import re
import time
import zlib
from collections import Counter

import numpy as np

from commlens.llm import html_text, langid, quality, toxicity


def words(alphabet, n, seed):
    rng = random.Random(seed)
    return " ".join("".join(rng.choice(alphabet) for _ in range(rng.randint(2, 7))) for _ in range(n))


def brute_base(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    often = {k for k, n in Counter(windows).items() if n > 1}
    covered = {i + k for i, x in enumerate(windows) if x in often for k in range(3)}
    return len(w), sum(map(len, w)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


def test_base_counts():
    rng = random.Random(4)
    for _ in range(200):
        text = "".join(rng.choice(["a", "b", " ", "\n", "é ", "a b c ", "#|", "\x0b"]) for _ in range(rng.randint(0, 80)))
        raw = text.encode()
        w = raw.split()
        assert quality.base_counts(raw, w, quality.WordIndex(w)) == brute_base(text), repr(text)


def test_every_trusted_document_counts(spark):
    """More good labels than any sample held: the counts and the threshold see all of them."""
    n = 20_500
    docs = spark.range(n).selectExpr("id AS doc_id", "repeat(concat('w', id % 50, ' x', id % 7, ' '), 2) AS text")
    trusted = quality.trusted_ids(docs.selectExpr("doc_id", "1 AS quality"))
    assert trusted.count() == n
    assert np.abs(quality.log_ratios(docs, trusted)).max() == 0
    scored = spark.range(n).selectExpr("id AS doc_id", "false AS base_failed", "CAST(id * 37 % 20500 AS double) AS score")
    assert abs(quality.fitted_threshold(scored, trusted) - (np.quantile(np.arange(n), quality.QUANTILE) - quality.MARGIN)) < 1e-9


def test_quality_verdicts(spark, documents):
    good, bad = words("abcdefgh", 15, 1).split(), words("#$%&*xyz", 15, 2).split()
    rows = [(100 + i, " ".join(random.Random(i).choices(good if i % 4 else bad, k=120)), 0 if i % 4 == 0 else 1) for i in range(120)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id bigint, text string")
    labels = spark.createDataFrame([(r[0], r[2], 0) for r in rows if r[0] % 2], "doc_id bigint, quality int, toxic int").union(spark.createDataFrame([(None, 1, 0)], "doc_id bigint, quality int, toxic int"))
    kept = {r.doc_id: r.kept for r in quality.judge_documents(docs, labels).collect()}
    assert all(kept[i] == bool(q) for i, _, q in rows)
    odd = {r.doc_id: r for r in quality.judge_documents(documents, labels).collect()}
    assert odd[3].n_words == 0 and odd[3].base_failed and not odd[4].kept and odd[5].n_words == 20_000
    assert quality.judge_documents(docs, labels.limit(0)).where("kept").count() == 120
    assert quality.judge_documents(docs.limit(0), labels).count() == 0


def test_language_forward_is_exact():
    model = langid.LanguageModel.train(langid.default_path(), {"a": [words("abcd", 300, 1)], "b": [words("efgh", 300, 2)]})
    table = langid.piece_table(model.path)
    number = {p: i for i, p in enumerate(table.pieces)}

    def brute(word):
        alpha = [np.ones(2)]
        for j in range(1, len(word) + 1):
            alpha.append(sum((alpha[i] * model.probs[number.get(word[i:j], -1)] for i in range(max(0, j - table.longest), j) if word[i:j] in number or j - i == 1), np.zeros(2)))
        return np.log(alpha[-1])

    some = [c for w in ["the", "abcdabcd", "efgh", "ñandú", "x", "q" * 30] for c in langid.chunks(w)]
    assert np.allclose(langid.forward_logs(table, model.probs, some), [brute(c) for c in some])
    for stretch in (5, 4096):
        langid.STRETCH = stretch
        for run in ["▁abcdabcd", "▁" + "ñandúefgh" * 6]:
            assert np.allclose(langid.long_log(table, model.probs, run), brute(run))


def test_language_predictions(spark, documents):
    rows = [(i, words("abcdeé" if i % 2 else "fghijß", 30, i), "aa" if i % 2 else "ff") for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    model = langid.fit(docs)
    got = {r.doc_id: r for r in langid.predict_documents(docs, model).collect()}
    assert all(got[i].lang_pred == lang and got[i].score > 0.9 for i, _, lang in rows)
    odd = {r.doc_id: r for r in langid.predict_documents(documents, model).collect()}
    assert odd[3].lang_pred == odd[4].lang_pred == odd[7].lang_pred == "und" and odd[3].score == 0
    kept = langid.keep_recognised(documents, model)
    assert kept.columns == documents.columns and {r.doc_id for r in kept.collect()}.isdisjoint({3, 4, 7})
    assert {r.lang_pred for r in langid.predict_documents(docs, langid.fit(docs.limit(0))).collect()} == {"und"}


def test_toxicity_gradient():
    texts = [words("abc", 40, i) for i in range(6)]
    vocab, net = toxicity.Vocabulary(), toxicity.Network(1)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    rows = np.concatenate([toxicity.windows(vocab.add(toxicity.words_of(t))) for t in texts])
    slots, y = vocab.slots(0, len(vocab.word)), (np.arange(len(rows)) % 2).astype(float)

    def loss():
        x = net.inputs(*slots)
        pre = net.parts(x)
        z = net.forward(pre[0][rows], pre[1][rows]).astype(float)
        return float(np.mean(np.log1p(np.exp(z)) - y * z))

    grads = net.gradients(slots, rows, y)
    for name in ("xf", "hf", "hr", "br", "att", "key", "out", "bias", "word", "gram"):
        flat, g = net.p[name].reshape(-1), grads[name].reshape(-1)
        at = int(np.abs(g).argmax())
        old, step = flat[at], 3e-3
        flat[at] = old + step
        up = loss()
        flat[at] = old - step
        down = loss()
        flat[at] = old
        assert abs((up - down) / (2 * step) - g[at]) < 2e-2 * abs(g[at]) + 2e-4, name


def test_toxicity_catches_stems(spark, documents):
    rows, common = [], words("abcdefghij", 300, 1).split()
    for i in range(1500):
        text = random.Random(i).choices(common, k=60)
        if i % 3 == 0:
            for k in (0, 20, 41):
                text[(i + k) % 60] = "zqxv" + text[k]
        rows.append((i, " ".join(text), int(i % 3 == 0)))
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id bigint, text string")
    labels = spark.createDataFrame([(r[0], 1, r[2]) for r in rows], "doc_id bigint, quality int, toxic int")
    net, share = toxicity.fit(docs, labels)
    got = {r.doc_id: r for r in toxicity.score_documents(docs, net, share).collect()}
    held = [(got[i].predicted, y) for i, _, y in rows if got[i].held_out]
    assert len(held) > 200 and sum(p == y for p, y in held) >= 0.95 * len(held)
    assert all(0 <= r.score <= 1 for r in toxicity.score_documents(documents, net, share).collect())
    assert toxicity.score_documents(documents, *toxicity.fit(docs, labels.limit(0))).where("score > 0").count() == 0


def test_toxicity_scores_against_plain_loops():
    """A text's score is the largest over its windows of a network read gate by gate."""
    net, rng = toxicity.Network(3), random.Random(2)
    texts = ["", "a", " ".join(rng.choices(["ab", "cde", "fghij", "x" * 60], k=75)), "w " * 33]
    sig = lambda x: 1 / (1 + np.exp(-x))
    p, width, hidden = net.p, toxicity.WIDTH, toxicity.HIDDEN

    def vector(word):
        if word is None:
            return np.zeros(2 * width)
        marked = f"<{word}>".encode()
        grams = [zlib.crc32(marked[i : i + k]) % toxicity.SLOTS for k in (3, 4, 5) for i in range(max(0, len(marked) - k) + 1)]
        return np.concatenate([p["word"][1 + zlib.crc32(word.encode()) % (toxicity.SLOTS - 1)], np.mean([p["gram"][g] for g in grams], axis=0)])

    def logit(window):
        states = {}
        for d, order in (("f", range(32)), ("r", range(31, -1, -1))):
            s, out = np.zeros(hidden), [None] * 32
            for t in order:
                x, u = window[t] @ p["x" + d] + p["b" + d], s @ p["h" + d]
                z, r = sig(x[:hidden] + u[:hidden]), sig(x[hidden : 2 * hidden] + u[hidden : 2 * hidden])
                s = z * s + (1 - z) * np.tanh(x[2 * hidden :] + r * u[2 * hidden :])
                out[t] = s
            states[d] = out
        h = [np.concatenate([states["f"][t], states["r"][t]]) for t in range(32)]
        e = np.array([(np.tanh(v @ p["att"]) @ p["key"])[0] for v in h])
        w = np.exp(e) / np.exp(e).sum()
        return (sum(a * v for a, v in zip(w, h, strict=True)) @ p["out"])[0] + p["bias"][0]

    want = []
    for text in texts:
        words = toxicity.words_of(text)
        starts = [0] if len(words) <= 32 else sorted({*range(0, len(words) - 32, toxicity.STRIDE), len(words) - 32})
        want.append(max(sig(logit([vector(w) for w in [*words[a : a + 32], *[None] * (32 - len(words))][:32]])) for a in starts))
    assert np.allclose(toxicity.Scorer(net).score(texts), want, atol=1e-5)


def test_quality_ratio_and_verdict_against_counts(spark):
    """Scores from plain dictionaries of cells, and the verdict they give."""
    rng = random.Random(9)
    rows = [(i, " ".join(rng.choices([f"aé{k}" for k in range(60)] if i % 3 else [f"q{k}" for k in range(80)], k=70))) for i in range(90)] + [(90, None), (91, "few words")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(0, 90, 2)], "doc_id bigint, quality int")
    mix, top = 0x9E3779B97F4A7C15, 64 - quality.BUCKETS.bit_length() + 1

    def cells(text):
        h = [zlib.crc32(w.encode()) for w in (text or "").split()]
        return [x * mix % 2**64 >> top for x in h] + [(a * 31 + b + 1) * mix % 2**64 >> top for a, b in zip(h, h[1:], strict=False)]

    good_ids = {r.doc_id for r in labels.collect() if r.quality}
    raw, good = Counter(c for _, t in rows for c in cells(t)), Counter(c for i, t in rows if i in good_ids for c in cells(t))
    n_raw, n_good = sum(raw.values()) + quality.BUCKETS, sum(good.values()) + quality.BUCKETS
    score = {i: np.mean([np.log((good[c] + 1) / n_good) - np.log((raw[c] + 1) / n_raw) for c in cells(t)]) if t else 0.0 for i, t in rows}
    got = {r.doc_id: r for r in quality.judge_documents(docs, labels).collect()}
    assert all(abs(got[i].score - s) < 1e-9 for i, s in score.items())
    line = np.quantile([score[i] for i in good_ids if not got[i].base_failed], quality.QUANTILE) - quality.MARGIN
    assert all(r.kept == (not r.base_failed and score[i] >= line) for i, r in got.items()) and len({r.kept for r in got.values()}) == 2


def test_deep_pages_and_messages_node_by_node():
    model = html_text.ContentModel.train(html_text.labelled_pages(30, 1), steps=10)
    forest = html_text.Forest([html_text.Page(s) for s in html_text.labelled_pages(12, 5)])
    for a, b in zip(forest.marginals(model.weights, model.edges), forest._one_by_one(model.weights, model.edges), strict=True):
        assert np.allclose(a, b)
    for source in ("<div>a" * 50_000, "<head><blockquote>" + "<p>a<td><option></option><body>" * 20_000, "</b>" * 50_000 + "<ul>" * 20_000 + "<li></li>" * 20_000):
        began = time.time()
        assert len(model.texts([source])) == 1 and time.time() - began < 10


def test_page_marginals_are_exact():
    """Sum-product against the sum over all labelings of small trees."""
    model = html_text.ContentModel.train(html_text.labelled_pages(30, 1), steps=10)
    page = html_text.Page("<body><div class=menu>a b</div><article><p>c d e<p>f</article></body>")
    forest = html_text.Forest([page])
    p, _ = forest.marginals(model.weights, model.edges)
    n, s = len(page.parent), forest.scores(model.weights)
    total = np.zeros(n)
    z = 0.0
    for code in range(1 << n):
        y = [code >> i & 1 for i in range(n)]
        w = np.exp(sum(s[i] * y[i] for i in range(n)) + sum(model.edges[forest.kind[i], y[page.parent[i]], y[i]] for i in range(1, n)))
        z += w
        total += w * np.array(y)
    assert np.allclose(p, total / z)


def test_page_texts(spark):
    source = """<html><head><title>T</title><script>var t="</p>";</script></head><body><nav><a href=x>Menu</a></nav><div class="cookie notice">We use cookies.</div>
    <article><h1>A  &amp; B</h1><p><b>One&nbsp;two.<br><p>three<!-- x --> four</p><ul><li>five<li>six</ul></article><section class="comments"><p>I like this article a lot.</p></section>
    <aside>Other things</aside><form><p>Subscribe</p></form><footer>&copy; me</footer>"""
    rows = [(1, "u", source), (2, "u", None), (3, "u", ""), (4, None, "<article>plain < text"), (4, None, "<article>plain < text"), (5, "u", "<p>" * 3000 + "x"), (6, "u", "<script>a<p>b")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").selectExpr("*", "1 AS text")
    got = {r.page_id: r for r in html_text.extract_pages(pages).collect()}
    assert got[1].text == "A & B\nOne two.\nthree four\nfive\nsix"
    assert got[1].n_chars == len(got[1].text)
    assert got[2].text == got[3].text == got[6].text == "" and got[4].text == "plain < text"
    assert html_text.extract_pages(pages.limit(0)).count() == 0
