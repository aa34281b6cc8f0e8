import hashlib

import numpy as np
from tokenizers import Tokenizer

import corpus_pipeline
from commlens.llm import bpe, registry
from commlens.llm.common import documents

SF = "/root/testdata/sf0.001"


def test_stages_chain(spark, tmp_path):
    docs = documents(spark, SF)
    columns = docs.columns
    seen = [docs.count()]
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, SF)
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        seen.append(docs.count())
        if name != "bpe":
            assert docs.columns == columns
        if name == "near_duplicates":
            ids = [r.doc_id for r in docs.select("doc_id").collect()]
            assert len(ids) == len(set(ids))
        if name == "mixing":
            texts = {r.doc_id: r.text for r in docs.collect()}
    assert seen[0] >= seen[1] >= seen[2] == seen[3] and seen[2] < seen[1]
    tok = Tokenizer.from_file(bpe.default_path())
    for r in docs.collect():
        ids = tok.encode(texts[r.doc_id], add_special_tokens=False).ids
        assert r.ids == ids and r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()


def test_every_operator_is_registered():
    names = registry.queries()
    assert {n.split("_")[0] for n in names} == {*(f"op{i}" for i in range(1, 11)), "pipeline"}
    assert 4 <= len(corpus_pipeline.STAGES) <= 5


def test_run_against_brute_force(spark, tmp_path):
    """All stages by plain means: predictions of the model, all pairs of shingle sets, regular expressions, SQL over the rest, the library."""
    import duckdb
    from test_links_media import brute_redacted

    from commlens.llm import langid, mixing

    docs = documents(spark, SF)
    rows = [r.asDict() for r in docs.collect()]
    judge = langid.scorer(langid.fit(docs))
    rows = [r for r, (lang, score) in zip(rows, judge.predict([r["text"] or "" for r in rows]), strict=True) if lang != "und" and score >= 0.5]

    def grams(text):
        w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").encode().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    rows.sort(key=lambda r: r["doc_id"])
    sets, root = [grams(r["text"]) for r in rows], list(range(len(rows)))
    for i, a in enumerate(sets):
        for j in range(i):
            if len(a & sets[j]) >= 0.8 * len(a | sets[j]):
                old, new = max(root[i], root[j]), min(root[i], root[j])
                root = [new if x == old else x for x in root]
    rows = [r for i, r in enumerate(rows) if root[i] == i]
    for r in rows:
        r["text"] = brute_redacted(r["text"])
    spark.createDataFrame(rows, docs.schema).write.parquet(str(tmp_path / "documents"))
    db = duckdb.connect()
    db.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{tmp_path}/documents/*.parquet')")
    copies = {r[0]: r[-1] for r in db.execute(mixing.SQL).fetchall()}
    tok = Tokenizer.from_file(bpe.default_path())
    want = []
    for r in rows:
        ids = tok.encode(r["text"], add_special_tokens=False).ids
        want += [(r["doc_id"], hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())] * copies[r["doc_id"]]
    got = corpus_pipeline.run(spark, SF)
    assert sorted((r.doc_id, r.ids_sha256) for r in got.collect()) == sorted(want) and len(want) > 50
