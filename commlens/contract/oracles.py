"""DuckDB statements for the registered queries, put together from named common table expressions."""

from __future__ import annotations

import re

C, Z, BETA = 6, 8, 0.1
ALPHA, RHO = 50 / Z, 50 / C
NU = (0.05, 0.4, -0.05, 0.3)


def hashed(key: str, salt: int) -> str:
    return f"(((({key}) * 48271 + {salt}) % 2147483647) * 16807 % 2147483647)"


def uniform(key: str, salt: int) -> str:
    return f"(({hashed(key, salt)}::DOUBLE + 0.5) / 2147483647.0)"


def sigmoid(x: str) -> str:
    return f"(1 / (1 + exp(-({x}))))"


def pg_mean(b: str) -> str:
    return f"(CASE WHEN abs({b}) < 1e-6 THEN 0.25 ELSE tanh(({b}) / 2) / (2 * ({b})) END)"


def psi(w: str, a: str) -> str:
    return f"((({w}) - ({a}) * ({w}) * ({w})) / 2)"


def _indiv(s: str = "fs", d: str = "fd") -> str:
    cols = (f"{s}.popularity", f"{s}.activeness", f"{d}.popularity", f"{d}.activeness")
    return " + ".join(f"({w}) * coalesce({c}, 0)" for w, c in zip(NU, cols, strict=True))


#: Name -> body. A body may use any other name; ``statement`` puts in what is needed, in order.
CTES: dict[str, str] = {
    "bought": "SELECT o_orderkey AS doc_id, o_custkey AS user_id, o_orderdate AS ts, l_partkey, l_suppkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "words": "SELECT doc_id, user_id, unnest(string_split(lower(p_name || ' ' || p_brand || ' ' || p_type), ' ')) AS word FROM bought JOIN part ON l_partkey = p_partkey",
    "tokens0": "SELECT doc_id, user_id, word, count(*) AS cnt FROM words WHERE word <> '' GROUP BY ALL",
    "sizes": "SELECT doc_id, CAST(sum(cnt) AS BIGINT) AS n_tok FROM tokens0 GROUP BY doc_id HAVING sum(cnt) >= 2",
    "tokens": "SELECT t.* FROM tokens0 t SEMI JOIN sizes USING (doc_id)",
    "docs": "SELECT o_orderkey AS doc_id, o_custkey AS user_id, o_orderdate AS ts, CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS INT) AS tbin, n_tok FROM orders JOIN sizes ON o_orderkey = doc_id",
    "vocab": "SELECT word, row_number() OVER (ORDER BY word) - 1 AS word_id, count(*) AS df, CAST(sum(cnt) AS BIGINT) AS cf FROM tokens GROUP BY word",
    "member": "SELECT DISTINCT l_partkey, l_suppkey, user_id FROM bought",
    "small": "SELECT l_partkey, l_suppkey FROM member GROUP BY ALL HAVING count(*) > 1",
    "friends": "SELECT DISTINCT a.user_id AS src, b.user_id AS dst FROM (SELECT * FROM member SEMI JOIN small USING (l_partkey, l_suppkey)) a JOIN member b USING (l_partkey, l_suppkey) WHERE a.user_id <> b.user_id",
    "diffs": """SELECT DISTINCT doc_id AS src_doc, p_doc AS dst_doc, user_id AS src_user, p_user AS dst_user, CAST((year(ts) - 1995) * 12 + month(ts) - 1 AS INT) AS tbin
      FROM (SELECT *, lag(doc_id) OVER w AS p_doc, lag(user_id) OVER w AS p_user, lag(ts) OVER w AS p_ts FROM bought WINDOW w AS (PARTITION BY l_partkey ORDER BY ts, doc_id, l_linenumber))
      WHERE user_id <> p_user AND date_diff('day', p_ts, ts) BETWEEN 0 AND 14""",
    "assign": f"SELECT doc_id, user_id, CAST({hashed('doc_id', 101)} % {C} AS INT) AS c, CAST({hashed('doc_id', 202)} // 64 % {Z} AS INT) AS z FROM docs",
    "uc": "SELECT user_id, c, count(*) AS n FROM assign GROUP BY ALL",
    "ct": "SELECT c, z, count(*) AS n FROM assign GROUP BY ALL",
    "tw": "SELECT z, word, CAST(sum(cnt) AS BIGINT) AS n FROM tokens JOIN assign USING (doc_id) GROUP BY ALL",
    "tt": "SELECT z, tbin, count(*) AS n FROM assign JOIN docs USING (doc_id) GROUP BY ALL",
    "pi": "SELECT user_id, c, n / sum(n) OVER (PARTITION BY user_id) AS p FROM uc",
    "theta": "SELECT c, z, n / sum(n) OVER (PARTITION BY c) AS p FROM ct",
    "pop_raw": "SELECT z, tbin, CAST(n AS DOUBLE) AS pop FROM tt",
    "pop_log1p": "SELECT z, tbin, ln(1 + n) AS pop FROM tt",
    "pop_share": "SELECT z, tbin, n / sum(n) OVER (PARTITION BY tbin) AS pop FROM tt",
    "lk": "SELECT d.*, s.c, s.z, t.c AS c2 FROM diffs d JOIN assign s ON s.doc_id = src_doc JOIN assign t ON t.doc_id = dst_doc",
    "eta_n": "SELECT c, c2, z, count(*) AS n FROM lk GROUP BY ALL",
    "eta": "SELECT c, c2, z, n / sum(n) OVER (PARTITION BY c) AS p FROM eta_n",
    "eta_joint": "SELECT c, c2, z, n / sum(n) OVER () AS p FROM eta_n",
    "eta_pair": "SELECT c, c2, z, n / sum(n) OVER (PARTITION BY c, c2) AS p FROM eta_n",
    "g": "SELECT e.z, e.c, e.c2, e.p * a.p * b.p AS g FROM eta e JOIN theta a ON a.c = e.c AND a.z = e.z JOIN theta b ON b.c = e.c2 AND b.z = e.z",
    "fx": "SELECT src, dst, sum(a.p * b.p) AS x FROM friends JOIN pi a ON a.user_id = src JOIN pi b ON b.user_id = dst AND b.c = a.c GROUP BY ALL",
    "fscore": "SELECT f.src, f.dst, coalesce(x, 0) AS x FROM friends f LEFT JOIN fx USING (src, dst)",
    "feat": """SELECT user_id, CASE WHEN coalesce(fe, 0) > 0 THEN coalesce(fo, 0) / fe ELSE 0.0 END AS popularity, CASE WHEN coalesce(nd, 0) > 0 THEN coalesce(df, 0) / nd ELSE 0.0 END AS activeness
      FROM (SELECT dst AS user_id, count(*) AS fo FROM friends GROUP BY ALL) FULL JOIN (SELECT src AS user_id, count(*) AS fe FROM friends GROUP BY ALL) USING (user_id)
      FULL JOIN (SELECT user_id, count(*) AS nd FROM docs GROUP BY ALL) USING (user_id) FULL JOIN (SELECT src_user AS user_id, count(DISTINCT src_doc) AS df FROM diffs GROUP BY ALL) USING (user_id)""",
    "yc": "SELECT src_doc, dst_doc, sum(a.p * g.g * b.p) AS y FROM lk l JOIN pi a ON a.user_id = src_user JOIN g ON g.z = l.z AND g.c = a.c JOIN pi b ON b.user_id = dst_user AND b.c = g.c2 GROUP BY ALL",
    "yi": f"SELECT src_doc, dst_doc, {_indiv()} AS y FROM lk LEFT JOIN feat fs ON fs.user_id = src_user LEFT JOIN feat fd ON fd.user_id = dst_user",
    "ys": """SELECT l.src_doc, l.dst_doc, l.src_user, l.dst_user, l.z, l.tbin, coalesce(yc.y, 0) AS y_c, coalesce(pop, 0) AS y_t, yi.y AS y_i, coalesce(yc.y, 0) + coalesce(pop, 0) + yi.y AS y
      FROM lk l LEFT JOIN yc USING (src_doc, dst_doc) LEFT JOIN pop_share p ON p.z = l.z AND p.tbin = l.tbin JOIN yi USING (src_doc, dst_doc)""",
    "nw": "SELECT count(DISTINCT word) AS n_words FROM tokens",
    "zs": f"SELECT CAST(range AS INT) AS z FROM range({Z})",
    "cs": f"SELECT CAST(range AS INT) AS c FROM range({C})",
    "tz": "SELECT z, CAST(sum(n) AS BIGINT) AS nz FROM tw GROUP BY z",
    "tfit": f"""SELECT doc_id, tw.z, sum(list_sum(list_transform(range(cnt), lambda i: ln(1 + (n - CASE WHEN tw.z = a.z THEN cnt ELSE 0 END) / ({BETA} + i))))) AS fit
      FROM tokens JOIN assign a USING (doc_id) JOIN tw USING (word) GROUP BY ALL""",
    "ttext": f"""SELECT a.doc_id, zs.z, ln(coalesce(ct.n, 0) - (zs.z = a.z)::INT + {ALPHA}) + coalesce(fit, 0)
        - list_sum(list_transform(range(n_tok), lambda i: ln(coalesce(nz, 0) - (zs.z = a.z)::INT * n_tok + n_words * {BETA} + i))) AS score
      FROM assign a JOIN docs USING (doc_id) CROSS JOIN zs CROSS JOIN nw LEFT JOIN tz ON tz.z = zs.z LEFT JOIN ct ON ct.c = a.c AND ct.z = zs.z LEFT JOIN tfit ON tfit.doc_id = a.doc_id AND tfit.z = zs.z""",
    "yz": f"""SELECT d.src_doc, d.dst_doc, zs.z, coalesce((SELECT NULL), 0) + coalesce(sum(a.p * g.g * b.p), 0) AS y_c FROM diffs d CROSS JOIN zs LEFT JOIN pi a ON a.user_id = src_user LEFT JOIN pi b ON b.user_id = dst_user
      LEFT JOIN g ON g.z = zs.z AND g.c = a.c AND g.c2 = b.c GROUP BY ALL""",
    "tlink": f"""SELECT doc_id, z, sum(t) AS term FROM (
      SELECT unnest([src_doc, dst_doc]) AS doc_id, z, t FROM (
        SELECT src_doc, dst_doc, yz.z, {psi('yz.y_c + coalesce(pop, 0) + yi.y', pg_mean('ys.y'))} AS t
        FROM yz JOIN ys USING (src_doc, dst_doc) JOIN yi USING (src_doc, dst_doc) LEFT JOIN pop_share p ON p.z = yz.z AND p.tbin = ys.tbin)) GROUP BY ALL""",
    "tfull": "SELECT doc_id, z, score + coalesce(term, 0) AS score FROM ttext LEFT JOIN tlink USING (doc_id, z)",
    "ctot": "SELECT c, sum(n) AS nc FROM ct GROUP BY c",
    "ctext": f"""SELECT a.doc_id, cs.c, ln(coalesce(uc.n, 0) - (cs.c = a.c)::INT + {RHO}) + ln(coalesce(ct.n, 0) - (cs.c = a.c)::INT + {ALPHA}) - ln(coalesce(nc, 0) - (cs.c = a.c)::INT + {Z * ALPHA}) AS score
      FROM assign a CROSS JOIN cs LEFT JOIN uc ON uc.user_id = a.user_id AND uc.c = cs.c LEFT JOIN ct ON ct.c = cs.c AND ct.z = a.z LEFT JOIN ctot ON ctot.c = cs.c""",
    "ends": f"SELECT src AS user_id, dst AS v, {pg_mean('x')} AS lam FROM fscore UNION ALL SELECT dst, src, {pg_mean('x')} FROM fscore",
    "s1": "SELECT e.user_id, c, sum(p) AS s1 FROM ends e JOIN pi ON pi.user_id = v GROUP BY ALL",
    "q": "SELECT e.user_id, a.c, b.c AS c2, sum(lam * a.p * b.p) AS q FROM ends e JOIN pi a ON a.user_id = v JOIN pi b ON b.user_id = v GROUP BY ALL",
    "qp": "SELECT q.user_id, q.c, sum(q * p) AS qp FROM q JOIN pi ON pi.user_id = q.user_id AND pi.c = q.c2 GROUP BY ALL",
    "nd": "SELECT user_id, count(*) AS n_docs FROM assign GROUP BY ALL",
    "cfriend": """SELECT a.doc_id, cs.c, coalesce(s1, 0) / (2 * n_docs) - (coalesce(qp, 0) / n_docs - coalesce(q.q, 0) / (n_docs * n_docs) + coalesce(dg.q, 0) / (2 * n_docs * n_docs)) AS term
      FROM assign a JOIN nd USING (user_id) CROSS JOIN cs LEFT JOIN s1 ON s1.user_id = a.user_id AND s1.c = cs.c LEFT JOIN qp ON qp.user_id = a.user_id AND qp.c = cs.c
      LEFT JOIN q ON q.user_id = a.user_id AND q.c = cs.c AND q.c2 = a.c LEFT JOIN q dg ON dg.user_id = a.user_id AND dg.c = cs.c AND dg.c2 = cs.c""",
    "vec": """SELECT src_doc AS doc_id, src_doc, dst_doc, g.c, sum(g.g * p) AS g FROM lk l JOIN pi ON pi.user_id = dst_user JOIN g ON g.z = l.z AND g.c2 = pi.c GROUP BY ALL
      UNION ALL SELECT dst_doc, src_doc, dst_doc, g.c2, sum(g.g * p) FROM lk l JOIN pi ON pi.user_id = src_user JOIN g ON g.z = l.z AND g.c = pi.c GROUP BY ALL""",
    "clink": f"""SELECT e.doc_id, cs.c, sum({psi('e.y + (coalesce(v.g, 0) - coalesce(v0.g, 0)) / n_docs', pg_mean('e.y'))}) AS term
      FROM (SELECT unnest([src_doc, dst_doc]) AS doc_id, src_doc, dst_doc, y FROM ys) e JOIN assign a ON a.doc_id = e.doc_id JOIN nd USING (user_id) CROSS JOIN cs
      LEFT JOIN vec v ON v.doc_id = e.doc_id AND v.src_doc = e.src_doc AND v.dst_doc = e.dst_doc AND v.c = cs.c
      LEFT JOIN vec v0 ON v0.doc_id = e.doc_id AND v0.src_doc = e.src_doc AND v0.dst_doc = e.dst_doc AND v0.c = a.c GROUP BY ALL""",
    "cfull": "SELECT doc_id, c, score + term + coalesce(l.term, 0) AS score FROM ctext JOIN cfriend f USING (doc_id, c) LEFT JOIN clink l USING (doc_id, c)".replace("score + term", "score + f.term"),
    "pi_s": f"SELECT u.user_id, cs.c, (coalesce(n, 0) + {RHO}) / (n_docs + {C * RHO}) AS p FROM nd u CROSS JOIN cs LEFT JOIN uc ON uc.user_id = u.user_id AND uc.c = cs.c",
    "theta_s": f"SELECT cs.c, zs.z, (coalesce(n, 0) + {ALPHA}) / (sum(coalesce(n, 0)) OVER (PARTITION BY cs.c) + {Z * ALPHA}) AS p FROM cs CROSS JOIN zs LEFT JOIN ct ON ct.c = cs.c AND ct.z = zs.z",
    "phi_s": f"SELECT tz.z, v.word, (coalesce(n, 0) + {BETA}) / (nz + n_words * {BETA}) AS p FROM tz CROSS JOIN (SELECT word FROM vocab) v CROSS JOIN nw LEFT JOIN tw ON tw.z = tz.z AND tw.word = v.word",
    "rcz": "SELECT e.c, e.z, sum(e.p * t.p) AS r FROM eta e JOIN theta_s t ON t.c = e.c2 AND t.z = e.z GROUP BY ALL",
    "qws": "SELECT word AS q_id, word FROM vocab",
    "rank": "SELECT q_id, c, score, row_number() OVER (PARTITION BY q_id ORDER BY round(score, 12) DESC, c) AS rank FROM (SELECT q_id, c, sum(r * p) AS score FROM qws JOIN phi_s USING (word) JOIN rcz USING (z) GROUP BY ALL)",
    "top5": "SELECT user_id, c FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY round(p, 12) DESC, c) AS k FROM pi_s) WHERE k <= 5",
    "rel": "SELECT DISTINCT word AS q_id, d.src_user AS user_id FROM diffs d JOIN tokens t ON t.doc_id = d.src_doc",
    "firsthit": "SELECT q_id, user_id, min(rank) AS k0 FROM rank JOIN top5 USING (c) GROUP BY ALL",
    "ks": "SELECT range AS k FROM range(1, 6)",
    "prk": """SELECT q_id, k, count(*) AS n_u, count(r.user_id) AS n_hit, any_value(n_rel) AS n_rel FROM firsthit f JOIN ks ON k0 <= k LEFT JOIN rel r USING (q_id, user_id)
      JOIN (SELECT q_id, count(*) AS n_rel FROM rel GROUP BY ALL) USING (q_id) GROUP BY q_id, k""",
}


def statement(final: str) -> str:
    """The final SELECT with all expressions it needs in front."""
    done: list[str] = []

    def need(text: str) -> None:
        for name in CTES:
            if name not in done and re.search(rf"\b{name}\b", re.sub(r"\b\w+\.(\w+)", r"\1_", text)) and re.search(rf"(?:FROM|JOIN|,)\s+\(?{name}\b", text):
                body = CTES[name]
                need(body)
                if name not in done:
                    done.append(name)

    need(final)
    return ("WITH " + ",\n".join(f"{n} AS ({CTES[n]})" for n in done) + "\n" if done else "") + final
