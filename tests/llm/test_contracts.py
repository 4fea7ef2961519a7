"""The registered queries of the operators, each whole, against plain versions that share no code with the library."""

import hashlib
import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest

from laneforge.llm.queries import ORACLES, QUERIES
from tests.llm.test_dedup import plain_components, plain_fingerprint
from tests.llm.test_katz import Plain as Model
from tests.llm.test_language import Plain as Language
from tests.llm.test_models import plain_pii, plain_rules
from tests.llm.test_passages import plain_passages

UP = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@pytest.fixture(scope="module")
def folder(spark, sf, tmp_path_factory):
    """Tables with the awkward rows among the given ones."""
    out = tmp_path_factory.mktemp("tables")
    docs = [(r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"]) for r in spark.read.parquet(f"{sf}/documents.parquet").filter("n_chars < 8000").limit(120).collect()]
    more = [None, "", " \t\n", "12 34 !!", "Hello World", "hello world", "write to me: a.b@c.de or 4111 1111 1111 1111, +1 (555) 123-4567, 1.2.3.4", "one line\ntwo lines here\nthree lines", "own\none line\ntwo lines here\nend", "w " * 9000, "漢字 привет", "ssn 123-45-6789"]
    docs += [(900_000 + i, t, "en" if i % 2 else None, "src1" if i % 3 else None, 0) for i, t in enumerate(more)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{out}/documents.parquet")
    urls = [None, "no scheme", "http://Sub.Example.NET/en/1?q=2#t", "https://example.com/de/7", "http://a.org/fr/x", "HTTP://x.Net?y", "ftp://bad.example.com/spam/9?id=1&b"]
    pages = [(i, urls[i]) for i in range(len(urls))]
    pages += [(100 + i, f"http://{'www' if i % 2 else 'm'}.host{i % 5}.{'com' if i % 3 else 'org'}/{'spam' if i % 5 == 2 else 'news'}/{i}/{'en' if i % 4 else 'de'}{'?ref=x' if i % 7 == 0 else ''}") for i in range(150)]
    spark.createDataFrame([(*p, "<p>") for p in pages], "page_id long, url string, html string").write.parquet(f"{out}/pages.parquet")
    labels = [(100 + i, int(i % 5 != 2), int(i % 11 == 0)) for i in range(0, 150, 1)] + [(None, 0, 0), (6, None, 1), (7, None, None)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{out}/labels.parquet")
    rng = np.random.default_rng(2)
    centres = rng.normal(size=(9, 16)) * 3
    vectors = [(i, (centres[i % 9] + rng.normal(size=16)).astype(np.float32).tolist(), 0) for i in range(900)]
    vectors += [(1000, None, 0), (1020, [0.0] * 16, 0), (1040, [float("nan")] * 16, 0), (1060, [1.0] * 3, 0), *[(2000 + i, vectors[5][1], 0) for i in range(40)]]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>, label int").write.parquet(f"{out}/embeddings.parquet")
    return str(out), docs, pages, labels, vectors


def crc(i, parts):
    return zlib.crc32(str(i).encode()) % parts


def test_op1(spark, folder):
    path, _, pages, labels, _ = folder
    fixed = [("block", "net", ""), ("allow", "example.net", "en/"), ("block", "example.com", "de/"), ("allow", "org", "fr/")]

    def parts(url):
        if url is None or "://" not in url:
            return "", ""
        rest = url.split("://", 1)[1]
        cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
        tail = rest[cut:]
        return rest[:cut].translate(UP), tail[: min([tail.find(c) for c in "?#" if c in tail], default=len(tail))]

    def tokens(url):
        import re

        host, path = parts(url)
        labels = [x for x in host.split(".") if x]
        scheme = re.match(r"([A-Za-z][A-Za-z0-9+.-]*)://", url or "")
        query = re.search(r"\?([^#]*)", url or "")
        out = ["scheme:" + (scheme[1].lower() if scheme else "")] + ["host:" + ".".join(labels[k:]) for k in range(len(labels))]
        out += ["path:" + w for w in re.split("[^a-z0-9]+", re.sub("[0-9]+", "0", path.lower())) if w]
        return out + ["query:" + q.split("=")[0] for q in (query[1].split("&") if query else []) if q]

    url_of = dict(pages)
    rows = [(tokens(url_of[i]), "block" if t == 1 or q == 0 else "allow") for i, q, t in labels if i in url_of]
    rules = plain_rules(rows, max(5, math.ceil(0.001 * len(rows))), 0.6)
    got = {r["page_id"]: r for r in QUERIES["op1_url_rules"](spark, path).collect()}
    assert len(got) == len(pages)
    blocked = 0
    for i, url in pages:
        host, way = parts(url)
        rule = max(((v, f"{d}/{p}") for v, d, p in fixed if (host == d or host.endswith("." + d)) and way.startswith("/" + p)), key=lambda r: len(r[1]), default=None)
        own = set(tokens(url))
        best = max(((c, v == "block", s, v) for (items, v), (c, s) in rules.items() if set(items) <= own), default=None)
        verdict = rule[0] if rule else best[3] if best else "allow"
        assert (got[i]["host"], got[i]["path"], got[i]["rule"], got[i]["verdict"]) == (host, way, rule and rule[1], verdict), url
        blocked += rule is None and verdict == "block"
    assert blocked > 20


def test_op2(spark, folder):
    path, docs, *_ = folder
    plain = Language([(lang, t) for i, t, lang, *_ in docs if crc(i, 4) != 2])
    got = {r["doc_id"]: r for r in QUERIES["op2_language_id"](spark, path).collect()}
    assert len(got) == len(docs)
    for i, t, *_ in docs:
        lang, score = plain.predict(t)
        assert (got[i]["held_out"], got[i]["lang_pred"]) == (crc(i, 4) == 2, lang) and got[i]["score"] == pytest.approx(score, abs=1e-6)


def test_op3(spark, folder):
    path, docs, *_ = folder
    groups = defaultdict(list)
    for i, t, *_ in docs:
        groups[(t or "").translate(UP)].append(i)
    want = {(i, max(ids), len(ids), i == max(ids), hashlib.sha256(t.encode()).hexdigest()) for t, ids in groups.items() for i in ids}
    assert {(r["doc_id"], r["keep_id"], r["group_size"], r["kept"], r["text_sha256"]) for r in QUERIES["op3_exact_dedup"](spark, path).collect()} == want


def test_op4(spark, folder):
    path, docs, *_ = folder
    lines = plain_passages([(i, t) for i, t, *_ in docs if t is not None])
    got = {r["doc_id"]: r for r in QUERIES["op4_line_dedup"](spark, path).collect()}
    assert len(got) == len(docs) and sum(r["n_removed"] for r in got.values()) > 0
    for i, t, *_ in docs:
        rest = "\n".join(lines.get(i, []))
        assert (got[i]["n_chars_left"], got[i]["text_sha256"]) == (len(rest), hashlib.sha256(rest.encode()).hexdigest())
        assert (got[i]["n_removed"] > 0) == (rest != (t or ""))


def test_op5(spark, folder):
    path, docs, *_ = folder
    plain = Model([t for i, t, *_ in docs if crc(i, 5) != 1], 3)
    got = {r["doc_id"]: r for r in QUERIES["op5_katz_lm"](spark, path).collect()}
    assert len(got) == len(docs)
    n, v = plain.total, len(plain.grams[1])
    for i, t, *_ in docs:
        own, r = plain.tokens(t), got[i]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (crc(i, 5) == 1, len(own), sum(plain.grams[1][w,] > 0 for w in own), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((plain.grams[1][w,] + 0.5) / (n + 0.5 * (v + 1))) for w in own))
        assert r["score"] == pytest.approx(plain.score(t))


def test_op6(spark, folder):
    path, docs, *_ = folder
    got = {r["doc_id"]: r for r in QUERIES["op6_pii"](spark, path).collect()}
    assert len(got) == len(docs)
    extra = 0
    for i, t, *_ in docs:
        found = plain_pii(t)
        base = [f"{k}:{a}:{b}" for k, a, b in found]
        r = got[i]
        assert [r[f"n_{k}"] for k in ("email", "ip", "card", "phone")] == [sum(x[0] == k for x in found) for k in ("email", "ip", "card", "phone")]
        assert r["base_sha256"] == hashlib.sha256(",".join(base).encode()).hexdigest()
        assert [s for s in r["spans"].split(",") if s][: len(base)] == base
        extra += len([s for s in r["spans"].split(",") if s]) - len(base)
    assert extra > 0


def test_op7(spark, folder):
    path, docs, *_ = folder
    fps = {i: plain_fingerprint(t) for i, t, *_ in docs}
    root, least = plain_components(list(fps.values())), {}
    for i, f in fps.items():
        least[root[f]] = min(least.get(root[f], i), i)
    want = {(i, f"{f:016x}", least[root[f]]) for i, f in fps.items()}
    assert {(r["doc_id"], r["fingerprint"], r["component_id"]) for r in QUERIES["op7_simhash"](spark, path).collect()} == want


@pytest.mark.parametrize("given", [True, False])
def test_op8(spark, folder, given):
    """Ranks, exact scores and recall with the query's own parameters, on clustered vectors and on the given ones."""
    path, _, _, _, vectors = folder
    if given:
        path = "/root/testdata/sf0.1"
        vectors = [(r["vec_id"], r["embedding"], 0) for r in spark.read.parquet(f"{path}/embeddings.parquet").collect()]
    dim = len(vectors[0][1])
    good = {i: np.array(v, float) for i, v, _ in vectors if v is not None and len(v) == dim and np.isfinite(v).all() and np.any(v)}
    got = defaultdict(list)
    for r in QUERIES["op8_multi_index"](spark, path).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    ids, v = np.array(list(good)), np.stack(list(good.values()))
    assert set(got) == {i for i in good if i % 20 == 0}
    hit = n = 0
    for i in got:
        s = (v * good[i]).sum(axis=1)
        own = sorted(got[i])
        assert [r for r, _, _ in own] == list(range(1, 21)) and all(x != i for _, x, _ in own)
        assert [(-x, j) for _, j, x in own] == sorted((-x, j) for _, j, x in own)
        assert all(x == pytest.approx(float((good[j] * good[i]).sum()), rel=1e-12) for _, j, x in own)
        best = [x for x in s[ids != i][np.argsort(-s[ids != i])][:20]]
        hit, n = hit + sum(x >= best[-1] - 1e-9 for _, _, x in own), n + 20
    assert hit >= 0.9 * n


def test_op10(spark, folder):
    import base64

    import tiktoken

    path, docs, *_ = folder
    with open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    real = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = set()
    for i, t, *_ in docs:
        ids = real.encode_ordinary(t or "")
        want.add((i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert {(r["doc_id"], r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in QUERIES["op10_byte_bpe"](spark, path).collect()} == want


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracles(spark, folder, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "pages", "labels"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{folder[0]}/{t}.parquet/*.parquet'")
    got, want = QUERIES[name](spark, folder[0]), con.sql(ORACLES[name])
    plain = lambda row, names: tuple(str(round(x, 6) if isinstance(x, float) else x) for _, x in sorted(zip(names, row)))
    assert Counter(plain(r, got.columns) for r in got.collect()) == Counter(plain(r, want.columns) for r in want.fetchall())
