"""The text operators against brute force, on the smallest tables and on rows with nulls, ties, repeats and empty texts."""

import collections
import hashlib
import re
import struct
import zlib

import numpy as np
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from vertexalg.llm import chat_format, common, decontamination, language_id, near_dedup, packing, quality_classifier, secret_scan, substring_dedup, url_filter, vector_search

WORD = re.compile("[^\x20\x09-\x0d]+")
ODD = [(1, "a b c " * 30), (1, "a b c " * 30), (2, None), (3, ""), (None, "a b c " * 30), (4, "é" * 70_000), (5, "x\u00a0 y\r\n\tz  "), (6, "a b c " * 30)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, 7, "x") for i, t in ODD], "doc_id long, text string, n_words int, kept string")


@pytest.fixture(scope="module")
def docs(sf):
    return sorted(pq.read_table(f"{sf}/documents.parquet").to_pylist(), key=lambda r: r["doc_id"])


def repeats(rows, size):
    """Expected (words, removed, kept text) per row; rows are documents in the order of ids and then as listed."""
    first, out = {}, []
    words = [WORD.findall(t or "") for _, t in rows]
    for r in sorted(range(len(rows)), key=lambda r: (rows[r][0] is not None, rows[r][0] or 0, r)):
        for p in range(len(words[r]) - size + 1):
            first.setdefault(tuple(words[r][p : p + size]), (r, p))
    for r, (i, _) in enumerate(rows):
        w, gone = words[r], set()
        for p in range(len(w) - size + 1):
            if first[tuple(w[p : p + size])] != (r, p):
                gone.update(range(p, p + size))
        out.append((i, len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone)))
    return out


def plain(rows):
    return sorted((tuple(r) for r in rows), key=repr)


def test_substring_dedup(spark, sf, docs, odd):
    want = [(*r[:3], hashlib.sha256(r[3].encode()).hexdigest()) for r in repeats([(r["doc_id"], r["text"]) for r in docs], 20)]
    assert plain(substring_dedup.op3_substring_dedup(spark, sf).collect()) == plain(want)
    assert plain(substring_dedup.remove_repeats(odd).collect()) == plain(repeats(ODD, 20))
    assert substring_dedup.remove_repeats(odd.where("doc_id > 99")).collect() == []
    spans = substring_dedup.factors(spark.createDataFrame([(1, "a b c d e f g"), (2, "x b c d e y")], "doc_id long, text string"), 3)
    assert [tuple(r) for r in spans.select("doc_id", "start", "n", "from_doc", "from_start").collect()] == [(2, 1, 2, 1, 1)]


def test_packing(spark, odd, docs):
    import public_tokenizers
    from tokenizers import Tokenizer

    tool = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = [(r["doc_id"], r["text"]) for r in docs[:60]] + [(10_000 + k, t) for k, (_, t) in enumerate(ODD)]
    rows += [(20_000, "don't  stop\n\n 's <|endoftext|> x\u3000 y \u2028z 12ab\t"), (20_001, " lead"), (20_002, "trail \n "), (20_003, "a\u0085 b c'LL I'm"), (20_004, "日本語 テキスト。 привет, мир! 🙂 🙂")]
    got = packing.pack(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), group=40, fan=2).collect()
    by, bins = collections.defaultdict(list), collections.defaultdict(list)
    for g in got:
        by[g.doc_id].append(g)
        bins[g.sequence_id].append(g)
    total = 0
    for i, t in rows:
        ids = [*tool.encode(t or "", add_special_tokens=False).ids, 0]
        total += len(ids)
        at = 0
        for k, g in enumerate(sorted(by[i], key=lambda g: g.piece)):
            part = ids[g.start : g.start + g.length]
            assert (g.piece, g.start) == (k, at) and g.length <= 2048 and (k == 0 or g.length == 2048)
            assert zlib.crc32(struct.pack(f"<{len(part)}I", *part)) == g.ids_crc32
            at += g.length
        assert at == len(ids)
    for members in bins.values():
        at = 0
        for g in sorted(members, key=lambda g: g.offset):
            assert g.offset == at
            at += g.length
        assert at <= 2048
    assert len(bins) <= -(-total // 2048) + 1
    assert packing.pack(odd.where("doc_id > 99")).collect() == []
    assert sum(r.length for r in packing.pack(odd.where("doc_id is null or doc_id = 1")).where("doc_id is null").collect()) > 0


def test_best_fit():
    assert sorted(map(sorted, packing.best_fit(np.array([5, 4, 3, 2, 6]), 10))) == [[0, 2, 3], [1, 4]]


def test_decontamination(spark, sf, docs, odd):
    pattern, low = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+"), str.maketrans({i: i + 32 for i in range(65, 91)})
    items = [(r["item_id"], r["text"]) for r in pq.read_table(f"{sf}/benchmark.parquet").to_pylist()]

    def want(rows, items, size):
        windows = collections.defaultdict(set)
        for k, t in items:
            w = pattern.findall((t or "").translate(low))
            n = min(size, len(w))
            for p in range(len(w) - n + 1 if n else 0):
                windows[tuple(w[p : p + n])].add(str(k))
        out = []
        for i, t in rows:
            w, hit, owners = pattern.findall((t or "").translate(low)), set(), set()
            for n in {len(x) for x in windows}:
                for p in range(len(w) - n + 1):
                    if own := windows.get(tuple(w[p : p + n])):
                        owners |= own
                        hit.update(range(p, p + n))
            out.append((i, len(w), len(hit), len(owners), hashlib.sha256(",".join(sorted(owners)).encode()).hexdigest(), bool(hit)))
        return out

    assert plain(decontamination.op5_decontamination(spark, sf).collect()) == plain(want([(r["doc_id"], r["text"]) for r in docs], items, 10))
    short = [(1, "B c"), (2, None), (3, "..."), (4, "a b c a b c a b c a"), (1, "B c")]
    frame = spark.createDataFrame(short, "item_id long, text string")
    for limit in (1 << 20, 8):
        got = decontamination.contamination_report(odd.dropDuplicates(["doc_id"]), frame, limit=limit)
        texts = [(r["doc_id"], r["text"]) for r in odd.dropDuplicates(["doc_id"]).collect()]
        assert plain(got.collect()) == plain(want(texts, short[:4], 10))
    clean = decontamination.keep_clean(odd, frame)
    assert clean.columns == odd.columns and {r["doc_id"] for r in clean.collect()} == {2, 3, 4, 5}


def shingle_sets(rows):
    out = []
    for i, t in rows:
        w = [x.lower() if x.isascii() else x for x in WORD.findall(t or "")]
        out.append((i, frozenset(tuple(w[p : p + 5]) for p in range(len(w) - 4)) or (frozenset([tuple(w)]) if w else frozenset())))
    return out


def classes(rows, least=0.8):
    sets = shingle_sets(rows)
    parent = {i: i for i, _ in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, (i, x) in enumerate(sets):
        for j, y in sets[:a]:
            if x and y and len(x & y) >= least * len(x | y):
                p, q = find(i), find(j)
                parent[max(p, q)] = min(p, q)
    return {i: find(i) for i, _ in sets}


def test_near_duplicates(spark, sf, docs):
    rows = [(r["doc_id"], r["text"]) for r in docs]
    words = [f"w{i}" for i in range(100)]
    for k in range(14):  # one source, edits that add up: the source alone ties many of them
        w = list(words)
        for e in range(1 + k // 3):
            w[(k * 7 + e * 31) % 100] = f"n{k}x{e}"
        rows.append((5000 + k, " ".join(w)))
    rows += [(6000, None), (6001, ""), (6002, "one two"), (6003, "one two")]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    want = classes(rows)
    for options in ({}, {"small": 2, "block": 300}):
        assert {r.doc_id: r.class_id for r in near_dedup.near_duplicates(frame, **options).collect()} == want
    assert near_dedup.near_duplicates(frame.where("doc_id < 0")).collect() == []


def test_dart_signatures():
    rng = np.random.default_rng(1)
    names = rng.integers(0, 2**63, 300).astype(np.uint64)
    a, b = rng.uniform(0.2, 5, 300), rng.uniform(0.2, 5, 300)
    b[:150] = a[:150]
    s = near_dedup.dart_signatures(np.concatenate([names, names]), np.concatenate([a, b]), np.array([0, 300, 600]), 4000)
    assert (s[0] == s[1]).mean() == pytest.approx(np.minimum(a, b).sum() / np.maximum(a, b).sum(), abs=0.03)
    assert not near_dedup.dart_signatures(names[:0], a[:0], np.array([0, 0]), 8).any()


def test_language(spark, sf, docs, odd):
    got = {r.doc_id: r for r in language_id.op1_language_id(spark, sf).collect()}
    out = [r for r in docs if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    assert {i for i, r in got.items() if r.held_out} == {r["doc_id"] for r in out}
    assert np.mean([got[r["doc_id"]].lang_pred == r["lang"] for r in out if r["text"]]) > 0.9
    model = language_id.learn(spark.read.parquet(f"{sf}/documents.parquet"))
    english, french = (next(r["text"] for r in docs if r["lang"] == x)[:200] for x in ("en", "fr"))
    mixed = language_id.identify(spark.createDataFrame([(1, f"{english}\n{french}"), (2, "... 12"), (3, None)], "doc_id long, text string"), model, with_spans=True).orderBy("doc_id").collect()
    assert {s["lang"] for s in mixed[0].spans} >= {"en", "fr"} and [s["lang"] for s in mixed[0].spans][0] == "en"
    assert [r.lang_pred for r in mixed[1:]] == ["und", "und"]
    assert {r.lang_pred for r in language_id.identify(odd, None).collect()} == {"und"}


def test_quality(spark, sf, odd):
    good = [f"the cat number {i} sat on a mat and thought of the sea" for i in range(200)]
    bad = [f"THE!! CAT!! {i}!! SAT!! ON!! A!! MAT!! &&&" for i in range(200)]
    net = quality_classifier.Network.learn(good[:150] + bad[:150], [1] * 150 + [0] * 150)
    frame = spark.createDataFrame([(i, t) for i, t in enumerate(good[150:] + bad[150:])], "doc_id long, text string")
    got = {r.doc_id: r.predicted for r in quality_classifier.classify(frame, net).collect()}
    assert [got[i] for i in range(100)] == [1] * 50 + [0] * 50
    scores = quality_classifier.classify(odd, net).collect()
    assert len(scores) == len(ODD) and all(0 <= r.score <= 1 for r in scores)
    assert quality_classifier.keep_good(frame, net).count() == 50 and quality_classifier.keep_good(odd, None).count() == len(ODD)
    whole = quality_classifier.op10_quality_classifier(spark, sf)
    assert whole.count() == spark.read.parquet(f"{sf}/documents.parquet").count()


def test_quality_gradient():
    rng = np.random.default_rng(0)
    net = quality_classifier.Network()
    raw = [bytes(rng.integers(97, 110, n).astype(np.uint8)) for n in (300, 10, 700)]
    x, edge = quality_classifier.symbols(np.frombuffer(b"".join(raw), np.uint8), np.append(0, np.cumsum([len(r) for r in raw])))
    y = np.array([1.0, 0.0, 1.0])
    loss = lambda: -np.mean(np.log(np.where(y == 1, p := net.score(net.tables(), x, edge), 1 - p)))
    g = net.gradient(x, edge, y)
    for key, at in (("dense", (3,)), ("dense", (20,)), ("filter", (2, 1, 3)), ("bias", (1,))):
        old, step = net.p[key][at], 1e-2
        net.p[key][at] = old + step
        up = loss()
        net.p[key][at] = old - step
        down = loss()
        net.p[key][at] = old
        assert g[key][at] == pytest.approx((up - down) / (2 * step), abs=3e-3)


def test_secrets(spark, sf, tmp_path):
    texts = ['a token = "abcdef123456" b', "secret=abc", "secret=token:abcdefgh", "AKIA" + "A" * 16 + " é AKIAB", "x" * 5 + "0" * 24 + " " + "f" * 23, None, "", 'PassWord: "deadbeefdeadbeefdeadbeef"', "token==api_key=qqqqqq"]
    texts.append("🙂 passwd='" + "z" * 50_000)
    frame = spark.createDataFrame(list(enumerate(texts)) + [(99, texts[0])], "doc_id long, text string")
    runs = {"access": "AKIA[A-Z0-9]+", "hex": "[0-9a-f]+"}
    rules = [(r.kind, re.compile(runs.get(r.kind, r.pattern)), r.group, r.least) for r in secret_scan.RULES]
    want = {}
    for i, t in [*enumerate(texts), (99, texts[0])]:
        found = [(m.start(), k, kind, m.end()) for k, (kind, p, g, n) in enumerate(rules) for m in p.finditer(t or "") if len(m[g]) >= n]
        want[i] = sorted(found)
    got = {r.doc_id: sorted((s["start"], s["rank"], s["kind"], s["end"]) for s in r.spans) for r in secret_scan.findings(frame).collect()}
    assert got == want and want[2] == [] and len(want[7]) == 2
    # a ledger: the second scan finds only what is new, and all paths see both
    ledger = str(tmp_path / "ledger")
    first = secret_scan.findings(frame.where("doc_id < 3"), ledger_path=ledger)
    assert {r.doc_id for r in first.collect()} == {0, 1, 2}
    before = spark.read.parquet(ledger).count()
    both = secret_scan.findings(frame, ledger_path=ledger)
    assert {r.doc_id: len(r.spans) for r in both.collect()} == {i: len(s) for i, s in want.items()}
    assert before == 3 * len(rules) and spark.read.parquet(ledger).count() == len(set(map(lambda t: t or "", texts))) * len(rules)
    clean = {r.doc_id: r.text for r in secret_scan.redact(frame).collect()}
    assert clean[0] == 'a [secret]" b' and clean[5] is None and clean[7] == '[secret]"' and clean[1] == "secret=abc"


def test_chat(spark):
    messages = [("t", 1, None, "user", "hi </s> & [INST]", 1.0), ("t", 2, 1, "assistant", "a&amp;<s>", 1.0), ("t", 3, 1, "assistant", None, 5.0), ("t", 4, 2, "user", "b", 9.0), ("u", 7, 99, None, "lone", None)]
    frame = spark.createDataFrame(messages, "tree string, node long, parent long, role string, text string, score double")
    every = chat_format.read_back(chat_format.format_trees(frame, keep=0)).collect()
    assert {(r.tree, r.leaf): [tuple(t) for t in r.turns] for r in every} == {("t", 4): [("user", "hi </s> & [INST]"), ("assistant", "a&amp;<s>"), ("user", "b")], ("t", 3): [("user", "hi </s> & [INST]"), ("assistant", "")], ("u", 7): [("", "lone")]}
    assert {(r.tree, r.leaf): r.learned for r in every} == {("t", 4): "a&amp;<s>", ("t", 3): "", ("u", 7): ""}
    assert {(r.tree, r.leaf) for r in chat_format.format_trees(frame, keep=1).collect()} == {("t", 4), ("u", 7)}
    long = spark.range(130).select(F.lit("c").alias("tree"), F.col("id").alias("node"), F.when(F.col("id") > 0, F.col("id") - 1).alias("parent"))
    assert sorted(r.up for r in chat_format.paths(long).collect()) == list(range(130))
    with pytest.raises(ValueError, match="circle"):
        chat_format.paths(spark.createDataFrame([("c", 1, 2), ("c", 2, 1)], "tree string, node long, parent long"))


def test_urls(spark):
    urls = ["http://A.ORG/x?q", "https://www.example.org/es/1", "https://example.org/en/12", "https://example.org/en/2", "http://x.com/fr/1#a", "ftp://x.com/de/", "http://nocom/de/", None, "nothing", "http://host", "http://h?a://b/c"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    labels = spark.createDataFrame([("http://bad.net/1", 0)] * 40 + [("http://good.net/1", 1)] * 40 + [("http://x.bad.net/1", None)], "url string, good int")
    more = spark.createDataFrame([(50, "http://bad.net/z"), (51, "http://good.net/z"), (52, "http://new.good.net/z")], "page_id long, url string")
    got = {r.page_id: tuple(r)[1:] for r in url_filter.judge(pages.union(more), labels).collect()}
    assert got[0][:2] == ("a.org", "/x") and got[0][2:] == ("org/", "allow")
    assert got[1][2:] == ("example.org/es/", "block") and got[2][2:] == ("example.org/en/1", "block") and got[3][2:] == ("org/", "allow")
    assert got[4][1:] == ("/fr/1", "com/fr/", "allow") and got[5][2:] == ("com/de/", "block") and got[6][2] is None
    assert got[7][:3] == got[8][:3] == ("", "", None) and got[9][:2] == ("host", "") and got[10][:2] == ("h", "")
    assert got[50][3] == "block" and got[51][3] == "allow" and got[52][3] == "allow"


def test_vectors(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(300, 12))
    x[5] = x[100]
    x[6] = 0
    rows = [(i, [float(v) for v in x[i]]) for i in range(300)] + [(300, None), (301, [1.0, None]), (302, [float("nan")] * 12), (100, [float(v) for v in x[100]]), (None, [1.0] * 12)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = collections.defaultdict(list)
    for r in vector_search.nearest(frame, frame.where("vec_id % 50 = 0"), query_group=3, group=64).collect():
        got[r.query_id].append((r.rank, r.vec_id, r.score))
    norm = np.sqrt((x * x).sum(axis=1))
    for q in range(0, 300, 50):
        s = np.where(norm > 0, x @ x[q] / np.where(norm > 0, norm, 1) / norm[q], -9)
        s[q] = -9
        want = np.lexsort((np.arange(300), -np.round(s, 12)))[:5]
        assert [v for _, v, _ in sorted(got[q])] == want.tolist()
        assert [c for _, _, c in sorted(got[q])] == pytest.approx(s[want].tolist(), abs=1e-12)
    a, b = vector_search.quantise(x[:5]), vector_search.quantise(x[7:50])
    about, off = vector_search.tile(a, b)
    assert (np.abs(about - (x[:5] @ x[7:50].T) / norm[:5, None] / norm[None, 7:50]) <= off).all()


def test_bytes():
    body, offsets = common.utf8(common.pa.array(["a bb", None, "", "ccc"]))
    start, end, first = common.spans(common.SPACE_WORD, body, offsets)
    assert [body[a:b].tobytes() for a, b in zip(start, end, strict=True)] == [b"a", b"bb", b"ccc"] and first.tolist() == [0, 2, 2, 2, 3]
    assert (common.word_hashes(body, start, end) == common.word_hashes(body, start, end, chunk=1)).all()
