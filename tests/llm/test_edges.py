"""Every text operator and pipeline stage on empty tables, null columns, odd rows and columns with clashing names."""

import collections
import sys
import zlib
from pathlib import Path

import numpy as np
import pyarrow.parquet as pq
import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))

import corpus_pipeline as P  # noqa: E402
from tests.llm.test_operators import ODD, plain  # noqa: E402
from vertexalg.llm import chat_format, common, decontamination, language_id, near_dedup, packing, quality_classifier, registry, secret_scan, substring_dedup, url_filter, vector_search  # noqa: E402

CLASHING = "spans string, blob string, kept_id long, held_out string, row long, _row long, _blob string, _spans string, _salt long, starts long, class_id string, score string, hits string, n long"
SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "labels": "doc_id long, quality int, toxic int",
    "conversations": "conv_id long, turn long, role string, text string",
}


def _tables(spark, folder, rows):
    for name, schema in SCHEMAS.items():
        spark.createDataFrame(rows.get(name, []), schema).write.parquet(f"{folder}/{name}.parquet")
    return str(folder)


@pytest.fixture(scope="module")
def empty(spark, tmp_path_factory):
    return _tables(spark, tmp_path_factory.mktemp("tables") / "empty", {})


@pytest.fixture(scope="module")
def nulls(spark, tmp_path_factory):
    """Every column null in some rows, and rows that are null altogether."""
    rows = {
        "documents": [(None,) * 5, (None,) * 5, (1, None, "en", None, None), (2, "the cat sat on a mat", None, "a", 20), (None, "le chat est là", "fr", None, 14), (3, "", "de", "b", 0), (3, "", "de", "b", 0)],
        "embeddings": [(None,) * 3, (0, None, None), (0, [1.0, 2.0], None), (1, [None, 1.0], 0), (2, [2.0, 1.0], None), (50, [], 1), (100, [0.0, 0.0], 1), (None, [1.0, 1.0], 1)],
        "pages": [(None,) * 3, (None,) * 3, (1, None, "x"), (2, "http://a.co.uk/2", None), (2, "http://a.co.uk/2", None), (3, "", "")],
        "benchmark": [(None, None), (1, None), (None, "cat sat"), (2, "")],
        "labels": [(None,) * 3, (None, 1, 0), (2, None, None), (3, 1, None)],
        "conversations": [(None,) * 4, (1, None, None, None), (1, 0, "user", None), (1, 0, None, "x"), (None, 1, "assistant", "y")],
    }
    return _tables(spark, tmp_path_factory.mktemp("tables") / "nulls", rows)


@pytest.mark.parametrize("name", sorted(registry.QUERIES))
def test_empty_tables(spark, empty, name):
    got = registry.QUERIES[name](spark, empty).collect()
    assert [r.conv_id for r in got] == [-7] if name.startswith("op6") else got == []


@pytest.mark.parametrize("name", sorted(registry.QUERIES))
def test_null_columns(spark, nulls, name):
    got = registry.QUERIES[name](spark, nulls).collect()
    if name.startswith("op9"):
        assert [(r.query_id, r.rank, r.vec_id) for r in got] == [(0, 1, 2)]
    elif name.startswith("op6"):
        assert sorted(r.conv_id or 0 for r in got) == [-7, 0, 1] and sum(r.n_turns for r in got) == 7
    else:
        assert len(got) == (6 if name.startswith("op8") else 7)


def test_pipeline_on_empty_and_null_tables(spark, empty, nulls):
    assert P.run(spark, empty).collect() == []
    got = P.run(spark, nulls).collect()
    assert sum(r.length for r in got) >= 4 and {r.doc_id for r in got} <= {None, 1, 2, 3}


@pytest.fixture(scope="module")
def wide(spark):
    rows = [(i, t, "en", "x", 7) + tuple(k if c.split()[1] == "long" else f"{c}{k}" for c in CLASHING.split(", ")) for k, (i, t) in enumerate([*ODD, (7, "token=abcdefgh and more")])]
    return spark.createDataFrame(rows, f"{SCHEMAS['documents']}, {CLASHING}")


def test_clashing_columns_in_stages(spark, sf, wide):
    """Stages keep all columns and their values, whatever their names."""
    known = {r["_row"]: r for r in wide.collect()}
    for name, stage in P.STAGES[:-1]:
        got = stage(spark, wide, sf)
        assert got.columns == wide.columns, name
        for r in got.collect():
            want, changed = known[r["_row"]].asDict(), {"text", "n_chars"} if name == "secrets" else set()
            assert {k: v for k, v in r.asDict().items() if k not in changed} == {k: v for k, v in want.items() if k not in changed}, name
        if name == "secrets":
            assert got.count() == wide.count() and "[secret] and more" in {r.text for r in got.collect()}
    assert {r.doc_id for r in P.packing(spark, wide, sf).collect()} == {r.doc_id for r in known.values()}


def test_clashing_columns_in_operators(spark, sf, wide):
    items = spark.createDataFrame([(1, "b c")], "item_id long, text string")
    n = wide.count()
    assert language_id.identify(wide, None).where("not held_out").count() == n
    assert quality_classifier.classify(wide, None).where("not held_out and score = 0.5").count() == n
    assert substring_dedup.remove_repeats(wide).count() == n and near_dedup.near_duplicates(wide).count() == n
    assert decontamination.contamination_report(wide, items).count() == n and secret_scan.findings(wide).count() == n
    assert decontamination.keep_clean(wide, items).columns == wide.columns
    vectors = spark.createDataFrame([(k, [1.0, float(k)], 1, 2.0, 3) for k in range(4)], "vec_id long, embedding array<double>, rank int, score double, variant long")
    assert vector_search.nearest(vectors, vectors.where("vec_id = 0"), 2).count() == 2
    pages = spark.createDataFrame([(1, "http://a.org/1", "h", "v", 1)], "page_id long, url string, host string, verdict string, good int")
    assert [r.verdict for r in url_filter.judge(pages, pages).collect()] == ["allow"]
    chat = spark.createDataFrame([(1, 0, "user", "x", "t", 1, 2)], "conv_id long, turn long, role string, text string, tree string, node long, leaf int")
    assert [r.n for r in chat_format.format_trees(chat_format.reply_chain(chat)).collect()] == [1]


def test_repeated_ids_as_queries(spark):
    rows = [(0, [1.0, 0.0]), (0, [0.0, 1.0]), (0, [0.0, 1.0]), (1, [1.0, 0.1]), (2, [0.1, 1.0]), (2, [1.0, 1.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = collections.Counter((r["rank"], r.vec_id) for r in vector_search.nearest(frame, frame.where("vec_id = 0"), 2).collect())
    assert got == {(1, 1): 1, (2, 2): 2, (1, 2): 1}


def test_host_levels(spark):
    hosts = {"a.b.co.uk": ("b.co.uk", "co.uk"), "b.co.uk:80": ("b.co.uk", "co.uk"), "x.gob.ar": ("x.gob.ar", "gob.ar"), "www.example.org": ("example.org", "org"), "co.de.com": ("de.com", "com"), "10.0.0.1": ("10.0.0.1", ""), "": ("", ""), "host": ("host", "host")}
    got = url_filter.with_levels(spark.createDataFrame([(h,) for h in hosts], "host string")).collect()
    assert {r.host: (r.domain, r.suffix) for r in got} == hosts


def test_labels_of_repeated_ids(spark):
    """One text a label, however often its id stands in the tables; nulls teach nothing."""
    a, b, c = [i for i in range(50) if zlib.crc32(str(i).encode()) % 3 != 1][:3]
    docs = spark.createDataFrame([(a, f"text {i}") for i in range(50)] + [(b, "other"), (None, "x"), (c, None)], "doc_id long, text string")
    labels = spark.createDataFrame([(a, 1)] * 9 + [(b, 0), (None, 1), (c, 1), (a, None)], "doc_id long, quality int")
    seen = {}
    before, quality_classifier.Network.learn = quality_classifier.Network.learn, classmethod(lambda cls, texts, marks: seen.update(x=list(zip(texts, marks, strict=True))))
    try:
        quality_classifier.learn(docs, labels)
    finally:
        quality_classifier.Network.learn = before
    assert [q for _, q in seen["x"]] == [0, 1] and seen["x"][0][0] == "other" and seen["x"][1][0].startswith("text")


def test_score_by_brute_force():
    """The network's probability of each text, from its embedding, filters and weights alone."""
    Q, rng = quality_classifier, np.random.default_rng(3)
    net = Q.Network(11)
    net.p["bias"], net.p["shift"] = rng.normal(0, 0.3, Q.FILTERS).astype(np.float32), np.array([0.2], np.float32)
    texts = ["", "a", "no no yes no", "é" * 200, " ".join(rng.choice(["to", "be", "or", "not", "longer"], 400)), "x" * 1000]
    body, offsets = common.utf8(common.pa.array(texts))
    got = net.score(net.tables().astype(np.float32), *Q.symbols(body, offsets))
    for text, p in zip(texts, got, strict=True):
        raw, marked, words = text.encode(), [], []
        for word in [w for w in text.encode().replace(b"\n", b" ").split(b" ")]:
            marked += [b + 256 * bool(word and word in words[-Q.LOOK_BACK :]) for b in word] + [32]
            words += [word] if word else []
        symbols = marked[: len(raw)]
        halves = max(1, -(-(len(raw) + Q.WIDTH) // Q.HALF))
        symbols += [0] * (halves * Q.HALF + Q.WIDTH - len(symbols))
        best = []
        for h in range(halves):
            places = range(h * Q.HALF, (h + 1) * Q.HALF, Q.STRIDE)
            best.append(np.max([sum(net.p["embed"][symbols[at + k]] @ net.p["filter"][k] for k in range(Q.WIDTH)) for at in places], axis=0))
        chunks = [np.maximum(np.maximum(best[h], best[min(h + 1, halves - 1)]) + net.p["bias"], 0) for h in range(halves)]
        z = np.concatenate([np.mean(chunks, axis=0), np.max(chunks, axis=0)]) @ net.p["dense"] + net.p["shift"][0]
        assert p == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-4)


def test_held_out_accuracy(spark):
    """Of labels that learning never sees, at sf0.01."""
    sf = "/root/testdata/sf0.01"
    marks = {r["doc_id"]: r["quality"] for r in pq.read_table(f"{sf}/labels.parquet").to_pylist()}
    got = [r for r in quality_classifier.op10_quality_classifier(spark, sf).collect() if r.held_out and r.doc_id in marks]
    assert len(got) > 100 and np.mean([r.predicted == marks[r.doc_id] for r in got]) > 0.97
    langs = {r["doc_id"]: r["lang"] for r in pq.read_table(f"{sf}/documents.parquet", columns=["doc_id", "lang", "text"]).to_pylist() if r["lang"] and r["text"]}
    told = [r for r in language_id.op1_language_id(spark, sf).collect() if r.held_out and r.doc_id in langs]
    assert len(told) > 200 and np.mean([r.lang_pred == langs[r.doc_id] for r in told]) > 0.99


def test_scratch_is_deleted(spark):
    with common.scratch():
        kept = common.materialise(spark.range(3).toDF("x"))
        path = kept._written.path
        assert plain(kept.collect()) == plain([(0,), (1,), (2,)])
    assert not Path(path.removeprefix("file:")).exists()


def test_neighbours_joined_with_themselves(spark):
    frame = spark.createDataFrame([(k, [1.0, float(k)]) for k in range(5)], "vec_id long, embedding array<double>")
    near = vector_search.nearest(frame, frame, 2)
    back = near.select(near["vec_id"].alias("query_id"), near["query_id"].alias("vec_id"))
    assert near.join(back, ["query_id", "vec_id"]).count() > 0
