"""The stages of the pipeline against what each must do to its own input."""

import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))

import corpus_pipeline as P  # noqa: E402
from tests.llm.test_operators import classes  # noqa: E402


def test_stages(spark, sf):
    assert [n for n, _ in P.STAGES] == ["quality", "near_dedup", "decontaminate", "secrets", "packing"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    good = P.C.materialise(P.quality(spark, docs, sf))
    assert good.columns == columns and 0.5 * docs.count() < good.count() <= docs.count()
    single = P.C.materialise(P.near_dedup(spark, good, sf))
    want = classes([(r["doc_id"], r["text"]) for r in good.collect()])
    assert {r["doc_id"] for r in single.collect()} == set(want.values()) and single.columns == columns
    from vertexalg.llm.decontamination import contamination_report

    clean = P.C.materialise(P.decontaminate(spark, single, sf))
    report = {r.doc_id: r.contaminated for r in contamination_report(single, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
    assert {r["doc_id"] for r in clean.collect()} == {i for i, hit in report.items() if not hit}
    safe = P.C.materialise(P.secrets(spark, clean, sf))
    from vertexalg.llm.secret_scan import findings

    assert safe.columns == columns and safe.count() == clean.count()
    assert findings(safe.select("doc_id", "text")).where("size(spans) > 0").isEmpty()
    assert safe.where("n_chars <> length(text)").isEmpty()
    packed = P.packing(spark, safe, sf)
    assert packed.select("doc_id").distinct().count() == safe.count()
