"""What a worker holds while it works, and what it keeps for later tasks."""

import random
import tracemalloc

import pyarrow as pa
from public_tokenizers import path

from vertexalg.llm import common, decontamination, packing


def peak_mb(run) -> float:
    tracemalloc.start()
    try:
        run()
        return tracemalloc.get_traced_memory()[1] / 2**20
    finally:
        tracemalloc.stop()


def texts(n: int, words: int) -> list[str]:
    rng = random.Random(5)
    some = ["".join(rng.choices("abcdefghij", k=rng.randint(2, 9))) for _ in range(500)]
    return [" ".join(rng.choices(some, k=words)) for _ in range(n)]


def test_scan_works_in_slices(spark):
    rows = texts(1200, 1000)  # 7.7 MB, more than one slice
    rows[700] = None
    planted = {3, 699, 1199}
    passage = " ".join(f"w{k}" for k in range(12))
    for k in planted:
        rows[k] = f"{rows[k]} {passage.upper()} end"
    docs = spark.createDataFrame([(0, "")], "doc_id long, text string")
    kept = []

    class Frame:
        schema = docs.schema

        def mapInArrow(self, run, schema):
            self.run = run
            return self

    frame = decontamination.keep_clean(Frame(), spark.createDataFrame([("i", passage)], "item_id string, text string"))
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(rows)), pa.int64()), pa.array(rows)], names=["doc_id", "text"])
    assert peak_mb(lambda: kept.extend(x for part in frame.run(iter([batch])) for x in part.column("doc_id").to_pylist())) < 60
    assert kept == [k for k in range(len(rows)) if k not in planted]


def test_encoder_is_dropped_by_other_operators():
    tool = packing.encoder(path("byte_bpe_50k.json"))
    list(common.tidy(iter, "packing")([]))
    assert packing.encoder(path("byte_bpe_50k.json")) is tool
    list(common.tidy(iter)([]))
    assert packing.encoder.cache_info().currsize == 0
