"""Operator 5: benchmark decontamination with one Aho-Corasick automaton.

Patterns are the word windows of the benchmark's items, normalised (A-Z lowered, words joined by one
space, a space at both ends). Each slice of text is normalised by byte tables, scanned once, and the
hits are mapped back through the numbers of the words, whose byte places in the original are known.

Scale: the text is scanned where it lies and never shuffled. The automaton is shipped with the task,
so its size is checked: patterns beyond ``limit`` bytes go to further automata, each with a scan of
its own over the texts, written once with a number for each row, by which the hits are merged.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C

WINDOW, LIMIT = 10, 32 << 20
SLICE = 512 << 10  # bytes of text that are scanned at once: their positions take some 50 times that


def normal_words(text: str | None) -> list[bytes]:
    body = C.LOWER[np.frombuffer((text or "").encode(), np.uint8)]
    start, end, _ = C.spans(C.ALNUM_WORD, body, np.array([0, len(body)]))
    raw = body.tobytes()
    return [raw[a:b] for a, b in zip(start.tolist(), end.tolist(), strict=True)]


def patterns_of(items: Iterator[tuple[object, str | None]], size: int = WINDOW) -> dict[bytes, tuple[int, list[str]]]:
    """Window text -> (its words, the items that have it; one without an id has no name here)."""
    found: dict[bytes, tuple[int, list[str]]] = {}
    for item, text in items:
        words = normal_words(text)
        n = min(size, len(words))
        for window in {b" " + b" ".join(words[i : i + n]) + b" " for i in range(len(words) - n + 1)} if n else ():
            owners = found.setdefault(window, (n, []))[1]
            if item is not None:
                owners.append(str(item))
    return found


def _blocks(items: DataFrame, size: int, limit: int) -> Iterator[dict[bytes, tuple[int, list[str]]]]:
    """Patterns in blocks whose text stays under limit (rows come one partition at a time)."""
    held, weight = [], 0
    for row in items.toLocalIterator():
        # a window costs its own bytes in the automaton: size times the item's text at most
        cost = (len(row[1]) if row[1] else 0) * size
        if held and weight + cost > limit:
            yield patterns_of(iter(held), size)
            held, weight = [], 0
        held.append((row[0], row[1]))
        weight += cost
    yield patterns_of(iter(held), size)


def _normalise(part: np.ndarray, off: np.ndarray):
    """Slice of rows to ' w1 w2 ... ' per row, one string; word counts by row; byte places of words."""
    low = C.LOWER[part]
    start, end, first = C.spans(C.ALNUM_WORD, low, off)
    count = np.diff(first)
    full = np.flatnonzero(count)
    # each word with the byte after it (a space by then); each row that has words opens with a space
    width = end - start + 1
    source = C.ranges(start, width)
    text = np.append(low, np.uint8(32))[source]
    stop = np.cumsum(width)
    text[stop - 1] = 32
    lead = (stop - width)[first[:-1][full]]
    text = np.insert(text, lead, 32)
    # 0 parts the rows, so that no pattern reaches over
    row_end = stop[first[1:][full] - 1] + np.arange(1, len(full) + 1)
    text = np.insert(text, row_end, 0)
    return text, start, end, first


_HIT = "{} long, n_words long, hits array<struct<start: int, length: int>>, items array<string>"


def _automaton(patterns: dict[bytes, tuple[int, list[str]]]):
    import ahocorasick

    machine = ahocorasick.Automaton()
    for window, value in patterns.items():
        machine.add_word(window.decode("latin-1"), value)
    machine.make_automaton()
    return machine


def _scan(patterns: dict[bytes, tuple[int, list[str]]], key: str = "doc_id"):
    built = []

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not built:
            built.append(_automaton(patterns))
        machine = built[0]
        for batch in batches:
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, SLICE):
                off = offsets[i : j + 1] - offsets[i]
                text, start, end, first = _normalise(body[offsets[i] : offsets[j]], off)
                places, lengths, which = [], [], []
                if len(patterns):
                    for at, (n, owners) in machine.iter(text.tobytes().decode("latin-1")):
                        places.append(at)
                        lengths.append(n)
                        which.append(owners)
                hits: list[list[dict]] = [[] for _ in range(j - i)]
                items: list[set[str]] = [set() for _ in range(j - i)]
                if places:
                    # a space stands after each word and before the first of a row
                    is_space = np.cumsum(text == 32)
                    rows_before = np.cumsum(text == 0)
                    at = np.array(places)
                    last = is_space[at] - rows_before[at] - 2  # number of the hit's last word
                    length = np.array(lengths)
                    row = np.searchsorted(first, last, side="right") - 1
                    for r, s, n, owners in zip(row.tolist(), (last - length + 1 - first[row]).tolist(), lengths, which, strict=True):
                        hits[r].append({"start": s, "length": n})
                        items[r].update(owners)
                columns = [batch.column(key).slice(i, j - i), pa.array(np.diff(first), pa.int64())]
                columns.append(pa.array(hits, pa.list_(pa.struct([("start", pa.int32()), ("length", pa.int32())]))))
                columns.append(pa.array([sorted(x) for x in items], pa.list_(pa.string())))
                yield pa.RecordBatch.from_arrays(columns, names=[key, "n_words", "hits", "items"])

    return C.tidy(run)


def find_contamination(docs: DataFrame, items: DataFrame, size: int = WINDOW, limit: int = LIMIT) -> DataFrame:
    """(doc_id, n_words, hits, items) per document: hits are word ranges that a benchmark window covers, items
    the sorted ids of the items that have one. Null and empty texts have no words, an item without words no
    window, an item of fewer words than size is one window; repeated item rows count as one item. An item with a null id makes hits like any other, but no name
    in items: it counts for n_hit and contaminated, not for n_items and items_sha256."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    passages = items.select(F.col("item_id").cast("string"), F.col("text").cast("string"))
    blocks = _blocks(passages, size, limit)
    first, second = next(blocks), next(blocks, None)
    if second is None:
        return texts.mapInArrow(_scan(first), _HIT.format("doc_id"))
    # ids can repeat or be null: a written number names the row
    rows = C.materialise(texts.withColumn("row", F.monotonically_increasing_id()), "texts")
    every = rows.select("row", "text").mapInArrow(_scan(first, "row"), _HIT.format("row"))
    for block in (second, *blocks):
        every = every.unionByName(rows.select("row", "text").mapInArrow(_scan(block, "row"), _HIT.format("row")).where("size(hits) > 0"))
    merged = every.groupBy("row").agg(F.max("n_words").alias("n_words"), F.flatten(F.collect_list("hits")).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    return rows.select("row", "doc_id").join(merged, "row").select("doc_id", "n_words", "hits", "items")


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        n_words = batch.column("n_words").to_numpy(zero_copy_only=False)
        hits, items = batch.column("hits"), batch.column("items")
        each = hits.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        flat, base = hits.flatten(), np.append(0, np.cumsum(n_words))
        start = flat.field("start").to_numpy(zero_copy_only=False).astype(np.int64) + np.repeat(base[:-1], each)
        hit = C.covered(int(base[-1]), start, flat.field("length").to_numpy(zero_copy_only=False).astype(np.int64))
        n_hit = np.diff(np.append(0, np.cumsum(hit))[base])
        names = items.to_pylist()
        columns = [batch.column("doc_id"), batch.column("n_words"), pa.array(n_hit, pa.int64()), pa.array([len(x) for x in names], pa.int64())]
        columns += [pa.array([hashlib.sha256(",".join(x).encode()).hexdigest() for x in names]), pa.array(n_hit > 0)]
        yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"])


def contamination_report(docs: DataFrame, items: DataFrame, size: int = WINDOW, limit: int = LIMIT) -> DataFrame:
    return find_contamination(docs, items, size, limit).mapInArrow(_digest, "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean")


def keep_clean(docs: DataFrame, items: DataFrame, size: int = WINDOW, limit: int = LIMIT) -> DataFrame:
    """The rows of docs (text, any other columns) that hold no window of items (item_id, text); one filter per automaton."""
    passages = items.select(F.col("item_id").cast("string"), F.col("text").cast("string"))

    def clean(patterns):
        scan = _scan(patterns)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                key, at = pa.array(np.arange(len(batch))), 0
                for part in scan(iter([pa.RecordBatch.from_arrays([key, batch.column("text")], names=["doc_id", "text"])])):
                    clear = [len(x) == 0 for x in part.column("hits")]
                    yield batch.slice(at, len(part)).filter(pa.array(clear))
                    at += len(part)

        return C.tidy(run)

    for block in _blocks(passages, size, limit):
        docs = docs.mapInArrow(clean(block), docs.schema)
    return docs


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination_report(C.table(spark, sf_dir, "documents"), C.table(spark, sf_dir, "benchmark"))


#: Windows of documents and items as text, joined; one row per document.
OP5_SQL = r"""with d as materialized (select row_number() over () as r, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
b as materialized (select item_id, w, least(len(w), 10) as n from (select distinct item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark where item_id is not null)),
p as materialized (select distinct item_id, n, array_to_string(w[i : i + n - 1], ' ') as shown from b, unnest(generate_series(1, len(w) - n + 1)) u(i) where n > 0),
x as materialized (select r, i, n, array_to_string(w[i : i + n - 1], ' ') as shown from d, (select distinct n from p), unnest(generate_series(1, len(w) - n + 1)) u(i)),
o as materialized (select r, i, n, item_id from x join p using (n, shown)),
h as (select r, count(distinct k) as n_hit from o, unnest(generate_series(i, i + n - 1)) u(k) group by r),
t as (select r, count(distinct item_id) as n_items, array_to_string(list_sort(list(distinct item_id::varchar)), ',') as items from o group by r)
select doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(items, '')) as items_sha256, n_hit is not null as contaminated
from d left join h using (r) left join t using (r)"""
