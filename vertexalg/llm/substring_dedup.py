"""Operator 3: exact substring deduplication by relative Lempel-Ziv parsing.

A phrase is a run of windows (of ``size`` words) that share their least 8-word hash, so equal
passages are cut into equal phrases wherever they stand. Phrases go to the reference block
that their least hash names; there each document is parsed greedily against everything that the
block indexes: a factor goes on while the next window continues the same earlier source, and at
its boundary the window is looked up afresh among all sources. A factor holds one window or more,
so every factor is a duplicate span of ``size`` words at least.

A row is a document of its own, whatever its id: rows are numbered before anything else, and dealt by number in one
shuffle that the parse and the cut both read. Rows are ordered by id (null first) and then by number.

Scale: one shuffle of text, one of phrases (about a byte per byte of text), one of factors. Each task first parses
against its own slice of rows and sends only the windows that are first there, so a passage that a third of all rows
hold arrives once per slice. Phrases come sorted by block, so a task holds some whole blocks at a time.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C

WINDOW, ANCHOR = 20, 8
SLICE = 8 << 20
_PHRASE = "block long, row long, doc_id long, start int, n int, hashes binary, from_row long, from_doc long, from_start int"
_FACTOR = "row long, doc_id long, start int, n int, from_row long, from_doc long, from_start int"
_AT_ONCE = 400_000  # windows of whole blocks that are compared at a time
_KEPT_BYTES = 5  # of a window's hash, beside the 8 bytes of the phrase's


def _least(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of width values."""
    have, out = 1, values
    while have * 2 <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    rest = width - have
    return np.minimum(out[:-rest], out[rest:]) if rest else out


def _factors(row, start, from_row, from_start, duplicate):
    """Greedy factors among windows in document order: [first, count] of windows that go on in one source."""
    at = np.flatnonzero(duplicate)
    if not len(at):
        return at, at
    a, b = at[1:], at[:-1]
    new = np.ones(len(at), bool)
    new[1:] = (row[a] != row[b]) | (start[a] != start[b] + 1) | (from_row[a] != from_row[b]) | (from_start[a] != from_start[b] + 1)
    first = np.flatnonzero(new)
    return at[first], np.diff(np.append(first, len(at)))


def _batch(schema: str, **columns) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary()}
    fields = [x.split() for x in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(columns[k], kinds[t]) if not isinstance(columns[k], pa.Array) else columns[k] for k, t in fields], names=[k for k, _ in fields])


def _binary(rows: np.ndarray, length: np.ndarray) -> pa.Array:
    """Rows of bytes (windows x _KEPT_BYTES), joined length[i] at a time."""
    at = np.zeros(len(length) + 1, np.int32)
    np.cumsum(length * _KEPT_BYTES, out=at[1:])
    return pa.Array.from_buffers(pa.binary(), len(length), [None, pa.py_buffer(at), pa.py_buffer(np.ascontiguousarray(rows).tobytes())])


def _parse(size: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        anchor = min(ANCHOR, size)
        for batch in batches:
            batch = pa.Table.from_batches([batch]).sort_by([("doc_id", "ascending"), ("row", "ascending")]).combine_chunks()
            numbers, ids = (batch.column(k).to_numpy() for k in ("row", "doc_id"))
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, SLICE):
                off = offsets[i : j + 1] - offsets[i]
                start, end, first = C.spans(C.SPACE_WORD, part := body[offsets[i] : offsets[j]], off)
                words = C.word_hashes(part, start, end)
                if len(words) < size:
                    continue
                count = np.diff(first)
                ok = np.arange(len(words) - size + 1) + size <= np.repeat(first[1:], count)[: len(words) - size + 1]
                place = np.flatnonzero(ok)
                if not len(place):
                    continue
                line = np.repeat(np.arange(j - i), count)[place]
                row, doc, pos = numbers[i:j][line], ids[i:j][line], (place - first[line]).astype(np.int32)
                window = C.window_hashes(words, size)[place]
                block = _least(C.window_hashes(words, anchor), size - anchor + 1)[place]
                # the earliest place of each window in this slice (rows are in order)
                order = np.argsort(window, kind="stable")
                same = np.zeros(len(order), bool)
                same[1:] = window[order[1:]] == window[order[:-1]]
                lead = np.maximum.accumulate(np.where(same, 0, np.arange(len(order))))
                source = np.empty(len(order), np.int64)
                source[order] = order[lead]
                later = source != np.arange(len(order))
                f, n = _factors(row, pos, row[source], pos[source], later)
                if len(f):
                    # settled: any block will do
                    g = source[f]
                    yield _batch(_PHRASE, block=C.mix(row[f].view(np.uint64) + pos[f].astype(np.uint64)).view(np.int64), row=row[f], doc_id=doc[f], start=pos[f], n=n, hashes=pa.nulls(len(f), pa.binary()), from_row=row[g], from_doc=doc[g], from_start=pos[g])
                keep = np.flatnonzero(~later)
                new = np.ones(len(keep), bool)
                a, b = keep[1:], keep[:-1]
                new[1:] = (row[a] != row[b]) | (pos[a] != pos[b] + 1) | (block[a] != block[b])
                head = np.flatnonzero(new)
                length = np.diff(np.append(head, len(keep)))
                p = keep[head]
                raw = window[keep].view(np.uint8).reshape(-1, 8)[:, :_KEPT_BYTES]
                zero = np.zeros(len(p), np.int64)
                yield _batch(_PHRASE, block=block[p].view(np.int64), row=row[p], doc_id=doc[p], start=pos[p], n=length, hashes=_binary(raw, length), from_row=zero, from_doc=zero, from_start=zero)

    return C.tidy(run)


def _resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Phrases sorted by block to factors: which of their windows stand earlier elsewhere. Holds whole blocks of about
    _AT_ONCE windows; the last block of a batch may go on in the next."""
    held: list[pa.RecordBatch] = []
    weight = 0

    def flush(last: bool) -> Iterator[pa.RecordBatch]:
        nonlocal held, weight
        data = pa.Table.from_batches(held).combine_chunks()
        key = data.column("block").to_numpy()
        cut = len(key) if last else int(np.searchsorted(key, key[-1]))
        held = data.slice(cut).to_batches() if cut < len(key) else []
        weight = int(data.column("n").to_numpy()[cut:].sum())
        data, key = data.slice(0, cut), key[:cut]
        # phrases whose block stands alone can have no earlier source
        edge = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
        size = np.diff(np.append(edge, len(key)))
        if (size > 1).any() and (found := _resolve_blocks(data.take(pa.array(np.flatnonzero(np.repeat(size > 1, size)))))) is not None:
            yield found

    for batch in batches:
        known = pc.is_null(batch.column("hashes"))
        if len(found := batch.filter(known)):
            yield found.select([k.split()[0] for k in _FACTOR.split(", ")])
        if len(rest := batch.filter(pc.invert(known))):
            held.append(rest.select(["block", "row", "doc_id", "start", "n", "hashes"]))
            weight += pc.sum(rest.column("n")).as_py()
            # nothing is whole yet while all that is held is of one block
            if weight > _AT_ONCE and held[0].column("block")[0] != rest.column("block")[-1]:
                yield from flush(False)
    if held:
        yield from flush(True)


def _resolve_blocks(data: pa.Table) -> pa.RecordBatch | None:
    data = data.sort_by([("doc_id", "ascending"), ("row", "ascending"), ("start", "ascending")]).combine_chunks()
    key, row0, doc0, start0, n = (data.column(k).to_numpy() for k in ("block", "row", "doc_id", "start", "n"))
    raw, _ = C.utf8(data.column("hashes"))
    wide = np.zeros((len(raw) // _KEPT_BYTES, 8), np.uint8)
    wide[:, :_KEPT_BYTES] = raw.reshape(-1, _KEPT_BYTES)
    short = wide.reshape(-1).view(np.uint64)
    key, row, doc = (np.repeat(x, n) for x in (key, row0, doc0))
    key = key.view(np.uint64)
    pos = C.ranges(start0.astype(np.int64), n)
    joint = C.mix(key ^ (short << np.uint64(16)))
    order = np.argsort(joint, kind="stable")
    a, b = order[1:], order[:-1]
    same = np.zeros(len(order), bool)
    same[1:] = (joint[a] == joint[b]) & (short[a] == short[b]) & (key[a] == key[b])
    lead = np.maximum.accumulate(np.where(same, 0, np.arange(len(order))))
    source = np.empty(len(order), np.int64)
    source[order] = order[lead]
    later = source != np.arange(len(order))
    f, n = _factors(row, pos, row[source], pos[source], later)
    if not len(f):
        return None
    g = source[f]
    return _batch(_FACTOR, row=row[f], doc_id=doc[f], start=pos[f].astype(np.int32), n=n, from_row=row[g], from_doc=doc[g], from_start=pos[g].astype(np.int32))


def _numbered(docs: DataFrame) -> DataFrame:
    """(row, doc_id, text), dealt by row. Each use plans the same shuffle, which Spark then writes once."""
    rows = docs.select(F.monotonically_increasing_id().alias("row"), C.known_id().alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.repartition("row")


def _found(numbered: DataFrame, size: int) -> DataFrame:
    phrases = numbered.mapInArrow(_parse(size), _PHRASE)
    return phrases.repartition("block").sortWithinPartitions("block").mapInArrow(_resolve, _FACTOR)


def factors(docs: DataFrame, size: int = WINDOW) -> DataFrame:
    """Duplicate spans of documents (doc_id, text): words start .. start+n+size-2 of a row also begin at from_start of an
    earlier row (from_row, of id from_doc) or earlier in the same. Every row is a document, in the order of ids (null first), rows
    of one id in that of their numbers (row, as Spark numbers them). Null and empty texts and those under size words have no span."""
    return _found(_numbered(docs), size).withColumn("doc_id", C.original_id()).withColumn("from_doc", C.original_id("from_doc"))


def _cut(size: int, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            body, offsets = C.utf8(batch.column("text"))
            starts, lengths = batch.column("starts"), batch.column("lengths")
            for i, j in C.row_slices(offsets):
                off = offsets[i : j + 1] - offsets[i]
                part = body[offsets[i] : offsets[j]]
                start, end, first = C.spans(C.SPACE_WORD, part, off)
                s, m = (x.slice(i, j - i) for x in (starts, lengths))
                each = pc.fill_null(pc.list_value_length(s), 0).to_numpy(zero_copy_only=False)
                flat = s.flatten().to_numpy(zero_copy_only=False).astype(np.int64) + np.repeat(first[:-1], each)
                gone = C.covered(len(start), flat, m.flatten().to_numpy(zero_copy_only=False).astype(np.int64) + size - 1)
                left = np.flatnonzero(~gone)
                width = end[left] - start[left] + 1
                text = np.append(part, np.uint8(32))[C.ranges(start[left], width)]
                stop = np.cumsum(width)
                text[stop - 1] = 32
                stop = np.append(0, stop)
                edge = np.searchsorted(left, first)
                raw = text.tobytes()
                each_text = [raw[stop[a] : stop[b] - 1] if b > a else b"" for a, b in zip(edge[:-1], edge[1:], strict=True)]
                out = [batch.column("doc_id").slice(i, j - i), pa.array(np.diff(first), pa.int64()), pa.array(np.diff(first) - np.diff(edge), pa.int64())]
                out.append(pa.array([x.decode() for x in each_text] if with_text else [hashlib.sha256(x).hexdigest() for x in each_text], pa.string()))
                yield pa.RecordBatch.from_arrays(out, names=["doc_id", "n_words", "n_removed", "kept"])

    return C.tidy(run)


def remove_repeats(docs: DataFrame, size: int = WINDOW, digest: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept): kept are the words outside all duplicate spans, joined by
    one space, or with digest the SHA-256 of that. One row per input row; of rows with equal texts the first keeps them.
    Null and empty texts have no words; an empty table gives no row; other columns of docs are left out."""
    numbered = _numbered(docs)
    found = _found(numbered, size).groupBy("row").agg(F.collect_list(F.struct("start", "n")).alias("x"))
    found = found.select("row", F.col("x.start").alias("starts"), F.col("x.n").alias("lengths"))
    out = numbered.join(found, "row", "left").mapInArrow(_cut(size, not digest), "doc_id long, n_words long, n_removed long, kept string")
    return out.withColumn("doc_id", C.original_id())


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(C.table(spark, sf_dir, "documents"), digest=True).withColumnRenamed("kept", "kept_sha256")


#: Every window of 20 words by itself; those that stand earlier too cover the words that go.
OP3_SQL = r"""with d as materialized (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
x as materialized (select doc_id, i, array_to_string(w[i : i + 19], ' ') as shown from d, unnest(generate_series(1, len(w) - 19)) u(i)),
again as (select doc_id, i from (select doc_id, i, row_number() over (partition by shown order by doc_id, i) as k from x) where k > 1),
gone as (select distinct doc_id, p from again, unnest(generate_series(i, i + 19)) u(p)),
words as (select doc_id, unnest(w) as word, generate_subscripts(w, 1) as p from d),
kept as (select doc_id, count(*) as n, string_agg(word, ' ' order by p) as text from words anti join gone using (doc_id, p) group by doc_id)
select doc_id, len(w)::bigint as n_words, (len(w) - coalesce(n, 0))::bigint as n_removed, sha256(coalesce(kept.text, '')) as kept_sha256 from d left join kept using (doc_id)"""
