"""Operator 4: hierarchical residual best-fit packing of tokenised documents.

Tokens come from the public byte-level BPE file. A text is first cut where that tokenizer cuts in any
case (before white space that follows other text, and after a letter that no letter follows);
each distinct piece is then encoded once per worker, and the ids are gathered from that store. The store holds pieces of
``LONGEST`` bytes at most, up to ``STORE`` bytes in all, and compares their bytes: longer ones are encoded each time.

Packing: every task packs its own pieces best-fit, largest first, and emits the bins that are full but for
``slack`` tokens. Underfull bins go up a tree with fewer, larger groups, where whole bins are
the items of the next best-fit round. The tree ends at groups of ``group`` bins, where a larger group
would gain next to nothing, so no task ever holds more than that.

Scale: only (id, length, crc) rows move, never text or ids; a bin has at most ``size`` members.
"""

from __future__ import annotations

import os
import zlib
from collections import defaultdict
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C

SIZE, SLACK, FAN, GROUP = 2048, 8, 8, 50_000
STORE, LONGEST = 64 << 20, 256  # bytes of pieces, places and ids that a worker remembers; bytes of a piece
SLICE = 512 << 10  # bytes of text that are encoded at once: positions, hashes and ids take many times that
_SPACE = C.table_of((0x09, 0x0D), (0x20, 0x20))
_LETTER = C.table_of((0x41, 0x5A), (0x61, 0x7A))


def cut_points(body: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts of pieces that can be encoded by themselves; whether each can follow any other in one text."""
    n = len(body)
    before, two, three = (np.concatenate([np.zeros(k, np.uint8), body[: n - k]]) if n >= k else np.zeros(n, np.uint8) for k in (1, 2, 3))
    # a space of more than one byte (U+0085, U+00A0, U+1680, U+2000.., U+3000) can end before here
    wide_space = ((two == 0xC2) & ((before == 0x85) | (before == 0xA0))) | ((three >= 0xE1) & (three <= 0xE3))
    space = _SPACE[body]
    at_space = space & ~_SPACE[before] & ~wide_space
    latin = (two == 0xC3) & (before >= 0x80) & (before != 0x97) & (before != 0xB7)
    # not before |, which goes on the one special token that the file knows
    after_letter = (_LETTER[before] | latin) & ~_LETTER[body] & (body < 0x80) & (body != 0x7C)
    begin = at_space | after_letter
    head = offsets[:-1][np.diff(offsets) > 0]
    begin[head] = True
    start = np.flatnonzero(begin)
    end = np.append(start[1:], n)
    last = end - 1
    plain_end = ~space[last] & (body[last] < 0x80)
    return start, space[start] & plain_end


class PieceEncoder:
    """Ids of texts; distinct pieces are encoded once and remembered."""

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=True)
        self.width = np.zeros(max(vocabulary.values()) + 1, np.int64)
        for token, k in vocabulary.items():
            self.width[k] = len(token)  # one letter of the byte alphabet for each byte
        self.forget()

    def forget(self) -> None:
        """An empty store: hashes (ascending), and of each its bytes and its ids as (place, number) in two flat arrays."""
        self.keys = np.zeros(0, np.uint64)
        self.at, self.count, self.byte_at, self.size = (np.zeros(0, kind) for kind in (np.int32, np.int16, np.int32, np.int16))
        self.ids, self.bytes = np.zeros(0, np.int32), np.zeros(0, np.uint8)

    def held(self) -> int:
        return 20 * len(self.keys) + 4 * len(self.ids) + len(self.bytes)

    def _encode(self, texts: list[str]) -> list[list[int]]:
        return [x.ids for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _ids_of(self, body, start, end, joinable) -> tuple[np.ndarray, np.ndarray]:
        """(ids of the pieces one after the other, number of each), from the tokenizer."""
        count = np.zeros(len(start), np.int64)
        parts, order = [np.zeros(0, np.int32)], [np.zeros(0, np.int64)]
        if len(together := np.flatnonzero(joinable)):
            width = end[together] - start[together]
            text = body[C.ranges(start[together], width)].tobytes().decode()
            ids = np.array(self._encode([text])[0], np.int32)
            token_end = np.cumsum(self.width[ids])
            stop = np.searchsorted(token_end, piece_end := np.cumsum(width)) + 1
            if not np.array_equal(token_end[stop - 1], piece_end):
                raise ValueError("a token reaches over a cut point")
            count[together] = np.diff(stop, prepend=0)
            parts.append(ids)
            order.append(np.repeat(together, count[together]))
        if len(alone := np.flatnonzero(~joinable)):
            each = self._encode([body[a:b].tobytes().decode() for a, b in zip(start[alone], end[alone], strict=True)])
            count[alone] = [len(x) for x in each]
            parts.append(np.array([i for x in each for i in x], np.int32))
            order.append(np.repeat(alone, count[alone]))
        return np.concatenate(parts)[np.argsort(np.concatenate(order), kind="stable")], count

    def _learn(self, body, start, end, joinable, keys) -> None:
        """Put pieces (keys ascending, none of them held) into the store."""
        ids, count = self._ids_of(body, start, end, joinable)
        size = end - start
        where = np.searchsorted(self.keys, keys)
        places = len(self.ids) + np.cumsum(count) - count, count, len(self.bytes) + np.cumsum(size) - size, size
        self.keys = np.insert(self.keys, where, keys)
        self.at, self.count, self.byte_at, self.size = (np.insert(old, where, new) for old, new in zip((self.at, self.count, self.byte_at, self.size), places, strict=True))
        self.ids, self.bytes = np.append(self.ids, ids), np.append(self.bytes, body[C.ranges(start, size)])

    def encode(self, body: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all rows, first id of each row and the end)."""
        if not len(body):
            return np.zeros(0, np.int32), np.zeros(len(offsets), np.int64)
        if self.held() > STORE:
            self.forget()
        start, joinable = cut_points(body, offsets)
        end = np.append(start[1:], len(body))
        size = end - start
        short = size <= LONGEST
        hashes = C.word_hashes(body, start, end)
        keys, first, back = np.unique(hashes, return_index=True, return_inverse=True)
        where = np.minimum(np.searchsorted(self.keys, keys), max(len(self.keys) - 1, 0))
        known = self.keys[where] == keys if len(self.keys) else np.zeros(len(keys), bool)
        new = np.flatnonzero(~known & short[first])
        if len(new):
            pick = first[new]
            self._learn(body, start[pick], end[pick], joinable[pick], keys[new])
        slot = np.minimum(np.searchsorted(self.keys, keys), max(len(self.keys) - 1, 0))[back]
        # a piece is taken from the store if its bytes are there, not if its hash is
        same = short & (self.size[slot] == size if len(self.keys) else False)
        at = np.flatnonzero(same)
        equal = body[C.ranges(start[at], size[at])] == self.bytes[C.ranges(self.byte_at[slot[at]], size[at])]
        same[at] = np.logical_and.reduceat(equal, np.cumsum(size[at]) - size[at]) if len(at) else True
        count, place, source = np.zeros(len(start), np.int64), np.zeros(len(start), np.int64), self.ids
        count[same], place[same] = self.count[slot[same]], self.at[slot[same]]
        if len(other := np.flatnonzero(~same)):
            ids, count[other] = self._ids_of(body, start[other], end[other], np.zeros(len(other), bool))
            place[other] = len(source) + np.cumsum(count[other]) - count[other]
            source = np.append(source, ids)
        upto = np.append(0, np.cumsum(count))
        return source[C.ranges(place, count)], upto[np.searchsorted(start, offsets)]


@lru_cache(maxsize=2)
def encoder(path: str) -> PieceEncoder:
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core; each thread would keep memory of its own
    return PieceEncoder(path)


C.remembers("packing", encoder.cache_clear)


def best_fit(sizes: np.ndarray, capacity: int) -> list[list[int]]:
    """Bins of item numbers: largest items first, each into the fullest bin that it fits."""
    room: dict[int, list[int]] = defaultdict(list)  # by room left
    bins: list[list[int]] = []
    open_rooms = 0  # bit r: some bin has room r
    for i in np.argsort(-sizes, kind="stable").tolist():
        s = int(sizes[i])
        fits = open_rooms >> s
        if fits:
            r = s + (fits & -fits).bit_length() - 1
            b = room[r].pop()
            if not room[r]:
                open_rooms ^= 1 << r
            bins[b].append(i)
        else:
            r, b = capacity, len(bins)
            bins.append([i])
        if r > s:
            room[r - s].append(b)
            open_rooms |= 1 << (r - s)
    return bins


_MEMBER = ("doc_id", "piece", "start", "length", "ids_crc32")
_BIN = "sequence_id long, fill int, final boolean, " + ", ".join(f"{k} array<long>" for k in _MEMBER)
_EMPTY = {k: np.zeros(0, np.int64) for k in _MEMBER}


def _pieces(ids: np.ndarray, first: np.ndarray, docs: np.ndarray, size: int) -> dict[str, np.ndarray]:
    """Rows of the pieces of each document: its ids, then id 0; the first piece takes what doesn't divide."""
    length = np.diff(first) + 1
    flat = np.zeros(len(ids) + len(docs), np.uint32)
    flat[C.ranges(first[:-1] + np.arange(len(docs)), length - 1)] = ids
    begin = first[:-1] + np.arange(len(docs))
    number = -(-length // size)
    lead = length - (number - 1) * size
    piece = C.ranges(np.zeros(len(docs), np.int64), number)
    at = np.where(piece == 0, 0, np.repeat(lead, number) + (piece - 1) * size)
    each = np.where(piece == 0, np.repeat(lead, number), size)
    raw, place = memoryview(flat.astype("<u4").tobytes()), np.repeat(begin, number) + at
    crc = np.array([zlib.crc32(raw[4 * a : 4 * (a + n)]) for a, n in zip(place.tolist(), each.tolist(), strict=True)], np.int64)
    return dict(zip(_MEMBER, (np.repeat(docs, number), piece, at, each, crc), strict=True))


def _bins(groups: list[list[int]], fill: np.ndarray, final: np.ndarray, level: int, base: int, member: dict[str, np.ndarray], edge: np.ndarray) -> pa.RecordBatch:
    """Bins of items; item i holds the members edge[i] .. edge[i+1]-1."""
    flat = np.array([i for g in groups for i in g], np.int64)
    each = np.diff(edge)[flat]
    order = C.ranges(edge[flat], each)
    upto = np.append(0, np.cumsum(each))[np.append(0, np.cumsum([len(g) for g in groups]))].astype(np.int32)
    ids = (level << 56) + (TaskContext.get().partitionId() << 32) + base + np.arange(len(groups))
    lists = [pa.ListArray.from_arrays(pa.array(upto), pa.array(member[k][order], pa.int64())) for k in _MEMBER]
    names = ["sequence_id", "fill", "final", *_MEMBER]
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(fill, pa.int32()), pa.array(final), *lists], names=names)


def _pack(member: dict[str, np.ndarray], edge: np.ndarray, size: int, slack: int, level: int, base: int, last: bool) -> pa.RecordBatch:
    sizes = np.add.reduceat(member["length"], edge[:-1])
    groups = best_fit(sizes, size)
    fill = np.array([int(sizes[g].sum()) for g in groups])
    return _bins(groups, fill, (fill >= size - slack) | last, level, base, member, edge)


def _first_level(path: str, size: int, slack: int, group: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tool, parts, held, base = encoder(path), [], 0, 0

        def flush():
            nonlocal parts, held, base
            member = {k: np.concatenate([p[k] for p in parts]) for k in _MEMBER}
            out = _pack(member, np.arange(held + 1), size, slack, 0, base, False)
            parts, held, base = [], 0, base + len(out)
            return out

        for batch in batches:
            docs = batch.column("doc_id").to_numpy(zero_copy_only=False)
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, SLICE):
                ids, first = tool.encode(body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
                parts.append(_pieces(ids, first, docs[i:j], size))
                held += len(parts[-1]["doc_id"])
                if held >= group:
                    yield flush()
        if held:
            yield flush()

    return C.tidy(run, "packing")


def _next_level(size: int, slack: int, group: int, level: int, last: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base, held = 0, []

        def flush(rows: pa.Table):
            lists = {k: rows.column(k).combine_chunks() for k in _MEMBER}
            edge = np.append(0, np.cumsum(lists["length"].value_lengths().to_numpy()))
            return _pack({k: x.flatten().to_numpy() for k, x in lists.items()}, edge, size, slack, level, base, last)

        for batch in batches:
            held.append(batch)
            if sum(map(len, held)) >= group:
                yield (out := flush(pa.Table.from_batches(held)))
                held, base = [], base + len(out)
        if sum(map(len, held)):
            yield flush(pa.Table.from_batches(held))

    return C.tidy(run, "packing")


def pack(docs: DataFrame, path: str | None = None, size: int = SIZE, slack: int = SLACK, fan: int = FAN, group: int = GROUP) -> DataFrame:
    """Documents (doc_id, text) to (doc_id, piece, start, length, ids_crc32, sequence_id, offset), a row per
    piece. A null or empty text is the one id 0; a null id stays null; rows that repeat an id are
    packed each for itself; an empty table gives no row. sequence_id: level, task, number."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    texts = docs.select(C.known_id().alias("doc_id"), F.col("text").cast("string").alias("text"))
    bins = C.materialise(texts.mapInArrow(_first_level(path, size, slack, group), _BIN), "bins")
    done, level = [bins.where("final")], 0
    groups = max(1, texts.rdd.getNumPartitions())
    while True:
        rest = bins.where("not final")
        n = rest.count()
        if not n:
            break
        least = -(-n // group)
        groups, level = max(least, groups // fan), level + 1
        last = groups == least
        bins = C.materialise(rest.repartition(groups, "sequence_id").mapInArrow(_next_level(size, slack, 2 * group, level, last), _BIN), "bins")
        if last:
            done.append(bins)
            break
        done.append(bins.where("final"))
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    members = F.arrays_zip(*_MEMBER)
    placed = F.transform(members, lambda m, i: F.struct(*(m[k].alias(k) for k in _MEMBER), F.aggregate(F.slice("length", 1, i), F.lit(0).cast("long"), lambda a, b: a + b).alias("offset")))
    out = out.select("sequence_id", F.explode(placed).alias("m"))
    return out.select(C.original_id("m.doc_id").alias("doc_id"), F.col("m.piece").cast("int").alias("piece"), "m.start", "m.length", "m.ids_crc32", "sequence_id", "m.offset")


def op4_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(C.table(spark, sf_dir, "documents"))
