"""Shared pieces of the text operators: table access, shared-folder tables, and
vectorised work on the UTF-8 bytes of Arrow string columns."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.conf import Table

NULL_ID = -(2**63)
SLICE_BYTES = 4 << 20
_U64 = np.uint64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_scratch: list[list[Table]] = []


def materialise(df: DataFrame, name: str = "step") -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage, survives lost executors,
    and fixes what a non-deterministic step (row order inside a partition) decided."""
    table = Table(df, name)
    if _scratch:
        _scratch[-1].append(table)
    out = table.df
    out._written = table
    return out


def discard(df: DataFrame) -> None:
    """Delete a materialised frame that nothing will read again."""
    df._written.delete()


@contextmanager
def scratch() -> Iterator[None]:
    """Frames that are materialised inside are deleted at the end; what must outlive them is written before."""
    _scratch.append([])
    try:
        yield
    finally:
        for table in _scratch.pop():
            table.delete()


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df doesn't have (names are compared without case, as Spark does)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def known_id(column: str = "doc_id") -> Column:
    """A null id stands as the smallest long inside an operator."""
    return F.coalesce(F.col(column).cast("long"), F.lit(NULL_ID))


def original_id(column: str = "doc_id") -> Column:
    return F.when(F.col(column) != NULL_ID, F.col(column))


_remembered: dict[str, Callable[[], object]] = {}


def remembers(name: str, forget: Callable[[], object]) -> None:
    """Tells that a worker keeps something from task to task under this name, and how it is dropped."""
    _remembered[name] = forget


def forget_others(name: str | None = None) -> None:
    """Drop what this worker remembers, but for that name."""
    for other, forget in _remembered.items():
        if other != name:
            forget()


def tidy(run, remembered: str | None = None):
    """A function of mapInArrow that gives back at its end what freed arrays have left to the allocators: workers are reused
    by later tasks, which would keep it beside their own. At its start it drops what tasks of other operators remember."""

    def wrapped(batches):
        forget_others(remembered)
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
                trim(0)

    return wrapped


# ---------------------------------------------------------------- bytes of Arrow columns


def utf8(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets of rows and the end) of a string column; a null row is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    _, offsets, data = column.buffers()
    if offsets is None or len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(len(column) + 1, np.int64)
    at = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    body = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return body[at[0] : at[-1]], at - at[0]


def row_slices(offsets: np.ndarray, limit: int = SLICE_BYTES):
    """Row ranges of at most limit bytes, of one row at least."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + limit, side="right")) - 1)
        yield i, j
        i = j


def spans(is_word: np.ndarray, body: np.ndarray, offsets: np.ndarray):
    """Starts and ends of the words of all rows, and the first word of each row (and the end)."""
    inside = is_word[body]
    n = len(body)
    if not n:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    begins, stops = inside.copy(), inside.copy()
    begins[1:] &= ~inside[:-1]
    stops[:-1] &= ~inside[1:]
    cut = offsets[(offsets > 0) & (offsets < n)]
    begins[cut] = inside[cut]
    stops[cut - 1] = inside[cut - 1]
    start, end = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    return start, end, np.searchsorted(start, offsets)


def table_of(*keep: tuple[int, int]) -> np.ndarray:
    """A byte table that is true on the given inclusive ranges."""
    out = np.zeros(256, bool)
    for a, b in keep:
        out[a : b + 1] = True
    return out


SPACE_WORD = ~table_of((0x20, 0x20), (0x09, 0x0D))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 0x20
ALNUM_WORD = table_of((0x30, 0x39), (0x61, 0x7A), (0x80, 0xFF))  # after LOWER


# ---------------------------------------------------------------- hashing

#: Of the first n bytes of a little-endian word of eight.
_MASK = np.array([(1 << 8 * n) - 1 for n in range(9)], _U64)
_ODD = _U64(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """The public splitmix64 finaliser."""
    x = x ^ (x >> _U64(30))
    x *= _U64(0xBF58476D1CE4E5B9)
    x ^= x >> _U64(27)
    x *= _U64(0x94D049BB133111EB)
    x ^= x >> _U64(31)
    return x


def word_hashes(body: np.ndarray, start: np.ndarray, end: np.ndarray, chunk: int = 1 << 16) -> np.ndarray:
    """A 64-bit hash of each word, chunk words at a time: of its length and first eight bytes, and of a sum over
    further eights, each mixed with its place (no sum of powers, which texts can be built to collide under)."""
    out = np.empty(len(start), _U64)
    if not len(start):
        return out
    padded = np.append(body, np.zeros(8, np.uint8))
    eight = np.ndarray((len(body) + 1,), "<u8", padded, strides=(1,))  # the eight bytes from every place
    for a in range(0, len(start), chunk):
        s, e = start[a : a + chunk], end[a : a + chunk]
        size = e - s
        h = mix((eight[s] & _MASK[np.minimum(size, 8)]) + size.astype(_U64) * _ODD)
        if len(long := np.flatnonzero(size > 8)):
            more = (size[long] - 1) // 8
            place = ranges(np.ones(len(long), np.int64), more)
            at = np.repeat(s[long], more) + 8 * place
            part = mix((eight[at] & _MASK[np.minimum(np.repeat(e[long], more) - at, 8)]) ^ mix(place.astype(_U64) * _ODD))
            h[long] = mix(h[long] + mix(np.add.reduceat(part, np.cumsum(more) - more)))
        out[a : a + chunk] = h
    return out


def window_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """A hash of each run of size words of the flat array (across rows too: callers mask those). Runs of 1, 2, 4, ...
    words are mixed from their halves, and a run of size from those of its binary digits."""
    n = len(words) - size + 1
    if n <= 0:
        return np.zeros(0, _U64)
    out, at, span, run = None, 0, 1, words
    while True:
        if size & span:
            part = run[at : at + n]
            out = part if out is None else mix(out * _ODD + part)
            at += span
        if span * 2 > size:
            return out
        run, span = mix(run[:-span] * _ODD + run[span:]), span * 2


def ranges(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """All positions start[i] .. start[i]+length[i]-1, one range after the other."""
    total = int(length.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(length)
    return np.arange(total) + np.repeat(start - (ends - length), length)


def covered(n: int, start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Which of n places lie in any of the ranges."""
    step = np.zeros(n + 1, np.int64)
    np.add.at(step, start, 1)
    np.add.at(step, start + length, -1)
    return np.cumsum(step[:n]) > 0
