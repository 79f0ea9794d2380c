"""Operator 1: language identification of mixed text.

Each word gets a log-likelihood per language from hashed character trigrams (with word edges) and from
whole known words; the script of its letters narrows the languages that may score at all. Viterbi with a penalty
per switch then labels every word of a document, which gives spans; the document's language is
the one with most labelled letters, and its score the share of letters that it has.

Learning counts trigrams and words of a bounded sample: per language the ``sample`` texts of the least
hash, so it does not depend on partitioning. Scale: one pass, no shuffle of the text; only hashes below a bound drawn
from the counts are ranked, about four times the sample whatever the table's size; the model has a fixed size
(2**16 trigram buckets and 2**16 word buckets per language).

A word is a run of letters and combining marks of one script that holds a letter; marks alone are no word.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vertexalg.llm import common as C

SAMPLE, SAMPLE_CHARS, SWITCH, BUCKETS = 400, 20_000, 6.0, 1 << 16
_EDGE = 0x20
#: First code points of blocks and the script that begins there (fixed values of Unicode).
_SCRIPTS = ((0x0000, "Latin"), (0x0370, "Greek"), (0x0400, "Cyrillic"), (0x0530, "Armenian"), (0x0590, "Hebrew"), (0x0600, "Arabic"), (0x0700, "Other"), (0x0900, "Devanagari"), (0x0980, "Indic"), (0x0E00, "Thai"), (0x0E80, "Other"), (0x10A0, "Georgian"), (0x1100, "Hangul"), (0x1200, "Other"), (0x1E00, "Latin"), (0x1F00, "Greek"), (0x2000, "Other"), (0x2C60, "Latin"), (0x2C80, "Other"), (0x3040, "Kana"), (0x3100, "Han"), (0xA640, "Other"), (0xA720, "Latin"), (0xA800, "Other"), (0xAC00, "Hangul"), (0xD7B0, "Other"), (0xF900, "Han"), (0xFB00, "Latin"), (0xFB07, "Other"), (0xFF21, "Latin"), (0xFF5B, "Other"), (0x20000, "Han"))
_NAMES = tuple(sorted({s for _, s in _SCRIPTS}))


@lru_cache(maxsize=1)
def _tables() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """By code point: is it a letter; is it a letter or a mark; its lower case; its script's number."""
    n = 0x110000
    kind = "".join(unicodedata.category(chr(i))[0] for i in range(n))
    letter, mark = (np.frombuffer(kind.encode(), np.uint8) == ord(k) for k in "LM")
    lower = np.arange(n, dtype=np.uint32)
    for i in np.flatnonzero(letter).tolist():
        if len(c := chr(i).lower()) == 1:
            lower[i] = ord(c)
    edge = np.array([a for a, _ in _SCRIPTS])
    script = np.array([_NAMES.index(s) for _, s in _SCRIPTS], np.int8)[np.searchsorted(edge, np.arange(n), side="right") - 1]
    return letter, letter | mark, lower, script


def _words(texts: pa.Array, i: int, j: int):
    """Letters words of rows i..j: code points of all rows, starts, ends, first word per row, script per word."""
    letter, inner, lower, script = _tables()
    body, offsets = C.utf8(texts.slice(i, j - i))
    points = np.frombuffer(body.tobytes().decode("utf-8", "replace").encode("utf-32-le", "replace"), np.uint32)
    # rows by code points: every byte but the continuations begins one
    upto = np.append(0, np.cumsum((body & 0xC0) != 0x80))
    off = upto[offsets]
    inside = inner[points]
    n = len(points)
    if not n:
        none = np.zeros(0, np.int64)
        return points, none, none, np.zeros(j - i + 1, np.int64), none
    begins, stops = inside.copy(), inside.copy()
    # a change of script begins a word too; marks go with the letter before them
    base = np.maximum.accumulate(np.where(letter[points] | ~inside, np.arange(n), 0))
    kind = script[points[base]]
    turn = kind[1:] != kind[:-1]
    begins[1:] &= ~inside[:-1] | turn
    stops[:-1] &= ~inside[1:] | turn
    cut = off[(off > 0) & (off < n)]
    begins[cut] = inside[cut]
    stops[cut - 1] = inside[cut - 1]
    start, end = np.flatnonzero(begins), np.flatnonzero(stops) + 1
    letters = np.append(0, np.cumsum(letter[points]))
    real = letters[end] > letters[start]
    start, end = start[real], end[real]
    return lower[points], start, end, np.searchsorted(start, off), kind[start]


def _features(points: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of the trigram around each letter, word after word (its neighbours beyond the word are edges), and of each word."""
    size = end - start
    at = C.ranges(start, size)
    here = points[at].astype(np.uint64)
    left, right = np.full(len(at), _EDGE, np.uint64), np.full(len(at), _EDGE, np.uint64)
    left[1:], right[:-1] = here[:-1], here[1:]
    stop = np.cumsum(size)
    left[stop - size] = _EDGE
    right[stop - 1] = _EDGE
    x = (left << np.uint64(42)) ^ (here << np.uint64(21)) ^ right
    tri = (C.mix(x) & np.uint64(BUCKETS - 1)).astype(np.int64)
    whole = np.add.reduceat(C.mix(here + (np.arange(len(at)) - np.repeat(stop - size, size) + 1).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)), stop - size) if len(at) else np.zeros(0, np.uint64)
    return tri, (C.mix(whole) & np.uint64(BUCKETS - 1)).astype(np.int64)


class Model:
    """Log-probabilities of trigrams and words per language, and which scripts each language uses."""

    def __init__(self, languages: list[str], trigram: np.ndarray, word: np.ndarray, scripts: np.ndarray) -> None:
        self.languages, self.trigram, self.word, self.scripts = languages, trigram, word, scripts

    @classmethod
    def learn(cls, rows: list[tuple[str, str]]) -> Model:
        languages = sorted({lang for lang, _ in rows})
        tri, word = np.full((BUCKETS, len(languages)), 0.5), np.full((BUCKETS, len(languages)), 0.5)
        seen = np.zeros((len(_NAMES), len(languages)))
        for k, lang in enumerate(languages):
            texts = pa.array([t for x, t in rows if x == lang])
            points, start, end, _, kind = _words(texts, 0, len(texts))
            a, b = _features(points, start, end)
            tri[:, k] += np.bincount(a, minlength=BUCKETS)
            word[:, k] += np.bincount(b, minlength=BUCKETS)
            seen[:, k] += np.bincount(kind, end - start, len(_NAMES))
        log = lambda x: np.log(x / x.sum(axis=0)).astype(np.float32)
        share = seen / np.maximum(seen.sum(axis=0), 1)
        return cls(languages, log(tri), log(word), share >= 0.01)

    def label(self, points, start, end, first, kind, switch: float) -> np.ndarray:
        """Viterbi's language of each word (rows step together, the longest first)."""
        n_lang, count = len(self.languages), np.diff(first)
        tri, word = _features(points, start, end)
        size = end - start
        score = np.empty((len(start), n_lang), np.float32)
        for k in range(n_lang):
            score[:, k] = (np.add.reduceat(self.trigram[tri, k], np.cumsum(size) - size) if len(size) else 0) + self.word[word, k]
        # languages that don't use the word's script are out, unless no language uses it
        allowed = self.scripts[kind]
        score[~allowed & allowed.any(axis=1, keepdims=True)] -= 1e4
        score[~allowed.any(axis=1)] = 0
        score -= score.max(axis=1, keepdims=True)
        order = np.argsort(-count, kind="stable")
        begin, longest = first[:-1][order], count[order]
        alive = np.searchsorted(-longest, -np.arange(1, (longest[0] if len(longest) else 0) + 1), side="right")
        back = np.empty((len(start), n_lang), np.int16)
        now = np.zeros((len(order), n_lang), np.float32)
        me = np.arange(n_lang)
        for t, m in enumerate(alive.tolist()):
            at = begin[:m] + t
            best = now[:m].argmax(axis=1)
            jump = now[np.arange(m), best][:, None] - (switch if t else 0)
            stay = now[:m] >= jump
            back[at] = np.where(stay, me, best[:, None])
            now[:m] = np.where(stay, now[:m], jump) + score[at]
        out = np.empty(len(start), np.int16)
        state = now.argmax(axis=1)
        for t in range(len(alive) - 1, -1, -1):
            m = alive[t]
            at = begin[:m] + t
            out[at] = state[:m]
            state[:m] = back[at, state[:m]]
        return out


def learn(docs: DataFrame, sample: int = SAMPLE) -> Model | None:
    """From rows (text, lang) with both; None if there are none. At most sample texts of SAMPLE_CHARS characters per language,
    those of the least hashes. Only hashes below a bound are ranked: it starts at four times the share of rows that the
    sample is, and widens for languages that have too few different texts under it."""
    rows = docs.where("lang is not null and text is not null and length(text) > 0").select("lang", "text", F.xxhash64("text").alias("h"))
    counts = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    if not counts:
        return None
    share = {lang: min(1.0, 4 * sample / n) for lang, n in counts.items()}
    last: dict[str, int] = {}
    while open_ := {lang: x for lang, x in share.items() if lang not in last}:
        low = F.lit(False)
        for lang, x in open_.items():
            bound = F.lit(True) if x >= 1 else F.col("h") < int(2**64 * x) - 2**63
            low |= (F.col("lang") == lang) & bound
        order = W.partitionBy("lang").orderBy("h")
        ranked = rows.where(low).select("lang", "h").distinct().withColumn("r", F.row_number().over(order)).where(F.col("r") <= sample)
        for r in ranked.groupBy("lang").agg(F.max("h").alias("h"), F.count("*").alias("n")).collect():
            if r["n"] == sample or share[r["lang"]] >= 1:
                last[r["lang"]] = r["h"]
        share = {lang: x if lang in last else min(1.0, 16 * x) for lang, x in share.items()}
    wanted = F.lit(False)
    for lang, h in last.items():
        wanted |= (F.col("lang") == lang) & (F.col("h") <= h)
    # what is learned, not what is predicted, is bounded
    picked = rows.where(wanted).groupBy("lang", "h").agg(F.min(F.substring("text", 1, SAMPLE_CHARS)).alias("t"))
    return Model.learn(sorted((r["lang"], r["t"]) for r in picked.collect()))


def _predict(model: Model | None, switch: float, with_spans: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text")
            _, offsets = C.utf8(texts)
            for i, j in C.row_slices(offsets, 2 << 20):
                points, start, end, first, kind = _words(texts, i, j)
                count, n = np.diff(first), j - i
                if model is None:
                    names, score, labels = ["und"] * n, np.zeros(n), None
                else:
                    labels = model.label(points, start, end, first, kind, switch)
                    row = np.repeat(np.arange(n), count)
                    k = len(model.languages)
                    letters = np.bincount(row * k + labels, end - start, n * k).reshape(n, k)
                    best = letters.argmax(axis=1)
                    score = letters.max(axis=1) / np.maximum(letters.sum(axis=1), 1)
                    names = [model.languages[b] if c else "und" for b, c in zip(best.tolist(), count.tolist(), strict=True)]
                columns = [batch.column("doc_id").slice(i, n), batch.column("held_out").slice(i, n), pa.array(names, pa.string()), pa.array(score, pa.float64())]
                columns_names = ["doc_id", "held_out", "lang_pred", "score"]
                if with_spans:
                    spans = []
                    _, off = C.utf8(texts.slice(i, n))
                    body, _ = C.utf8(texts.slice(i, n))
                    base = np.append(0, np.cumsum((body & 0xC0) != 0x80))[off]
                    for r in range(n):
                        mine: list[dict] = []
                        for w in range(first[r], first[r + 1]) if labels is not None else ():
                            name, a, b = model.languages[labels[w]], int(start[w] - base[r]), int(end[w] - base[r])
                            if mine and mine[-1]["lang"] == name:
                                mine[-1]["end"] = b
                            else:
                                mine.append({"lang": name, "start": a, "end": b})
                        spans.append(mine)
                    columns.append(pa.array(spans, pa.list_(pa.struct([("lang", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))))
                    columns_names.append("spans")
                yield pa.RecordBatch.from_arrays(columns, names=columns_names)

    return C.tidy(run)


def held_out(column: str, modulus: int, rest: int) -> Column:
    return F.coalesce(F.crc32(F.col(column).cast("string")) % modulus == rest, F.lit(False))


def identify(docs: DataFrame, model: Model | None, switch: float = SWITCH, with_spans: bool = False, held: Column | None = None) -> DataFrame:
    """(doc_id, held_out, lang_pred, score[, spans]) per row of docs (doc_id, text); other columns are left out.

    held: what held_out shall say (false if not given). A null or empty text, or one without letters (marks alone are none), is
    'und' with score 0; so is everything without a model (no labelled rows). Of languages with equal numbers of
    letters the first by name is told. A null id stays null, rows that repeat an id are labelled each for itself, an
    empty table gives no row. spans: lang, start and end in code points, of runs of words of one language."""
    schema = "doc_id long, held_out boolean, lang_pred string, score double" + ", spans array<struct<lang: string, start: int, end: int>>" * with_spans
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), (F.lit(False) if held is None else held).alias("held_out"))
    return texts.mapInArrow(_predict(model, switch, with_spans), schema)


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held = held_out("doc_id", 4, 2)
    return identify(docs, learn(docs.where(~held).select("text", "lang")), held=held)
