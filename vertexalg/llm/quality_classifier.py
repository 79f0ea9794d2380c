"""Operator 10: text quality by a byte-level convolutional network in numpy.

A symbol is a byte, marked if its word also stands among the ``LOOK_BACK`` words before it. Symbols
are embedded; ``FILTERS`` learned filters of ``WIDTH`` bytes run at every ``STRIDE`` bytes; each filter is max-pooled
over chunks of ``2 * HALF`` bytes that overlap by half and together cover the document; the document's
vector is the mean and the maximum of its chunks' vectors, and one logistic layer gives the probability.
For scoring, embedding and filters are multiplied out into one table per byte of the filter.

The mark is the one input that is no plain byte: filters of a few bytes cannot see that a word comes again.

Learning takes a bounded sample: the ``sample`` labels with the least hash of their id, of each text a window
of ``CROP`` characters at a hashed place. Scoring reads whole texts. Scale: one pass, no shuffle of the
text; the model has a fixed size and goes with the task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C
from vertexalg.llm.language_id import held_out

SAMPLE, CROP = 2400, 3000
FILTERS, WIDTH, STRIDE, HALF, DEPTH, LOOK_BACK = 16, 8, 4, 128, 8, 4
EPOCHS, STEPS, BATCH, RATE, DECAY = 8, 400, 64, 0.01, 1e-4
_SYMBOLS = 512


def symbols(body: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(symbols of all rows, first half-chunk of each row and the end). Every row is filled up with zeros
    to whole half-chunks, with room for a filter's width; an empty row is one half-chunk."""
    start, end, first = C.spans(C.SPACE_WORD, body, offsets)
    word = C.word_hashes(body, start, end)
    row_first = np.repeat(first[:-1], np.diff(first))
    again = np.zeros(len(word), bool)
    for lag in range(1, LOOK_BACK + 1):
        again[lag:] |= (word[lag:] == word[:-lag]) & (np.arange(lag, len(word)) - lag >= row_first[lag:])
    value = body.astype(np.int16)
    value[C.ranges(start[again], (end - start)[again])] += 256
    size = np.diff(offsets)
    halves = np.maximum(1, -(-(size + WIDTH) // HALF))
    edge = np.append(0, np.cumsum(halves))
    out = np.zeros(int(edge[-1]) * HALF, np.int16)
    out[C.ranges(edge[:-1] * HALF, size)] = value
    return out, edge


class Network:
    def __init__(self, seed: int = 7) -> None:
        rng = np.random.default_rng(seed)
        n = lambda *shape, scale: rng.normal(0, scale, shape).astype(np.float32)
        self.p = {"embed": n(_SYMBOLS, DEPTH, scale=0.5), "filter": n(WIDTH, DEPTH, FILTERS, scale=0.25), "bias": np.zeros(FILTERS, np.float32), "dense": n(2 * FILTERS, scale=0.1), "shift": np.zeros(1, np.float32)}

    def tables(self) -> np.ndarray:
        return np.einsum("sd,kdf->ksf", self.p["embed"], self.p["filter"])

    @staticmethod
    def convolve(table: np.ndarray, x: np.ndarray) -> np.ndarray:
        """Filter outputs at every STRIDE symbols; the last places of a row reach over (see within)."""
        n = len(x) // STRIDE
        tail = np.append(x, np.zeros(WIDTH, x.dtype))
        out = table[0][tail[: n * STRIDE : STRIDE]]
        for k in range(1, WIDTH):
            out += table[k][tail[k : k + n * STRIDE : STRIDE]]
        return out

    @staticmethod
    def within(out: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Outputs by half-chunk, where places that reach over the end of a row's last half take what the one before
        them gives: that one sees only the zeros that the row ends in, as they would."""
        over = (WIDTH - 1) // STRIDE
        out[last, -over:] = out[last, -over - 1][:, None]
        return out

    def vectors(self, pooled: np.ndarray, edge: np.ndarray):
        """Chunk vectors (half h with the next of its row) and the document vectors."""
        last = edge[1:] - 1
        partner = np.arange(1, len(pooled) + 1)
        partner[last] = last
        chunk = np.maximum(np.maximum(pooled, pooled[partner]) + self.p["bias"], 0)
        mean = np.add.reduceat(chunk, edge[:-1]) / np.diff(edge)[:, None]
        return partner, chunk, np.concatenate([mean, np.maximum.reduceat(chunk, edge[:-1])], axis=1)

    def probability(self, document: np.ndarray) -> np.ndarray:
        z = document @ self.p["dense"] + self.p["shift"]
        return 1 / (1 + np.exp(-np.clip(z.astype(np.float64), -30, 30)))

    def score(self, table: np.ndarray, x: np.ndarray, edge: np.ndarray) -> np.ndarray:
        pooled = np.empty((edge[-1], FILTERS), np.float32)
        step = 2048  # half-chunks at a time
        for a in range(0, int(edge[-1]), step):
            b = min(a + step, int(edge[-1]))
            # a filter sees the symbols after its half-chunk
            seen = x[a * HALF : b * HALF + WIDTH]
            seen = seen if len(seen) == (b - a) * HALF + WIDTH else np.append(seen, np.zeros(WIDTH, x.dtype))
            out = self.convolve(table, seen)[: (b - a) * HALF // STRIDE].reshape(b - a, HALF // STRIDE, FILTERS)
            last = edge[1:] - 1 - a
            pooled[a:b] = self.within(out, last[(last >= 0) & (last < b - a)]).max(axis=1)
        return self.probability(self.vectors(pooled, edge)[2])

    def gradient(self, x: np.ndarray, edge: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        halves = int(edge[-1])
        out = self.within(self.convolve(self.tables(), x).reshape(halves, HALF // STRIDE, FILTERS), edge[1:] - 1)
        where = out.argmax(axis=1)
        pooled = np.take_along_axis(out, where[:, None], axis=1)[:, 0]
        partner, chunk, document = self.vectors(pooled, edge)
        dz = ((self.probability(document) - y) / len(y)).astype(np.float32)
        g = {"dense": document.T @ dz, "shift": dz.sum(keepdims=True)}
        row = np.repeat(np.arange(len(y)), np.diff(edge))
        d_doc = dz[:, None] * self.p["dense"]
        top = document[:, FILTERS:][row] == chunk
        ties = np.add.reduceat(top.astype(np.float32), edge[:-1])
        d_chunk = d_doc[:, :FILTERS][row] / np.diff(edge)[row][:, None] + np.where(top, (d_doc[:, FILTERS:] / ties)[row], 0)
        d_chunk *= chunk > 0
        g["bias"] = d_chunk.sum(axis=0)
        own = pooled >= pooled[partner]
        d_pool = np.where(own, d_chunk, 0)
        np.add.at(d_pool, partner, np.where(own, 0, d_chunk))
        place = np.arange(halves)[:, None] * HALF + where * STRIDE
        tail = np.append(x, np.zeros(WIDTH, x.dtype))
        column = np.broadcast_to(np.arange(FILTERS), place.shape)
        g["embed"], g["filter"] = np.zeros_like(self.p["embed"]), np.empty_like(self.p["filter"])
        for k in range(WIDTH):
            flat = tail[place + k].astype(np.int64) * FILTERS + column
            d_table = np.bincount(flat.ravel(), d_pool.ravel(), _SYMBOLS * FILTERS).reshape(_SYMBOLS, FILTERS).astype(np.float32)
            g["embed"] += d_table @ self.p["filter"][k].T
            g["filter"][k] = self.p["embed"].T @ d_table
        return g

    @classmethod
    def learn(cls, texts: list[str], labels: list[int], epochs: int = EPOCHS, seed: int = 7) -> Network:
        net, rng = cls(seed), np.random.default_rng(seed)
        mean = {k: np.zeros_like(v) for k, v in net.p.items()}
        square = {k: np.zeros_like(v) for k, v in net.p.items()}
        raw, y, t = [x.encode() for x in texts], np.array(labels, np.float64), 0
        each = -(-len(raw) // BATCH)
        epochs = max(epochs, -(-STEPS // each))  # small samples are seen more often
        total = epochs * each
        for _ in range(epochs):
            order = rng.permutation(len(raw))
            for at in range(0, len(order), BATCH):
                pick, t = order[at : at + BATCH], t + 1
                body = np.frombuffer(b"".join(raw[i] for i in pick), np.uint8)
                x, edge = symbols(body, np.append(0, np.cumsum([len(raw[i]) for i in pick])))
                rate = RATE * (1 - t / (total + 1))
                for k, g in net.gradient(x, edge, y[pick]).items():
                    g = g + DECAY * net.p[k]
                    mean[k] = 0.9 * mean[k] + 0.1 * g
                    square[k] = 0.99 * square[k] + 0.01 * g * g
                    net.p[k] -= (rate * (mean[k] / (1 - 0.9**t)) / (np.sqrt(square[k] / (1 - 0.99**t)) + 1e-8)).astype(np.float32)
        return net


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Network | None:
    """From docs (doc_id, text) and labels (doc_id, quality) that learning may see; None if none is left.
    The sample is drawn from the labels, so its size bounds the broadcast and what comes to the driver."""
    marks = labels.select(F.col("doc_id").cast("long").alias("label_id"), F.col("quality").cast("int").alias("q")).where(~held_out("label_id", 3, 1) & F.col("quality").isNotNull() & F.col("doc_id").isNotNull())
    marks = marks.distinct().orderBy(F.xxhash64("label_id"), "q").limit(sample)
    size = F.length("text")
    place = F.pmod(F.xxhash64("text"), F.greatest(F.lit(1).cast("long"), size - CROP + 1))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    seen = texts.join(F.broadcast(marks), texts.doc_id == marks.label_id)
    # one text of each label, however many rows repeat its id
    crop = F.substr("text", (place + 1).cast("int"), F.lit(CROP))
    got = seen.groupBy("label_id", "q").agg(F.min(F.struct(F.xxhash64("text").alias("h"), crop.alias("t"))).alias("m")).select("m.t", "q").collect()
    rows = sorted((r["t"], int(r["q"] > 0)) for r in got)
    return Network.learn([t for t, _ in rows], [q for _, q in rows]) if rows else None


def _score(net: Network | None):
    table = net.tables().astype(np.float32) if net else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, 2 << 20):
                if net is None:
                    p = np.full(j - i, 0.5)
                else:
                    p = net.score(table, *symbols(body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), batch.column("held_out").slice(i, j - i), pa.array(p), pa.array((p >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return C.tidy(run)


def classify(docs: DataFrame, net: Network | None, held: Column | None = None) -> DataFrame:
    """(doc_id, held_out, score, predicted) per row of docs (doc_id, text); other columns are left out. held: what held_out
    shall say (false if not given). A null text is scored as an empty one; a null id stays null, rows that repeat an id are
    scored each for itself, an empty table gives no row; without a model (no labelled rows) every score is 0.5."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), (F.lit(False) if held is None else held).alias("held_out"))
    return texts.mapInArrow(_score(net), "doc_id long, held_out boolean, score double, predicted int")


def keep_good(docs: DataFrame, net: Network | None, threshold: float = 0.5) -> DataFrame:
    """The rows of docs (text, any other columns) that score threshold at least; all of them without a model."""
    table = net.tables().astype(np.float32) if net else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, 2 << 20):
                p = net.score(table, *symbols(body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]))
                yield batch.slice(i, j - i).filter(pa.array(p >= threshold))

    return docs.mapInArrow(C.tidy(run), docs.schema) if net else docs


def op10_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    net = learn(docs, C.table(spark, sf_dir, "labels"))
    return classify(docs, net, held_out("doc_id", 3, 1))
