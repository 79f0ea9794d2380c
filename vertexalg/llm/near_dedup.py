"""Operator 7: near-duplicates by DartMinHash signatures, banded joins and an exact check.

A dart is a point of the (weight, rank) plane of one element. The plane is cut into cells of measure one
whose darts (a Poisson(1) number) come from a hash of element and cell, so two documents see the same
darts wherever both have the weight. A document looks at ranks up to t/total weight, which gives about t
darts; each dart names a coordinate of the signature, and the earliest dart of a coordinate is its value.
Equal coordinates have the probability of the weighted Jaccard similarity. Cost: elements + t.

Candidates share one of ``bands`` bands of ``rows`` coordinates: at similarity 0.8 a pair is missed with
probability (1 - 0.8**6)**32 < 1e-4. All candidates are then judged on their whole shingle sets.

Linking: documents of one shingle set are one node, named by the least written row number among them and read from that
row's text, as ids can repeat or be null. Every bucket is first a star: all its nodes are compared with
the most central one (that meets most others in its buckets), which costs one comparison per copy and not
one per pair. Buckets that are not one component then have the rest compared: up to ``small`` nodes by pairs,
larger ones inside tasks: buckets that overlap form a family, its nodes outside the largest component
meet all of the family in blocks of about ``block`` shingles, and only links leave the task. So every two nodes that share a bucket
are compared or tied otherwise: no link is lost.

Scale: signatures never leave the task, band keys are 8 bytes, the text moves to its candidates and with them to their pivots, pivots with many partners are salted, and components are stars of edges.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C
from vertexalg.llm.components import components

SHINGLE, SIMILARITY = 5, 0.8
BANDS, ROWS, SMALL, SALT_ROWS, BLOCK = 32, 6, 8, 2000, 500_000
_CELLS = 200_000  # cells, or shingles that are compared, at a time
_ENTRY = [("h", "<u8"), ("n", "<u4")]  # of a compared set: hash and count
_POISSON = np.cumsum(np.exp(-1) / np.array([1.0, *np.cumprod(np.arange(1.0, 20.0))]))
_U = np.uint64


def shingles(body: np.ndarray, offsets: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(hash, count, first of each row and the end): the distinct shingles of all rows, ascending in a row.
    Words are parted by ASCII white space, A-Z lowered; a row of fewer words than size, but not none, is one shingle."""
    low = C.LOWER[body]
    start, end, first = C.spans(C.SPACE_WORD, low, offsets)
    words = C.word_hashes(low, start, end)
    count = np.diff(first)
    number = np.where(count >= size, count - size + 1, np.minimum(count, 1))
    row = np.repeat(np.arange(len(count)), number)
    place = C.ranges(first[:-1], number)
    short = np.repeat(np.minimum(count, size), number)
    value = np.zeros(len(place), np.uint64)
    for n in np.unique(short).tolist():
        at = short == n
        value[at] = C.mix(C.window_hashes(words, n)[place[at]] + _U(n))
    order = np.lexsort((value, row))
    value, row = value[order], row[order]
    new = np.ones(len(value), bool)
    new[1:] = (value[1:] != value[:-1]) | (row[1:] != row[:-1])
    at = np.flatnonzero(new)
    return value[at], np.diff(np.append(at, len(value))), np.searchsorted(row[at], np.arange(len(count) + 1))


def _unit(x: np.ndarray) -> np.ndarray:
    return (x >> _U(11)) * 2.0**-53


def _throw(element, weight, row, reach, n_rows: int, k: int):
    """Darts of each (element, weight) with rank below reach: earliest rank and dart by (row, coordinate)."""
    best = np.full(n_rows * k, np.inf)
    value = np.zeros(n_rows * k, np.uint64)
    top = np.maximum(0, np.ceil(np.log2(weight))).astype(np.int64)
    ranks, darts, slots = [], [], []
    for band in range(int(top.max(initial=0)) + 1):
        use = np.flatnonzero(top >= band)
        low, width = (0.0, 1.0) if band == 0 else (2.0 ** (band - 1), 2.0 ** (band - 1))
        number = np.ceil(reach[use] * width).astype(np.int64)
        strip = C.ranges(np.zeros(len(use), np.int64), number)
        who = np.repeat(use, number)
        cell = C.mix(element[who] + _U(band * 0xA24BAED4963EE407 % 2**64) + (strip + 1).astype(np.uint64) * _U(0x9FB21C651E98DF25))
        many = np.searchsorted(_POISSON, _unit(cell), side="right")
        dart = C.mix(np.repeat(cell, many) + (C.ranges(np.zeros(len(many), np.int64), many) + 1).astype(np.uint64) * _U(0xC2B2AE3D27D4EB4F))
        who = np.repeat(who, many)
        rank = (np.repeat(strip, many) + _unit(dart)) / width
        keep = rank < reach[who]
        # a cell that the weight covers only in part
        if (weight[who] < low + width).any():
            keep &= low + width * _unit(C.mix(dart + _U(0x165667B19E3779F9))) < weight[who]
        who, dart, rank = who[keep], dart[keep], rank[keep]
        slots.append(row[who] * k + (C.mix(dart + _U(0x27D4EB2F165667C5)) % _U(k)).astype(np.int64))
        ranks.append(rank)
        darts.append(dart)
    slot, rank, dart = np.concatenate(slots), np.concatenate(ranks), np.concatenate(darts)
    np.minimum.at(best, slot, rank)
    first = rank == best[slot]
    value[slot[first]] = dart[first]
    return best.reshape(n_rows, k), value.reshape(n_rows, k)


def dart_signatures(element: np.ndarray, weight: np.ndarray, first: np.ndarray, k: int) -> np.ndarray:
    """Signatures (rows x k) of rows of weighted elements; weights are positive; a row without elements is all 0."""
    n = len(first) - 1
    out = np.zeros((n, k), np.uint64)
    row = np.repeat(np.arange(n), np.diff(first))
    total = np.bincount(row, weight, n)
    darts = k * (np.log(k) + 2)
    todo = np.flatnonzero(total > 0)
    while len(todo):
        left = []
        cost = np.cumsum(np.maximum(np.diff(first)[todo], darts))
        a = 0
        while a < len(todo):
            b = max(a + 1, int(np.searchsorted(cost, (cost[a - 1] if a else 0) + _CELLS, side="right")))
            part = todo[a:b]
            number = np.diff(first)[part]
            at = C.ranges(first[part], number)
            best, value = _throw(element[at], weight[at], np.repeat(np.arange(len(part)), number), np.repeat(darts / total[part], number), len(part), k)
            full = np.isfinite(best).all(axis=1)
            out[part[full]] = value[full]
            left.append(part[~full])
            a = b
        todo, darts = np.concatenate(left), darts * 2  # more ranks only add later darts
    return out


_SKETCH = "row long, doc_id long, set_a long, set_b long, n int, bands array<long>"


def _sketch(size: int, bands: int, rows: int, weighted: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, 1 << 20):
                value, count, first = shingles(body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], size)
                n = np.diff(first)
                weight = count.astype(float) if weighted else np.ones(len(value))
                signature = dart_signatures(value, weight, first, bands * rows)
                keys = C.mix(np.repeat(np.arange(1, bands + 1, dtype=np.uint64)[None], j - i, 0) * _U(0x9E3779B97F4A7C15))
                for r in range(rows):
                    keys = C.mix(keys ^ signature[:, r::rows])
                # the set by two sums of hashes
                marked = C.mix(value + (count.astype(np.uint64) if weighted else _U(1)))
                sums = [np.append(_U(0), np.cumsum(x, dtype=np.uint64)) for x in (marked, C.mix(marked + _U(7)))]
                a, b = (s[first[1:]] - s[first[:-1]] for s in sums)
                at = np.arange(0, (j - i + 1) * bands, bands, dtype=np.int32)
                lists = pa.ListArray.from_arrays(pa.array(at), pa.array(keys.reshape(-1).view(np.int64)))
                columns = [*(batch.column(k).slice(i, j - i) for k in ("row", "doc_id")), pa.array(a.view(np.int64)), pa.array(b.view(np.int64)), pa.array(n, pa.int32()), lists]
                yield pa.RecordBatch.from_arrays(columns, names=["row", "doc_id", "set_a", "set_b", "n", "bands"])

    return C.tidy(run)


def _read_sets(size: int):
    """(doc, text) to the shingles of the text, 12 bytes for each: hash and count."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            body, offsets = C.utf8(batch.column("text"))
            for i, j in C.row_slices(offsets, 1 << 20):
                value, count, first = shingles(body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], size)
                raw = np.empty(len(value), _ENTRY)
                raw["h"], raw["n"] = value, count
                edge = pa.py_buffer((first * raw.itemsize).astype(np.int32))
                sets = pa.Array.from_buffers(pa.binary(), j - i, [None, edge, pa.py_buffer(raw.tobytes())])
                yield pa.RecordBatch.from_arrays([batch.column("doc").slice(i, j - i), sets], names=["doc", "shingles"])

    return C.tidy(run)


def _judge(size: int, similarity: float, weighted: bool):
    """Rows (pivot, salt, doc, text) sorted by group, each group's pivot first, to the pairs that are similar enough: every text
    is read into its shingles where it meets its pivot's, and only a pivot's are kept."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, own = None, None
        for batch in batches:
            groups = list(zip(*(batch.column(k).to_pylist() for k in ("pivot", "salt")), strict=True))
            docs = batch.column("doc").to_pylist()
            body, offsets = C.utf8(batch.column("text"))
            links: list[tuple[int, int]] = []
            for i, j in C.row_slices(offsets, 1 << 20):
                value, count, first = shingles(body[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], size)
                if not weighted:
                    count = np.ones(len(value), np.int64)
                for r in range(i, j):
                    at = slice(first[r - i], first[r - i + 1])
                    h, n = value[at], count[at]
                    if groups[r] != now:
                        now, own = groups[r], (h.copy(), n.copy())
                        continue
                    place = np.minimum(np.searchsorted(own[0], h), len(own[0]) - 1)
                    both = own[0][place] == h
                    common = np.minimum(n[both], own[1][place[both]]).sum()
                    if common >= similarity * (n.sum() + own[1].sum() - common) - 1e-9:
                        links.append((now[0], docs[r]))
            yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in links], pa.int64()), pa.array([b for _, b in links], pa.int64())], names=["pivot", "doc"])

    return C.tidy(run)


def _verified(pairs: DataFrame, texts: DataFrame, size: int, similarity: float, weighted: bool) -> DataFrame:
    """Pairs (pivot, doc) whose whole shingle sets are similar enough."""
    many = pairs.groupBy("pivot").agg(F.greatest(F.lit(1), F.ceil(F.count("*") / SALT_ROWS)).cast("int").alias("salts"))
    salted = pairs.join(many, "pivot").select("pivot", "doc", F.pmod(F.hash("doc"), "salts").alias("salt"), F.lit(1).alias("later"))
    wanted = salted.union(many.select("pivot", F.col("pivot").alias("doc"), F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.lit(0)))
    beside = wanted.join(texts.withColumnRenamed("row", "doc"), "doc").select("pivot", "salt", "later", "doc", "text")
    grouped = beside.repartition("pivot", "salt").sortWithinPartitions("pivot", "salt", "later")
    return grouped.mapInArrow(_judge(size, similarity, weighted), "pivot long, doc long")


def _compare_block(similarity: float, weighted: bool, bands: int):
    """One cell of a family: its asking nodes against its partners; pairs that share a band and are not tied yet."""

    def run(asking: pa.Table, partners: pa.Table) -> pa.Table:
        found: list[tuple[int, int]] = []
        if len(asking) and len(partners):
            side = []
            for rows in (asking, partners):
                raw, offsets = C.utf8(rows.column("shingles"))
                flat = raw.view(_ENTRY)
                keys = rows.column("bands").combine_chunks().flatten().to_numpy().reshape(-1, bands)
                side.append((rows.column("doc").to_numpy(), rows.column("component").to_numpy(), keys, flat["h"], flat["n"].astype(np.int64) if weighted else np.ones(len(flat), np.int64), offsets // flat.itemsize))
            (a_doc, a_part, a_keys, a_hash, a_count, a_at), (b_doc, b_part, b_keys, b_hash, b_count, b_at) = side
            owner = np.repeat(np.arange(len(b_doc)), np.diff(b_at))
            weight = np.bincount(owner, b_count, len(b_doc))
            for r in range(len(a_doc)):
                near = np.flatnonzero((a_keys[r] == b_keys).any(axis=1) & (a_part[r] != b_part))
                if not len(near):
                    continue
                h, n = a_hash[a_at[r] : a_at[r + 1]], a_count[a_at[r] : a_at[r + 1]]
                upto = np.cumsum(b_at[near + 1] - b_at[near])
                for part in np.split(near, np.flatnonzero(np.diff(upto // _CELLS)) + 1):
                    size = b_at[part + 1] - b_at[part]
                    flat = C.ranges(b_at[part], size)
                    at = np.minimum(np.searchsorted(h, b_hash[flat]), len(h) - 1)
                    common = np.where(h[at] == b_hash[flat], np.minimum(n[at], b_count[flat]), 0)
                    both = np.bincount(np.repeat(np.arange(len(part)), size), common, len(part))
                    alike = both >= similarity * (n.sum() + weight[part] - both) - 1e-9
                    found += [(int(a_doc[r]), int(x)) for x in b_doc[part[alike]]]
        return pa.table({"pivot": pa.array([x for x, _ in found], pa.int64()), "doc": pa.array([y for _, y in found], pa.int64())})

    return run


def _rest(large: DataFrame, found: DataFrame, sets: DataFrame, texts: DataFrame, size: int, similarity: float, weighted: bool, bands: int, block: int) -> DataFrame:
    """Links between nodes of open large buckets (key, doc, pivot) that stars left in different components (node, component)."""
    named = large.join(found.withColumnRenamed("node", "doc"), "doc", "left").withColumn("component", F.coalesce("component", "doc"))
    mixed = named.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo <> hi").select("key")
    open_ = C.materialise(named.join(mixed, "key").select("doc", "pivot", "component"), "open")
    members = open_.select("doc", "component").distinct().join(sets.select("doc", "n"), "doc")
    family = components(open_.where("doc <> pivot"), "doc", "pivot").withColumnRenamed("component", "family")
    members = C.materialise(members.join(family.withColumnRenamed("node", "doc"), "doc"), "family")
    parts = members.groupBy("family", "component").agg(F.sum("n").alias("n"))
    facts = parts.groupBy("family").agg(F.sum("n").alias("all"), F.max(F.struct("n", (-F.col("component")).alias("c"))).alias("m"))
    facts = facts.select("family", (-F.col("m.c")).alias("main"), F.ceil(F.col("all") / block).cast("int").alias("blocks"), F.greatest(F.lit(1), F.ceil((F.col("all") - F.col("m.n")) / block)).cast("int").alias("askers"))
    rows = members.join(facts, "family").join(sets.select("doc", "bands"), "doc")
    told = members.join(texts.withColumnRenamed("row", "doc"), "doc").select("doc", "text").mapInArrow(_read_sets(size), "doc long, shingles binary")
    full = C.materialise(rows.join(told, "doc"), "family_sets")
    part = lambda n: F.pmod(F.xxhash64("doc"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    columns = ("family", "i", "j", "doc", "component", "bands", "shingles")
    asking = full.where("component <> main").withColumn("i", part("askers")).withColumn("j", every("blocks")).select(*columns)
    partners = full.withColumn("j", part("blocks")).withColumn("i", every("askers")).select(*columns)
    cell = ("family", "i", "j")
    return asking.groupBy(*cell).cogroup(partners.groupBy(*cell)).applyInArrow(_compare_block(similarity, weighted, bands), "pivot long, doc long")


def _classes(numbered: DataFrame, size: int = SHINGLE, similarity: float = SIMILARITY, bands: int = BANDS, rows: int = ROWS, weighted: bool = False, small: int = SMALL, block: int = BLOCK) -> DataFrame:
    """(row, doc_id, group, class_id) per row of numbered (row, doc_id, text), whose numbers are unique and written:
    rows of one class have one group, class_id is its least doc_id; null ids stand as the least."""
    texts = numbered.select("row", F.col("text").cast("string").alias("text"))
    named = numbered.select("row", C.known_id().alias("doc_id"), F.col("text").cast("string").alias("text"))
    sketch = C.materialise(named.mapInArrow(_sketch(size, bands, rows, weighted), _SKETCH), "sketch")
    sets = sketch.where("n > 0").groupBy("set_a", "set_b").agg(F.min("row").alias("doc"), F.min("doc_id").alias("least"), F.first("n").cast("long").alias("n"), F.first("bands").alias("bands"))
    keys = sets.select("doc", F.explode("bands").alias("key")).distinct()
    shared = keys.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    bucket = C.materialise(keys.join(shared, "key").select("key", "doc", "n"), "buckets")
    central = bucket.groupBy("doc").agg(F.sum(F.col("n") - 1).alias("met"))
    ranked = bucket.join(central, "doc").groupBy("key").agg(F.max(F.struct("met", (-F.col("doc")).alias("d"))).alias("m"))
    starred = C.materialise(bucket.join(ranked.select("key", (-F.col("m.d")).alias("pivot")), "key"), "stars")
    C.discard(bucket)
    pairs = starred.where("doc <> pivot").select("pivot", "doc").distinct()
    links = C.materialise(_verified(pairs, texts, size, similarity, weighted), "links")
    found = components(links, "pivot", "doc")

    few = starred.where((F.col("n") > 2) & (F.col("n") <= small)).join(found.withColumnRenamed("node", "doc"), "doc", "left").select("key", "doc", F.coalesce("component", "doc").alias("component"))
    untied = few.alias("a").join(few.alias("b"), (F.col("a.key") == F.col("b.key")) & (F.col("a.doc") < F.col("b.doc")) & (F.col("a.component") != F.col("b.component")))
    left = untied.select(F.col("a.doc").alias("pivot"), F.col("b.doc").alias("doc")).distinct()
    more = C.materialise(_verified(left, texts, size, similarity, weighted), "links")
    rest = C.materialise(_rest(starred.where(F.col("n") > small), found, sets, texts, size, similarity, weighted, bands, block), "links")
    found = components(links.union(more).union(rest), "pivot", "doc")
    nodes = sets.select("set_a", "set_b", "least", "doc").join(found.withColumnRenamed("node", "doc"), "doc", "left").select("set_a", "set_b", "least", F.coalesce("component", "doc").alias("group"))
    classes = nodes.join(nodes.groupBy("group").agg(F.min("least").alias("class_id")), "group").select("set_a", "set_b", "group", "class_id")
    tied = sketch.select("row", "doc_id", "n", "set_a", "set_b").join(classes, ["set_a", "set_b"], "left")
    own = lambda x, y: F.when(F.col("n") > 0, F.col(x)).otherwise(F.col(y)).alias(x)
    return tied.select("row", "doc_id", own("group", "row"), own("class_id", "doc_id"))


def _numbered(docs: DataFrame, name: str) -> DataFrame:
    return C.materialise(docs.withColumn(name, F.monotonically_increasing_id()), "numbered")


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """(doc_id, class_id) per row of docs (doc_id, text): class_id is the least doc_id of the connected group of
    documents tied by similarity of their word shingles (as sets, or with weighted by counts). Options: those of _classes.

    Null and empty texts have no shingle and are each their own class. Rows that repeat an id get
    one class each by their text. A null id counts as the least id; an empty table gives no row."""
    found = _classes(_numbered(docs.select("doc_id", "text"), "row"), **options)
    return found.select(C.original_id().alias("doc_id"), C.original_id("class_id").alias("class_id"))


def keep_first(docs: DataFrame, **options) -> DataFrame:
    """One row of docs (doc_id, text, any other columns) for each class: that of its least id (a null one first), of rows of
    one id the first as they were numbered. Texts without a shingle all stay."""
    row = C.fresh(docs, "_row")
    numbered = _numbered(docs, row)
    found = _classes(numbered.select(F.col(row).alias("row"), "doc_id", "text"), **options)
    first = found.groupBy("group").agg(F.min(F.struct("doc_id", "row")).alias("m")).select(F.col("m.row").alias(row))
    return numbered.join(first, row, "left_semi").select(*(F.col(f"`{c}`") for c in docs.columns))


def op7_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(C.table(spark, sf_dir, "documents"))


#: All pairs that share a shingle, judged exactly, and the least id of each connected group.
OP7_SQL = r"""with recursive d as materialized (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
s as materialized (select distinct doc_id, array_to_string(w[i : i + 4], ' ') as shown from d, unnest(generate_series(1, greatest(len(w) - 4, 1))) u(i) where len(w) > 0),
n as materialized (select doc_id, count(*) as n from s group by doc_id),
c as materialized (select a.doc_id as x, b.doc_id as y, count(*) as shared from s a join s b on a.shown = b.shown and a.doc_id < b.doc_id group by all),
l as materialized (select x, y from c join n p on p.doc_id = x join n q on q.doc_id = y where 5 * shared >= 4 * (p.n + q.n - shared)),
e as materialized (select x, y from l union all select y, x from l),
k(doc_id, class_id) using key (doc_id) as (
 select doc_id, doc_id from documents
 union
 select e.y, min(k.class_id) from k join e on e.x = k.doc_id join recurring.k as old on old.doc_id = e.y where k.class_id < old.class_id group by e.y)
select doc_id, class_id from k"""
