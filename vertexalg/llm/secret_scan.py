"""Operator 2 [native]: incremental secret scan over a blob ledger.

Every version of a text is named by its SHA-256. The ledger holds one row per (blob, rule, version) that has been
scanned, with the spans found; a scan reads the distinct blobs, leaves out pairs that the ledger has, and joins
the findings back to all paths that have the blob. Only DataFrame expressions run: the pieces between matches
(split) and the matches (regexp_extract_all) give the places of matches by their lengths.

Scale: a blob is scanned once however many paths hold it; copies are dropped before the shuffle by
the partial aggregate; paths and findings meet on 64-byte names. A blob of more than 1 / ``HOT`` of all paths is met in
parts: there are fewer than ``HOT`` of those whatever the table's size, so their names may be broadcast.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.llm import common as C


@dataclass(frozen=True)
class Rule:
    """kind and version name the rule; group of a match must have least characters (group 0: the match)."""

    kind: str
    pattern: str
    group: int
    least: int
    version: str = "1"

    @property
    def name(self) -> str:
        return f"{self.kind}@{self.version}"


_BEGIN = r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY(?: BLOCK)?-----"
#: The first three are the base kinds, in the order in which they rank.
RULES = (
    Rule("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 1, 6),
    # runs are maximal, so asking for the length in the pattern finds the same matches as dropping short ones after
    Rule("access", r"AKIA[A-Z0-9]{16,}", 0, 20),
    Rule("hex", r"[0-9a-f]{24,}", 0, 24),
    # up to the END line, or where it is missing the next lines (60 at most) that look like a key's
    Rule("pem", _BEGIN + r"(?:[^-]*(?:-[^-]+){0,8}" + _BEGIN.replace("BEGIN", "END") + r"|(?:[ \t\r\n]+[A-Za-z0-9+/=]{16,}){0,60})", 0, 1, "2"),
)
BASE, HOT = 3, 1000
_SPAN = "array<struct<start: long, rank: int, kind: string, end: long>>"


def spans_of(text: Column, rule: Rule, rank: int) -> Column:
    """Spans of the leftmost non-overlapping matches whose group is long enough; code points, end exclusive."""
    gaps, found = F.split(text, rule.pattern, -1), F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    kept = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group))
    # zipped first, so that a text is split once and not once per match; the gap after the last match goes
    zipped = F.filter(F.arrays_zip(gaps.alias("gap"), found.alias("found"), kept.alias("kept")), lambda x: x["found"].isNotNull())
    rows = F.transform(zipped, lambda x: F.struct(F.length(x["gap"]).alias("gap"), F.length(x["found"]).alias("size"), F.length(x["kept"]).alias("kept")))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.expr(f"cast(array() as {_SPAN})").alias("out"))

    def step(acc: Column, m: Column) -> Column:
        begin = acc["at"] + m["gap"]
        span = F.struct(begin.alias("start"), F.lit(rank).alias("rank"), F.lit(rule.kind).alias("kind"), (begin + m["size"]).alias("end"))
        return F.struct((begin + m["size"]).alias("at"), F.when(m["kept"] >= rule.least, F.array_append(acc["out"], span)).otherwise(acc["out"]).alias("out"))

    spans = F.aggregate(rows, start, step, lambda acc: acc["out"])
    return F.when(text.rlike(rule.pattern), spans).otherwise(F.expr(f"cast(array() as {_SPAN})"))


def scan_blobs(blobs: DataFrame, rules: tuple[Rule, ...] = RULES, ledger: DataFrame | None = None) -> DataFrame:
    """New ledger rows (blob, rule, spans) for blobs (blob, text): of each blob the rules that the ledger lacks."""
    if ledger is None:
        todo = blobs.withColumn("seen", F.array().cast("array<string>"))
    else:
        seen = ledger.groupBy("blob").agg(F.collect_set("rule").alias("seen"))
        todo = blobs.join(seen, "blob", "left").withColumn("seen", F.coalesce("seen", F.array().cast("array<string>")))
        todo = todo.where(F.size(F.array_except(F.array(*(F.lit(r.name) for r in rules)), "seen")) > 0)
    each = [F.when(~F.array_contains("seen", r.name), F.struct(F.lit(r.name).alias("rule"), spans_of(F.col("text"), r, k).alias("spans"))) for k, r in enumerate(rules)]
    return todo.select("blob", F.explode(F.array_compact(F.array(*each))).alias("x")).select("blob", "x.rule", "x.spans")


def _blob(text: str = "text") -> Column:
    """The name of a text; a null one is empty."""
    return F.sha2(F.coalesce(F.col(text).cast("string"), F.lit("")), 256)


def distinct_blobs(paths: DataFrame) -> DataFrame:
    """(blob, text) once per text of paths (text)."""
    return paths.select(_blob().alias("blob"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).groupBy("blob").agg(F.first("text").alias("text"))


def read_ledger(spark: SparkSession, path: str) -> DataFrame | None:
    """The ledger (blob, rule, spans) in a Parquet folder; None if there is none yet."""
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return spark.read.parquet(path) if folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder) else None


def update_ledger(paths: DataFrame, path: str, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Scan what the ledger in folder path lacks of paths (text) and append it; the whole ledger. Nothing that was
    scanned before with the same version of a rule is scanned again."""
    scan_blobs(distinct_blobs(paths), rules, read_ledger(paths.sparkSession, path)).write.mode("append").parquet(path)
    return read_ledger(paths.sparkSession, path)


def _located(paths: DataFrame, rules: tuple[Rule, ...], ledger: DataFrame) -> tuple[DataFrame, str, str]:
    """paths with two more columns, whose names are returned: the blob and its spans (null if it has none)."""
    blob, spans = C.fresh(paths, "_blob"), C.fresh(paths, "_spans")
    known = ledger.where(F.col("rule").isin([r.name for r in rules]) & (F.size("spans") > 0))
    by_blob = known.groupBy("blob").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("spans")))).alias("spans"))
    counts = paths.select(_blob().alias("blob")).groupBy("blob").agg(F.count("*").alias("n"))
    total = max(1, paths.count())
    hot = F.broadcast(counts.where(F.col("n") * HOT > total).select("blob", F.ceil(F.col("n") * HOT / total).cast("int").alias("salts")))
    every = by_blob.join(hot, "blob", "left").select(F.col("blob").alias(blob), F.col("spans").alias(spans), F.explode(F.sequence(F.lit(0), F.coalesce("salts", F.lit(1)) - 1)).alias("_salt"))
    salt, salts = C.fresh(paths, "_salt"), C.fresh(paths, "_salts")
    keyed = paths.withColumn(blob, _blob()).join(hot.select(F.col("blob").alias(blob), F.col("salts").alias(salts)), blob, "left")
    keyed = keyed.withColumn(salt, F.pmod(F.monotonically_increasing_id(), F.coalesce(F.col(salts), F.lit(1))).cast("int"))
    return keyed.join(every.withColumnRenamed("_salt", salt), [blob, salt], "left").select(*(F.col(f"`{c}`") for c in paths.columns), blob, spans), blob, spans


def findings(paths: DataFrame, rules: tuple[Rule, ...] = RULES, ledger: DataFrame | None = None, ledger_path: str | None = None) -> DataFrame:
    """(path columns but text, blob, spans): each row of paths (text, ...) with all spans of its blob, sorted by
    start and then rank of the rule. A null text is an empty one; equal texts share one scan; ids may be null or repeat, as
    rows are met by their texts; an empty table gives no row. Columns of paths that are named blob or spans are left out.

    ledger_path: a Parquet folder; its rows count as the ledger, and new ones are appended to it. ledger: rows
    of an earlier scan, which stays as it is. Without either everything is new, and kept for this call alone."""
    if ledger_path is not None:
        known = update_ledger(paths, ledger_path, rules)
    else:
        known = C.materialise(scan_blobs(distinct_blobs(paths), rules, ledger), "ledger")
        known = known if ledger is None else known.unionByName(ledger)
    found, blob, spans = _located(paths, rules, known)
    kept = [F.col(f"`{c}`") for c in paths.columns if c.lower() not in ("text", "blob", "spans")]
    return found.select(*kept, F.col(blob).alias("blob"), F.coalesce(spans, F.expr(f"cast(array() as {_SPAN})")).alias("spans"))


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Spans are read back from the ledger that the scan has written."""
    found = findings(C.table(spark, sf_dir, "documents").select("doc_id", "text"))
    base = F.filter("spans", lambda s: s["rank"] < BASE)
    count = lambda k: F.size(F.filter("spans", lambda s: s["rank"] == k)).cast("long")
    return found.select("doc_id", *(count(k).alias(f"n_{r.kind}") for k, r in enumerate(RULES[:BASE])), F.sha2(_joined(base), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def redact(docs: DataFrame, rules: tuple[Rule, ...] = RULES, mark: str = "[secret]") -> DataFrame:
    """docs (text, ...) with every maximal union of spans replaced by mark; null texts stay null, and so do all
    rows and other columns, whatever their names. Findings travel by blob, so the text moves to them once."""
    known = C.materialise(scan_blobs(distinct_blobs(docs), rules), "ledger")
    found, _, spans = _located(docs, rules, known)
    text = F.col("text").cast("string")
    start = F.struct(F.lit("").alias("out"), F.lit(0).cast("long").alias("at"))

    def step(acc: Column, s: Column) -> Column:
        # text up to the span, and the mark unless the span goes on from the one before
        gap = F.substr(text, (acc["at"] + 1).cast("int"), F.greatest(s["start"] - acc["at"], F.lit(0)).cast("int"))
        shown = F.when((s["start"] >= acc["at"]), F.concat(acc["out"], gap, F.lit(mark))).otherwise(acc["out"])
        return F.struct(shown.alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))

    clean = F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substr(text, (acc["at"] + 1).cast("int"), F.length(text))))
    shown = F.when(text.isNotNull() & F.col(spans).isNotNull(), clean).otherwise(text)
    return found.select(*(shown.alias(c) if c == "text" else F.col(f"`{c}`") for c in docs.columns))


# the SQL finds whole runs and drops short ones after, as the kinds are defined
_WHOLE = {"access": r"AKIA[A-Z0-9]+", "hex": r"[0-9a-f]+"}
_ORACLE_RULES = [(r.kind, _WHOLE.get(r.kind, r.pattern).replace("'", "''"), r.group, r.least, k) for k, r in enumerate(RULES)]
OP2_SQL = (
    "with d as (select doc_id, coalesce(text, '') as text from documents), m as ("
    + " union all ".join(f"select doc_id, '{kind}' as kind, {k} as rank, {least} as least, string_split_regex(text, '{p}') as gaps, regexp_extract_all(text, '{p}') as found, regexp_extract_all(text, '{p}', {g}) as kept from d" for kind, p, g, least, k in _ORACLE_RULES)
    + """), i as (select *, unnest(range(1, len(found) + 1)) as n from m),
s as (select doc_id, kind, rank, cast(list_sum(list_transform(gaps[1:n], lambda x: length(x))) + coalesce(list_sum(list_transform(found[1:n - 1], lambda x: length(x))), 0) as bigint) as start, length(found[n]) as size from i where length(kept[n]) >= least),
t as (select doc_id, count(*) filter (rank = 0) as a, count(*) filter (rank = 1) as b, count(*) filter (rank = 2) as c,
 string_agg(kind || ':' || start || ':' || (start + size), ',' order by start, rank) filter (rank < 3) as base, string_agg(kind || ':' || start || ':' || (start + size), ',' order by start, rank) as spans from s group by doc_id)
select doc_id, coalesce(a, 0) as n_assign, coalesce(b, 0) as n_access, coalesce(c, 0) as n_hex, sha256(coalesce(base, '')) as base_sha256, coalesce(spans, '') as spans from d left join t using (doc_id)"""
)
