"""Secret scans over an incremental blob ledger.

Every text is a blob under its content address (SHA-256). The ledger has one row per scanned blob and rule
version, with the blob's findings. A run scans only the pairs that the ledger lacks, each blob once however many
rows carry it, and joins the findings back to all rows, of all historical versions given.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from replica_sync.llm.common import by_place, pick, shared_folder, small_batches

RULE_VERSION = "rules-1"
# The base patterns, then further well-known credential formats.
BASE = {
    "assign": (re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A), 2, 6),
    "access": (re.compile(r"AKIA[A-Z0-9]+"), 0, 20),
    "hex": (re.compile(r"[0-9a-f]{24,}"), 0, 24),
}
MORE = {
    "private_key": (re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:[^-]|-(?!----END))*(?:-----END [A-Z ]*PRIVATE KEY-----)?"), 0, 0),
    "jwt": (re.compile(r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"), 0, 0),
    "github": (re.compile(r"(?:gh[pousr]_[A-Za-z0-9]{36,}|github_pat_[A-Za-z0-9_]{22,})"), 0, 0),
    "slack": (re.compile(r"xox[abeoprs]-[A-Za-z0-9-]{10,}"), 0, 0),
    "url_login": (re.compile(r"[a-z][a-z0-9+.-]{1,15}://[^\s/:@]+:[^\s/:@]+@"), 0, 0),
}
KINDS = [*BASE, *MORE]
_MARKS = ("password", "passwd", "secret", "token", "apikey", "api_key")
_SEEDS = {"private_key": "PRIVATE KEY-----", "jwt": "eyJ", "github": "_", "slack": "xox", "url_login": "://", "access": "AKIA"}


def spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) in code points, by start, then kind in the order of KINDS."""
    lowered, found = None, []
    for order, (kind, (pattern, group, least)) in enumerate((BASE | MORE).items()):
        if kind in _SEEDS:
            if _SEEDS[kind] not in text:
                continue
        elif kind == "assign":
            lowered = text.lower()
            if not any(mark in lowered for mark in _MARKS):
                continue
        found += [(m.start(), order, m.end()) for m in pattern.finditer(text) if m.end(group) - m.start(group) >= least]
    return [(KINDS[order], start, end) for start, order, end in sorted(found)]


def digest_row(text: str) -> tuple[int, int, int, str, str]:
    """Counts of the base kinds, SHA-256 of the base spans, all spans."""
    every = spans(text)
    named = [f"{kind}:{start}:{end}" for kind, start, end in every]
    base = [x for x, (kind, _, _) in zip(named, every) if kind in BASE]
    counts = [sum(kind == k for kind, _, _ in every) for k in BASE]
    return (*counts, hashlib.sha256(",".join(base).encode()).hexdigest(), ",".join(named))


def redacted(text: str, mark: str, found: list[tuple[int, int]]) -> str:
    """The text with the found (start, end) spans, overlaps joined, replaced by mark."""
    out, at = [], 0
    for start, end in sorted(found):
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join([*out, text[at:]])


FINDINGS = "n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string"
LEDGER = f"blob string, rule_version string, {FINDINGS}"


def with_blob(rows: DataFrame) -> DataFrame:
    return rows.withColumn("blob", F.sha2(F.coalesce(F.col("text"), F.lit("")).cast("binary"), 256))


def scan_unseen(rows: DataFrame, ledger: DataFrame | None = None, rule_version: str = RULE_VERSION) -> DataFrame:
    """New ledger rows: findings of the blobs that the ledger lacks under this rule version.

    One copy of each blob reaches the scanner: copies meet in a partial aggregate before the exchange.
    """
    blobs = with_blob(rows.select("text"))
    if ledger is not None:
        seen = ledger.where(F.col("rule_version") == rule_version).select("blob")
        blobs = blobs.join(seen, "blob", "left_anti")
    once = blobs.groupBy("blob").agg(F.any_value(F.coalesce("text", F.lit(""))).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, "text"):
            found = [digest_row(x) for x in batch.column(1).to_pylist()]
            columns = [pa.array(c, t) for c, t in zip(zip(*found), [pa.int64()] * 3 + [pa.string()] * 2)]
            yield pa.record_batch([batch.column(0), pa.array([rule_version] * len(found)), *columns], names=[x.split()[0] for x in LEDGER.split(", ")])

    return once.mapInArrow(run, LEDGER)


class BlobLedger:
    """A ledger kept as a table of Parquet files at a path that all executors see."""

    def __init__(self, spark: SparkSession, path: str | None = None, rule_version: str = RULE_VERSION):
        self.spark, self.path, self.rule_version = spark, path or shared_folder(spark, "blob-ledger"), rule_version

    def rows(self) -> DataFrame | None:
        """All rows of all rule versions, None before the first run."""
        place = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        if not place.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(place):
            return None
        return self.spark.read.schema(LEDGER).parquet(self.path)

    def update(self, docs: DataFrame, text: str = "text") -> None:
        """Scans the blobs that are new under this rule version and appends them; repeating it adds nothing."""
        scan_unseen(pick(docs, text=text), self.rows(), self.rule_version).write.mode("append").parquet(self.path)

    def findings(self, docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
        """doc_id, the findings and blob of every row, joined back from the ledger."""
        return joined_back(with_blob(pick(docs, doc_id=doc_id, text=text)), self.spans())

    def spans(self) -> DataFrame:
        return self.spark.read.schema(LEDGER).parquet(self.path).where(F.col("rule_version") == self.rule_version)


def joined_back(rows: DataFrame, ledger: DataFrame) -> DataFrame:
    names = [x.split()[0] for x in FINDINGS.split(", ")]
    one = ledger.select("blob", *names)
    return rows.select("doc_id", "blob").join(one, "blob").select("doc_id", *names, "blob")


def scan_secrets(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", ledger: BlobLedger | None = None) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, blob of every row.

    ledger: of earlier runs, by default a new one in the shared folder; only what it lacks is scanned. A null text counts as empty, and
    has no spans. Repeated rows share one scan; an empty table gives an empty result; other columns are not read.
    """
    ledger = ledger or BlobLedger(docs.sparkSession)
    ledger.update(docs, text)
    return ledger.findings(docs, doc_id, text)


def redact_secrets(docs: DataFrame, text: str = "text", mark: str = "[secret]", ledger: BlobLedger | None = None) -> DataFrame:
    """The same rows and columns, every found span of the text replaced by mark and n_chars, if there, set anew.

    ledger: as in scan_secrets; the spans come back from it by content address. Null and empty texts stay as they are, repeated rows stay
    repeated, an empty table gives an empty result, and other columns of whatever names go along.
    """
    ledger = ledger or BlobLedger(docs.sparkSession)
    ledger.update(docs, text)
    schema, place = docs.schema, docs.columns.index(text)
    size = docs.columns.index("n_chars") if "n_chars" in docs.columns else None
    address = F.sha2(F.coalesce(F.col(f"`{text}`"), F.lit("")).cast("binary"), 256)
    found = ledger.spans().where(F.col("spans") != "").select(F.col("blob").alias("found blob"), F.col("spans").alias("found spans"))
    addressed = docs.select(*[F.col(f"`{c}`") for c in docs.columns], address.alias("text address"))
    marked = addressed.join(found, F.col("text address") == F.col("found blob"), "left").drop("text address", "found blob")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in small_batches(batches, f"c{place}"):
            columns = list(batch.columns)
            where = columns.pop().to_pylist()
            if any(where):
                old = columns[place].to_pylist()
                new = [redacted(x, mark, [tuple(map(int, s.split(":")[1:])) for s in w.split(",")]) if w else x for x, w in zip(old, where)]
                columns[place] = pa.array(new, columns[place].type)
                if size is not None:
                    columns[size] = pa.array([len(b) if w else n for b, w, n in zip(new, where, columns[size].to_pylist())], columns[size].type)
            yield pa.record_batch(columns, names=schema.names)

    return by_place(marked).mapInArrow(run, schema)
