"""Secret scans by an incremental ledger of content-addressed blobs.

Every text (any version of any path) is one blob, named by its SHA-256. The ledger is a
table of (blob, rule_version, spans) for everything scanned so far. A run scans only those
blobs that the ledger lacks under the present rule version, each once however many paths
hold it, and joins the findings back to all paths.

Defined results: a null text is the empty blob; an empty text has no findings; repeated
rows get equal findings each; overlapping findings of different kinds are all kept, and
within a kind findings are leftmost and do not overlap; ties at one start go by the order
of RULES; an empty table gives an empty result. Extra columns are carried through.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .kernels import frugal

RULE_VERSION = "3"
LEDGER_SCHEMA = "blob binary, rule_version string, spans array<string>"

# The patterns. (kind, pattern, group whose length counts, least length, base rule)
RULES = (
    ("assign", r"(?:(?i:password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 1, 6, True),
    ("access", r"AKIA[A-Z0-9]+", 0, 20, True),
    ("hex", r"[0-9a-f]{24,}", 0, 24, True),
    ("private_key", r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----[A-Za-z0-9+/=\s]*(?:-----END (?:[A-Z]+ )*PRIVATE KEY-----)?", 0, 1, False),
    ("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]*", 0, 20, False),
    ("bearer", r"(?i:bearer)\x20+[A-Za-z0-9._~+/-]{16,}", 0, 16, False),
    ("url_login", r"[a-z][a-z0-9+.-]{1,20}://[^\s/:@]{1,64}:[^\s/:@]{1,128}@", 0, 1, False),
    ("vendor_key", r"(?:gh[pousr]_|xox[abprs]-|sk_live_|AIza)[A-Za-z0-9_-]{16,}", 0, 20, False),
)
ORDER = {kind: i for i, (kind, *_) in enumerate(RULES)}
BASE = tuple(kind for kind, *_, base in RULES if base)
_COMPILED = [(kind, re.compile(pattern, re.ASCII), group, least) for kind, pattern, group, least, _ in RULES]


def find_secrets(text: str | None) -> list[tuple[int, int, str]]:
    """(start, end, kind) of every finding, in code points, by start and then the order of RULES."""
    found = []
    for kind, pattern, group, least in _COMPILED if text else ():
        found += [(m.start(), m.end(), kind) for m in pattern.finditer(text) if m.end(group) - m.start(group) >= least]
    return sorted(found, key=lambda x: (x[0], ORDER[x[2]]))


def scan_blobs(blobs: DataFrame) -> DataFrame:
    """(blob, text) to ledger rows: blob, rule_version and spans as ``kind:start:end`` strings."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans = [[f"{k}:{a}:{b}" for a, b, k in find_secrets(x.as_py())] for x in batch.column("text")]
            yield pa.RecordBatch.from_arrays([batch.column("blob"), pa.array([RULE_VERSION] * len(spans), type=pa.string()), pa.array(spans, type=pa.list_(pa.string()))], names=["blob", "rule_version", "spans"])

    return blobs.select("blob", "text").mapInArrow(frugal(run), LEDGER_SCHEMA)


def blob_of(text: str = "text"):
    return F.unhex(F.sha2(F.coalesce(F.col(text), F.lit("")).cast("binary"), 256))


def pending_blobs(paths: DataFrame, ledger: DataFrame | None = None, text: str = "text") -> DataFrame:
    """(blob, text) once for each blob that the ledger lacks under RULE_VERSION."""
    named = paths.select(blob_of(text).alias("blob"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    once = named.groupBy("blob").agg(F.first("text").alias("text"))
    if ledger is None:
        return once
    return once.join(ledger.where(F.col("rule_version") == RULE_VERSION).select("blob"), "blob", "left_anti")


def stored_ledger(spark: SparkSession, ledger_path: str) -> DataFrame | None:
    """The rows under ledger_path, or None if nothing stands there yet."""
    try:
        return spark.read.schema(LEDGER_SCHEMA).parquet(ledger_path)
    except AnalysisException as e:
        if e.getCondition() != "PATH_NOT_FOUND":
            raise
        return None


def extend_ledger(paths: DataFrame, ledger_path: str, ledger: DataFrame | None = None, text: str = "text") -> DataFrame:
    """Scan what neither ledger has, append it to the table under ledger_path, and return the whole ledger.

    ledger: rows of earlier runs kept elsewhere; those stored under ledger_path needn't be passed.
    """
    spark = paths.sparkSession
    stored = stored_ledger(spark, ledger_path)
    known = ledger.select("blob", "rule_version", "spans") if ledger is not None else None
    both = [x for x in (stored, known) if x is not None]
    fresh = scan_blobs(pending_blobs(paths, reduce(DataFrame.unionByName, both) if both else None, text))
    fresh.write.mode("append").parquet(ledger_path)
    stored = spark.read.schema(LEDGER_SCHEMA).parquet(ledger_path)
    if known is None:
        return stored
    return stored.unionByName(known.join(stored.select("blob", "rule_version"), ["blob", "rule_version"], "left_anti"))


def findings_by_path(paths: DataFrame, ledger: DataFrame, keys: list[str], text: str = "text") -> DataFrame:
    """keys and ``spans`` of every path, from the ledger's rows of RULE_VERSION."""
    # Only blobs with findings travel; of equal rows (a scan that ran twice) one counts.
    known = ledger.where((F.col("rule_version") == RULE_VERSION) & (F.size("spans") > 0)).groupBy("blob").agg(F.first("spans").alias("spans"))
    named = paths.select(*keys, blob_of(text).alias("blob"))
    return named.join(known, "blob", "left").select(*keys, "blob", F.coalesce("spans", F.array().cast("array<string>")).alias("spans"))


def digests(found: DataFrame, key: str = "doc_id") -> DataFrame:
    """Counts by base kind, the base spans' SHA-256 and all spans, comma-joined."""
    base = F.filter("spans", lambda x: F.split(x, ":")[0].isin(*BASE))
    count = lambda kind: F.size(F.filter("spans", lambda x: x.startswith(f"{kind}:"))).cast("bigint").alias(f"n_{kind}")
    return found.select(key, *[count(k) for k in BASE], F.sha2(F.concat_ws(",", base).cast("binary"), 256).alias("base_sha256"), F.concat_ws(",", "spans").alias("spans"))
