"""Secret scans over an incremental ledger of content-addressed blobs.

Every version of a text is addressed by its SHA-256. A ledger row says what one version
of one rule found in one blob; only pairs of blob and rule version that the ledger lacks
are scanned, each once, however many paths hold the blob. Findings then join back to all paths.

Defined cases: a null text is the empty text; a null path is a path like any other; repeated
rows each get their row; findings that start together come in the order of the rules; a text of any length is searched as a whole; an empty
table gives an empty result; other columns, of whatever name, are ignored or come back as they were.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common


class Rule(NamedTuple):
    """group: the group whose length counts; least: the least length of a finding."""

    kind: str
    version: int
    pattern: str
    flags: int
    group: int
    least: int


# The kinds, patterns and least lengths of the base rules, in their order.
RULES = (
    Rule("assign", 1, r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.ASCII | re.IGNORECASE, 2, 6),
    Rule("access", 1, r"AKIA[A-Z0-9]+", re.ASCII, 0, 20),
    Rule("hex", 1, r"[0-9a-f]+", re.ASCII, 0, 24),
)

#: Batches in which the query lets the versions come.
BATCHES = 2
SPANS = "array<struct<start:int,stop:int>>"
LEDGER = f"blob string, kind string, version int, spans {SPANS}"


def find(rule: Rule, text: str) -> list[dict]:
    """Leftmost matches that don't overlap; those too short are dropped afterwards."""
    pattern = rule.pattern
    if rule.group == 0 and pattern.endswith("]+"):  # a greedy run: to ask for the least length at once finds the same runs
        fixed = 4 if pattern.startswith("AKIA") else 0
        pattern = f"{pattern[:-1]}{{{rule.least - fixed},}}"
    return [{"start": m.start(), "stop": m.end()} for m in re.finditer(pattern, text, rule.flags) if m.end(rule.group) - m.start(rule.group) >= rule.least]


def _scan(rules: tuple[Rule, ...]):
    by_key = {(r.kind, r.version): r for r in rules}
    schema = pa.schema([("blob", pa.string()), ("kind", pa.string()), ("version", pa.int32()), ("spans", pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())])))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, "text"):
            rows = []
            for blob, text, due in zip(*(common.column(part, c).to_pylist() for c in ("blob", "text", "due")), strict=True):
                for key in due:
                    rule = by_key[key["kind"], key["version"]]
                    rows.append({"blob": blob, "kind": rule.kind, "version": rule.version, "spans": find(rule, text)})
            yield pa.RecordBatch.from_pylist(rows, schema)

    return run


def update_ledger(docs: DataFrame, ledger: DataFrame | None = None, rules: tuple[Rule, ...] = RULES, path: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(versions: path and blob of every row, ledger entries that were missing).

    ledger: blob, kind, version, spans of earlier runs. Entries to come are not computed before they are read.
    """
    versions = common.stage(docs.select(F.col(path).alias("path"), F.sha2(F.coalesce(F.col(text), F.lit("")), 256).alias("blob")))
    wanted = F.array(*(F.struct(F.lit(r.kind).alias("kind"), F.lit(r.version).alias("version")) for r in rules))
    blobs = versions.groupBy("blob").agg(F.min("path").alias("at"))  # one path per blob: copies are dropped before any text moves
    if ledger is None:
        due = blobs.withColumn("due", wanted)
    else:
        pairs = blobs.select("blob", "at", F.explode(wanted).alias("w")).select("blob", "at", "w.kind", "w.version")
        due = pairs.join(ledger, ["blob", "kind", "version"], "left_anti").groupBy("blob", "at").agg(F.collect_set(F.struct("kind", "version")).alias("due"))
    texts = docs.select(F.col(path).alias("path"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    unseen = texts.join(due, F.col("path").eqNullSafe(F.col("at"))).where(F.sha2("text", 256) == F.col("blob")).select("blob", "text", "due")
    found = unseen.mapInArrow(_scan(rules), LEDGER)
    return versions, found.groupBy("blob", "kind", "version").agg(F.first("spans").alias("spans"))


def findings(versions: DataFrame, ledger: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """path, blob, spans (kind, start, stop; by start, then by the order of the rules) of every version's row."""
    order = F.create_map(*(x for k, r in enumerate(rules) for x in (F.lit(r.kind), F.lit(k))))
    each = ledger.where(F.size("spans") > 0).select("blob", F.transform("spans", lambda s: F.struct(s["start"].alias("start"), order[F.col("kind")].alias("rank"), s["stop"].alias("stop"), F.col("kind").alias("kind"))).alias("spans"))
    by_blob = each.groupBy("blob").agg(F.sort_array(F.flatten(F.collect_list("spans"))).alias("spans"))
    return versions.join(by_blob, "blob", "left").select("path", "blob", F.coalesce("spans", F.array().cast("array<struct<start:int,rank:int,stop:int,kind:string>>")).alias("spans"))


def listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")


def batch_of(path: Column, batches: int) -> Column:
    """In which of so many batches a path's version comes."""
    return F.pmod(F.xxhash64(path), F.lit(batches))


def history(docs: DataFrame, rules: tuple[Rule, ...] = RULES, batches: int = BATCHES) -> tuple[DataFrame, DataFrame]:
    """(versions, ledger) of docs (doc_id, text) that come in batches, one after the other.

    The ledger is a table in the shared folder that each batch adds its missing entries to: a blob that an earlier batch held is not scanned again.
    """
    versions, ledger = None, None
    for k in range(batches):
        seen, missing = update_ledger(docs.where(batch_of(F.col("doc_id"), batches) == k), ledger, rules)
        missing = common.stage(missing)
        versions = seen if versions is None else versions.unionByName(seen)
        ledger = missing if ledger is None else ledger.unionByName(missing)
    return versions, ledger


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    versions, ledger = history(common.documents(spark, sf_dir).select("doc_id", "text"))
    found = findings(versions, ledger)

    def count(kind: str) -> Column:
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    return found.select(F.col("path").alias("doc_id"), *(count(r.kind) for r in RULES), F.sha2(listed(F.col("spans")), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"), "blob")


def redact(docs: DataFrame) -> DataFrame:
    """docs with every finding in its text replaced by its kind in brackets; n_chars follows."""
    versions, ledger = update_ledger(docs.select("doc_id", "text"))
    hit = findings(versions, ledger).where(F.size("spans") > 0).select("path", "blob", "spans").dropDuplicates(["path", "blob"])
    keyed = common.as_row(docs).select("row", F.col("row.doc_id").alias("id"), F.col("row.text").alias("text"), F.sha2(F.coalesce("row.text", F.lit("")), 256).alias("own"))
    joined = keyed.join(hit, F.col("id").eqNullSafe(F.col("path")) & (F.col("own") == F.col("blob")), "left")
    # Overlapping findings make one gap; text between gaps stays as it is.
    step = F.aggregate(
        "spans",
        F.struct(F.lit("").alias("out"), F.lit(0).alias("at")),
        lambda a, s: F.when(s["stop"] <= a["at"], a).otherwise(F.struct(F.concat(a["out"], F.substring(F.col("text"), a["at"] + 1, F.greatest(s["start"] - a["at"], F.lit(0))), F.concat(F.lit("["), s["kind"], F.lit("]"))).alias("out"), s["stop"].alias("at"))),
    )
    clean = F.when(F.col("spans").isNull(), F.col("text")).otherwise(F.concat(step["out"], F.substring(F.col("text"), step["at"] + 1, F.length("text"))))
    own = {"text": clean}
    if "n_chars" in docs.columns:
        own["n_chars"] = F.when(F.col("spans").isNull(), F.col("row.n_chars")).otherwise(F.length(clean).cast("long"))
    return common.from_row(joined, docs.columns, **own)
