"""Secret scans with an incremental ledger of content-addressed blobs.

Every version of a text is addressed by the SHA-256 of its bytes. A ledger says which rules, by name and version, each
blob has been scanned with, and what was found. A scan reads one copy of each blob that lacks a pair (blob, rule version),
runs only the missing rules on it, and joins the findings back to all rows that hold the blob. Copies, reverts and
versions scanned before cost nothing again; a new rule version rescans each blob for that rule alone.

Null texts are the empty blob. Rows may repeat; every row gets its findings; further columns are kept. An empty table
gives an empty ledger. Offsets are code points, end exclusive; letters match in either case only where a rule says so.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import settle, table


@dataclass(frozen=True)
class SecretRule:
    """kind: name of what is found; least: characters that `group` must have, else the match is dropped; marks: a text without any of them can't match."""

    kind: str
    version: int
    pattern: str
    group: int = 0
    least: int = 0
    flags: int = re.ASCII
    marks: tuple[str, ...] = ()

    @property
    def key(self) -> str:
        return f"{self.kind}@{self.version}"


#: The patterns of the contract.
BASE_RULES = (
    SecretRule("assign", 1, r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6, re.ASCII | re.IGNORECASE, (":", "=")),
    SecretRule("access", 1, r"AKIA[A-Z0-9]+", 0, 20, re.ASCII, ("AKIA",)),
    SecretRule("hex", 1, r"[0-9a-f]{24,}", 0, 24),
)
MORE_RULES = (
    SecretRule("pem", 1, r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----(?:[A-Za-z0-9+/=\s]*-----END [A-Z ]{0,40}PRIVATE KEY-----)?", 0, 0, re.ASCII, ("PRIVATE KEY-----",)),
    SecretRule("jwt", 1, r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0, 0, re.ASCII, ("eyJ",)),
    SecretRule("url_login", 1, r"(?<![a-z0-9+.-])[a-z][a-z0-9+.-]{1,20}://[^\s:/@]{1,200}:[^\s:/@]{1,200}@", 0, 0, re.ASCII, ("://",)),
)
RULES = BASE_RULES + MORE_RULES
SPANS = "array<struct<kind:string,start:int,end:int>>"
LEDGER = f"blob string, rules array<string>, spans {SPANS}"


def blob(text: Column) -> Column:
    return F.sha2(F.coalesce(text, F.lit("")), 256)


def spans_in(text: str, rules: Iterable[SecretRule]) -> list[dict]:
    """Leftmost non-overlapping matches of each rule, in the order of rules."""
    found = []
    for rule in rules:
        if rule.marks and not any(m in text for m in rule.marks):
            continue
        for m in re.finditer(rule.pattern, text, rule.flags):
            if m.end(rule.group) - m.start(rule.group) >= rule.least:
                found.append({"kind": rule.kind, "start": m.start(), "end": m.end()})
    return found


def scan_ledger(versions: DataFrame, text: str = "text", ledger: DataFrame | None = None, rules: tuple[SecretRule, ...] = RULES) -> DataFrame:
    """The ledger after this scan, written to the shared folder: what it held, and every blob of `versions`."""
    by_key = {r.key: r for r in rules}
    wanted = F.array(*[F.lit(k) for k in by_key]).cast("array<string>")
    unseen = versions.select(blob(F.col(text)).alias("blob"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    if ledger is None:
        unseen = unseen.withColumn("missing", wanted)
    else:
        known = ledger.select("blob", F.col("rules").alias("known"))
        unseen = unseen.join(known, "blob", "left").withColumn("missing", F.array_except(wanted, F.coalesce("known", F.array().cast("array<string>"))))
        unseen = unseen.where(F.size("missing") > 0).drop("known")
    unseen = unseen.groupBy("blob").agg(F.first("text").alias("text"), F.first("missing").alias("missing"))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())])
        for batch in batches:
            rows = zip(batch.column(1), batch.column(2), strict=True)
            spans = [spans_in(t.as_py(), [by_key[k] for k in m.as_py()]) for t, m in rows]
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.string()), batch.column(2).cast(pa.list_(pa.string())), pa.array(spans, pa.list_(kind))], ["blob", "rules", "spans"])

    made = unseen.select("blob", "text", "missing").mapInArrow(scan, LEDGER)
    if ledger is not None:
        held = ledger.select(F.col("blob"), F.col("rules"), F.col("spans"))
        made = held.unionByName(made).groupBy("blob").agg(F.flatten(F.collect_list("rules")).alias("rules"), F.flatten(F.collect_list("spans")).alias("spans"))
    return settle(made.select("blob", "rules", "spans"), "secret-ledger", large=True)


def with_findings(versions: DataFrame, ledger: DataFrame, text: str = "text", rules: tuple[SecretRule, ...] = RULES, out: str = "secret_spans") -> DataFrame:
    """Adds a column of spans to every row: the findings of its blob by the kinds of `rules`, by start, then in the order of rules."""
    order = F.array(*[F.lit(r.kind) for r in rules])
    hits = ledger.where(F.size("spans") > 0).select(F.col("blob").alias("__blob"), F.col("spans").alias("__spans"))
    joined = versions.withColumn("__key", blob(F.col(text))).join(hits, F.col("__key") == F.col("__blob"), "left")
    keyed = F.transform(
        F.filter(F.coalesce("__spans", F.array().cast(SPANS)), lambda s: F.array_contains(order, s["kind"])),
        lambda s: F.struct(s["start"].alias("start"), F.array_position(order, s["kind"]).alias("rank"), s["end"].alias("end"), s["kind"].alias("kind")),
    )
    return joined.withColumn(out, F.sort_array(keyed)).drop("__key", "__blob", "__spans")


def redacted(versions: DataFrame, text: str = "text", mask: str = "[SECRET]") -> DataFrame:
    """The rows with every secret replaced; spans that overlap become one mask."""
    columns = versions.columns
    found = with_findings(versions, scan_ledger(versions, text), text, out="__secrets")
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))

    def step(a: Column, s: Column) -> Column:
        fresh = s["start"] >= a["at"]
        put = F.when(fresh, F.concat(a["out"], F.substring(F.col(text), a["at"] + 1, s["start"] - a["at"]), F.lit(mask))).otherwise(a["out"])
        return F.struct(put.alias("out"), F.greatest(a["at"], s["end"]).alias("at"))

    rest = lambda a: F.concat(a["out"], F.substring(F.col(text), a["at"] + 1, F.length(text)))
    clean = F.when(F.size("__secrets") > 0, F.aggregate("__secrets", start, step, rest)).otherwise(F.col(text))
    return found.withColumn(text, clean).select(*columns)


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op5_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    # the rules come in two versions of the set: the second scan runs on each blob only what the ledger lacks
    ledger = scan_ledger(docs, ledger=scan_ledger(docs, rules=BASE_RULES))
    found = with_findings(docs, ledger).select("doc_id", "secret_spans")
    base = F.filter("secret_spans", lambda s: s["kind"].isin([r.kind for r in BASE_RULES]))
    n = lambda kind: F.size(F.filter("secret_spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", n("assign"), n("access"), n("hex"), F.sha2(_listed(base), 256).alias("base_sha256"), _listed(F.col("secret_spans")).alias("spans"))
