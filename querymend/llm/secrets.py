"""Secret scan with an incremental ledger of blobs.

A blob is a text under its SHA-256; a path (document id, file version) points
to one. The ledger keeps, for each blob and rule version, the spans found. A
scan addresses every path, leaves out blobs that the ledger already has under
the rule version, reads one path of each blob that is left, appends to the
ledger and joins the findings back to all paths. Texts stay where they are:
only addresses are shuffled, and the versions (path and blob) to skip, later
copies and known blobs, are broadcast while they are few, or anti-joined beyond
that. A path may have several blobs and may be null.

Null texts count as empty (no spans). Repeated rows give repeated results.
Other columns are left behind.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, slices, workspace

SPANS = "array<struct<start:int,rank:int,stop:int,kind:string>>"


@dataclass(frozen=True)
class SecretRule:
    """``hint``: literals of which a text with a match has one, in lower case if
    ``fold``; () for none. ``group`` must have ``least`` characters."""

    kind: str
    pattern: str
    hint: tuple[str, ...]
    fold: bool = False
    group: int = 0
    least: int = 0


#: Fixed values of the contract: the base kinds in their order.
BASE_RULES = [
    SecretRule("assign", r"""(?ai:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", ("password", "passwd", "secret", "token", "apikey", "api_key"), True, 1, 8),
    SecretRule("access", r"AKIA[A-Z0-9]+", ("AKIA",), least=16),
    SecretRule("hex", r"[0-9a-f]{32,}", ()),
]
#: Kinds of our own.
MORE_RULES = [
    SecretRule("private_key", r"-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----", ("-----BEGIN ",)),
    SecretRule("web_token", r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]{5,}\.eyJ[A-Za-z0-9_-]{5,}\.[A-Za-z0-9_-]+", ("eyJ",)),
    SecretRule("repo_token", r"(?<![A-Za-z0-9_])gh[pousr]_[A-Za-z0-9]{36,}", ("ghp_", "gho_", "ghu_", "ghs_", "ghr_")),
]
HEX = np.zeros(256, bool)
HEX[np.frombuffer(b"0123456789abcdef", np.uint8)] = True


@dataclass
class RuleSet:
    version: str
    rules: list[SecretRule] = field(default_factory=lambda: [*BASE_RULES, *MORE_RULES])

    def spans(self, text: str, long_hex: bool) -> list[dict]:
        """All spans of one text, by start, then in the order of the rules."""
        out, folded = [], None
        for rank, rule in enumerate(self.rules):
            if rule.hint:
                if rule.fold and folded is None:
                    folded = text.lower()
                if not any(h in (folded if rule.fold else text) for h in rule.hint):
                    continue
            elif rule.kind == "hex" and not long_hex:
                continue
            for m in re.finditer(rule.pattern, text):
                if len(m[rule.group]) >= rule.least:
                    out.append((m.start(), rank, m.end(), rule.kind))
        return [dict(zip(("start", "rank", "stop", "kind"), x, strict=True)) for x in sorted(out)]


class BlobLedger:
    """Findings by blob and rule version, as Parquet that only grows."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path, self.schema = spark, path, f"blob binary, spans {SPANS}, version string"

    def exists(self) -> bool:
        jvm = self.spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(self.path)
        return at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(at)

    def findings(self, version: str) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path).where(F.col("version") == version).drop("version")

    def append(self, rows: DataFrame, version: str) -> None:
        rows.withColumn("version", F.lit(version)).write.mode("append").parquet(self.path)


def scan(df: DataFrame, ledger: BlobLedger, rules: RuleSet, key: str = "doc_id", text: str = "text", skip_limit: int = 1_000_000) -> DataFrame:
    """(key, blob, spans) for every row of ``df``; the ledger gains the blobs
    that it did not have. ``skip_limit``: most versions (a path and the 32 bytes
    of its blob) that are broadcast to be left out."""
    spark, folder = df.sparkSession, workspace(df.sparkSession)
    body = F.coalesce(F.col(text), F.lit(""))
    address = F.unhex(F.sha2(body, 256))
    paths = materialize(df.select(F.col(key).alias("path"), address.alias("blob")), folder, "paths")
    copies = materialize(paths.groupBy("blob").agg(F.min("path").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"), folder, "copies")
    skip = paths.join(copies.hint("merge"), "blob").where("not path <=> first").select("path", "blob")
    if ledger.exists():
        skip = skip.unionAll(paths.join(ledger.findings(rules.version).select("blob"), "blob", "left_semi").select("path", "blob"))
    skip = materialize(skip.distinct(), folder, "skip")
    rows = df.select(F.col(key).alias("path"), body.alias("text"), address.alias("blob"))
    n = skip.count()
    if n:
        same = rows["path"].eqNullSafe(skip["path"]) & (rows["blob"] == skip["blob"])
        rows = rows.join(F.broadcast(skip) if n <= skip_limit else skip.hint("merge"), same, "left_anti")

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text"):
            gaps = np.flatnonzero(~HEX[data])
            long = np.flatnonzero(np.diff(np.concatenate([[-1], gaps, [len(data)]])) > 32)
            begin = np.concatenate([[-1], gaps])[long] + 1
            has = np.zeros(len(batch), bool)
            # a run may cross rows here; the pattern decides within each row
            for a, b in zip(np.searchsorted(offsets, begin, "right") - 1, np.searchsorted(offsets, np.concatenate([gaps, [len(data)]])[long], "left"), strict=True):
                has[max(a, 0) : b] = True
            found = [rules.spans(t, h) for t, h in zip(batch.column(1).to_pylist(), has.tolist(), strict=True)]
            kind = pa.list_(pa.struct([("start", pa.int32()), ("rank", pa.int32()), ("stop", pa.int32()), ("kind", pa.string())]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, kind)], ["blob", "spans"])

    # rows that repeat a version bring its blob twice
    fresh = rows.select("blob", "text").mapInArrow(find, f"blob binary, spans {SPANS}")
    ledger.append(fresh.dropDuplicates(["blob"]), rules.version)
    hits = ledger.findings(rules.version).where("size(spans) > 0")
    return paths.join(hits.hint("merge"), "blob", "left").select(F.col("path").alias(key), "blob", F.coalesce("spans", F.expr(f"cast(array() as {SPANS})")).alias("spans"))


def new_ledger(spark: SparkSession) -> BlobLedger:
    return BlobLedger(spark, f"{workspace(spark)}/ledger")


def span_text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")


def secrets_digest(df: DataFrame, ledger: BlobLedger | None = None, rules: RuleSet | None = None, key: str = "doc_id") -> DataFrame:
    """The contract's columns, from the operator's spans."""
    found = scan(df, ledger or new_ledger(df.sparkSession), rules or RuleSet("r1"), key)
    count = lambda name: F.size(F.filter("spans", lambda s: s["kind"] == name)).cast("long").alias(f"n_{name}")
    base = F.filter("spans", lambda s: s["rank"] < len(BASE_RULES))
    return found.select(key, *[count(r.kind) for r in BASE_RULES], F.sha2(span_text(base), 256).alias("base_sha256"), span_text(F.col("spans")).alias("spans"))


def redact(df: DataFrame, found: DataFrame, text: str = "text", broadcast_limit: int = 200_000) -> DataFrame:
    """``df`` with the spans of ``found`` replaced by ``[secret]`` in its texts.
    Spans belong to a blob, so each row gets those of its own text, whatever its
    id, and stays one row."""
    hits = found.where("size(spans) > 0").select(F.col("blob").alias("_blob"), F.col("spans").alias("_spans")).dropDuplicates(["_blob"])
    hits = materialize(hits, workspace(df.sparkSession), "hits")
    hits = F.broadcast(hits) if hits.count() <= broadcast_limit else hits
    body = F.col(text)
    step = lambda acc, s: F.when(s["start"] >= acc["at"], F.struct(s["stop"].alias("at"), F.concat(acc["out"], F.substring(body, acc["at"] + 1, s["start"] - acc["at"]), F.lit("[secret]")).alias("out"))).otherwise(F.struct(F.greatest(acc["at"], s["stop"]).alias("at"), acc["out"].alias("out")))
    done = F.aggregate("_spans", F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substring(body, acc["at"] + 1, F.length(body))))
    joined = df.join(hits, F.unhex(F.sha2(body, 256)) == hits["_blob"], "left")
    return joined.withColumn(text, F.when(F.col("_spans").isNull(), body).otherwise(done)).select(*df.columns)
