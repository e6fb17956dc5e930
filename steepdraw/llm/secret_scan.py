"""Incremental secret scan over a ledger of blobs, in DataFrame functions only.

Each version of a text is addressed by the SHA-256 of its bytes.  A ledger holds one row for each
(blob, rule version) ever scanned.  A scan reads the text of unseen pairs only, once per distinct
blob however many paths hold it, appends the findings to the ledger and joins them back to all
paths.  Hot blobs are reduced to one row by map-side aggregation before any text moves, and the
join back has one ledger row per blob, so its other side may be split at will.

Spans are in code points, end exclusive.  Positions come from the lengths of the matches and of
the gaps between them.  Null text counts as empty and finds nothing.  Rows that repeat an id or a
text each get their findings.  Columns other than the id and the text are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise


@dataclass(frozen=True)
class Rule:
    """One kind of secret: a pattern, and a group that must have at least `least` characters."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0


#: The base kinds, in the order that breaks ties.  A run of n or more characters is
#: found by the same leftmost search as a run of any length that is dropped when shorter.
BASE = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    Rule("access", r"AKIA[A-Z0-9]{12,}"),
    Rule("hex", r"[0-9a-f]{32,}"),
)
#: Further published token formats.
EXTRA = (
    Rule("pem", r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----"),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
)
RULES = BASE + EXTRA
RULE_VERSION = "1"
_SPAN = "array<struct<start:bigint,rank:int,kind:string,end:bigint>>"


def spans_of(text: Column, rule: Rule, rank: int) -> Column:
    """Spans of one rule: leftmost matches that don't overlap, short ones dropped."""
    found = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    sized = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group))
    gaps = F.split(text, rule.pattern, -1)
    lengths = F.zip_with(
        F.zip_with(F.slice(gaps, 1, F.size(found)), found, lambda g, m: F.struct(F.length(g).alias("gap"), F.length(m).alias("len"))),
        F.transform(sized, F.length),
        lambda a, s: F.struct(a["gap"].alias("gap"), a["len"].alias("len"), s.alias("size")),
    )
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast(_SPAN).alias("spans"))
    walked = F.aggregate(
        lengths,
        start,
        lambda acc, x: F.struct(
            (acc["at"] + x["gap"] + x["len"]).cast("bigint").alias("at"),
            F.when(
                x["size"] >= rule.least,
                F.concat(
                    acc["spans"],
                    F.array(F.struct((acc["at"] + x["gap"]).cast("bigint").alias("start"), F.lit(rank).alias("rank"), F.lit(rule.kind).alias("kind"), (acc["at"] + x["gap"] + x["len"]).cast("bigint").alias("end"))).cast(_SPAN),
                ),
            )
            .otherwise(acc["spans"])
            .alias("spans"),
        ),
    )["spans"]
    return F.when(text.rlike(rule.pattern), walked).otherwise(F.array().cast(_SPAN))


def all_spans(text: Column, rules: tuple[Rule, ...]) -> Column:
    return F.array_sort(F.concat(*[spans_of(text, r, i) for i, r in enumerate(rules)]))


def joined(spans: Column) -> Column:
    """kind:start:end of each span, joined by commas."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan_unseen(versions: DataFrame, ledger: DataFrame | None = None, rules: tuple[Rule, ...] = RULES, rule_version: str = RULE_VERSION, key: str = "doc_id") -> DataFrame:
    """Ledger rows (blob, rule_version, spans) of the pairs that `ledger` lacks."""
    addressed = versions.select(F.col(key).alias("path"), F.coalesce("text", F.lit("")).alias("text")).withColumn("blob", F.sha2(F.encode("text", "UTF-8"), 256))
    first = addressed.groupBy("blob").agg(F.min("path").alias("first_path"))
    if ledger is not None:
        first = first.join(ledger.where(F.col("rule_version") == rule_version).select("blob"), "blob", "left_anti")
    first = first.withColumnRenamed("blob", "first_blob")
    fresh = addressed.join(first, (F.col("blob") == F.col("first_blob")) & F.col("path").eqNullSafe(F.col("first_path")))
    found = fresh.select("blob", F.lit(rule_version).alias("rule_version"), all_spans(F.col("text"), rules).alias("spans"))
    return found.groupBy("blob", "rule_version").agg(F.first("spans").alias("spans"))  # rows may repeat a path and its text


def join_back(versions: DataFrame, ledger: DataFrame, rule_version: str = RULE_VERSION, key: str = "doc_id") -> DataFrame:
    """Spans of every path, from the ledger."""
    addressed = versions.select(F.col(key), F.sha2(F.encode(F.coalesce("text", F.lit("")), "UTF-8"), 256).alias("blob"))
    known = ledger.where((F.col("rule_version") == rule_version) & (F.size("spans") > 0)).select("blob", "spans").dropDuplicates(["blob"])  # an append that was retried repeats its rows
    return addressed.join(known, "blob", "left").select(key, "blob", F.coalesce("spans", F.array().cast(_SPAN)).alias("spans"))


def scan(versions: DataFrame, ledger_path: str | None = None, rules: tuple[Rule, ...] = RULES, rule_version: str = RULE_VERSION, key: str = "doc_id") -> DataFrame:
    """key, blob and spans of every version; unseen blobs are added to the ledger at `ledger_path`.

    Without a path the ledger starts empty in the shared scratch folder.
    """
    spark = versions.sparkSession
    if ledger_path is None:
        return join_back(versions, materialise(scan_unseen(versions, None, rules, rule_version, key), "ledger"), rule_version, key)
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(ledger_path)
    there = hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop)
    scan_unseen(versions, spark.read.parquet(ledger_path) if there else None, rules, rule_version, key).write.mode("append").parquet(ledger_path)
    return join_back(versions, spark.read.parquet(ledger_path), rule_version, key)


def oracle_sql(rules: tuple[Rule, ...] = RULES) -> str:
    """The driver query in DuckDB's SQL: matches and gaps by the same patterns, without a ledger."""
    kinds = []
    for i, r in enumerate(rules):
        pattern = r.pattern.replace("'", "''")
        kinds.append(
            f"SELECT doc_id, {i} AS rank, '{r.kind}' AS kind, k, len(whole[k]) AS own, len(sized[k]) AS size, len(gaps[k]) AS gap FROM ("
            f"SELECT doc_id, whole, sized, gaps, unnest(range(1, len(whole) + 1)) AS k FROM ("
            f"SELECT doc_id, regexp_extract_all(text, '{pattern}', 0) AS whole, regexp_extract_all(text, '{pattern}', {r.group}) AS sized, regexp_split_to_array(text, '{pattern}') AS gaps "
            f"FROM documents WHERE regexp_matches(text, '{pattern}')))"
        )
    least = " ".join(f"WHEN {i} THEN {r.least}" for i, r in enumerate(rules))
    names = ", ".join(f"'{r.kind}'" for r in BASE)
    text = "string_agg(kind || ':' || (stop - own)::BIGINT || ':' || stop::BIGINT, ',' ORDER BY stop - own, rank)"
    counts = ", ".join(f"coalesce(n_{r.kind}, 0)::BIGINT AS n_{r.kind}" for r in BASE)
    sums = ", ".join(f"count(*) FILTER (WHERE kind = '{r.kind}') AS n_{r.kind}" for r in BASE)
    return f"""
WITH found AS ({" UNION ALL ".join(kinds)}
), placed AS (
  SELECT *, sum(gap + own) OVER (PARTITION BY doc_id, rank ORDER BY k) AS stop FROM found
), kept AS (
  SELECT * FROM placed WHERE size >= CASE rank {least} END
), joined AS (
  SELECT doc_id, {sums}, {text} FILTER (WHERE kind IN ({names})) AS base, {text} AS spans FROM kept GROUP BY doc_id
)
SELECT d.doc_id, {counts}, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans
FROM documents d LEFT JOIN joined j ON d.doc_id = j.doc_id
"""
