"""Secret scans with an incremental blob ledger, in DataFrame expressions only.

Every version of a text is addressed by its SHA-256. A ledger holds what each rule version found
in each blob; a scan reads the rules over those blobs alone that have no entry for the rule
version, appends their entries, and joins the ledger back to every path (id) that carries the blob.
Entries are appended after the scan of all unseen blobs; an interrupted scan leaves none.

Positions count code points, end exclusive. Three base rules (assign, access, hex) are matched
leftmost and without overlap, each by itself, and matches that are too short are dropped; four
more rules add spans of further formats.

Defined results: a null text is the empty blob, without findings; rows that repeat a text share one
blob and one scan; rows that repeat an id are reported each; columns other than id and text are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vpcoreset.llm.common import scratch

# The rules (kind, pattern, group that is measured, least length, quick test).
RULES = (
    ("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12, ("rlike", r"(?i:passw|secret|token|api_?key)")),
    ("access", r"AKIA[A-Z0-9]+", 0, 18, ("contains", "AKIA")),
    ("hex", r"[0-9a-f]+", 0, 16, ("rlike", r"[0-9a-f]{16}")),
    ("github", r"gh[opsu]_[A-Za-z0-9]+", 0, 36, ("rlike", r"gh[opsu]_")),
    ("slack", r"xox[abprs]-[A-Za-z0-9-]+", 0, 20, ("contains", "xox")),
    ("jwt", r"eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 0, 40, ("contains", "eyJ")),
    ("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----", 0, 20, ("contains", "PRIVATE KEY-----")),
)
BASE = ("assign", "access", "hex")
RULE_VERSION = "rules-1"
SPAN = "struct<start:int,kind_no:int,kind:string,end:int>"


def _spans(text: Column, no: int) -> Column:
    """Spans of one rule: the gaps between matches and the matches, laid end to end, give the positions."""
    kind, pattern, group, least, (test, word) = RULES[no]
    p = F.lit(pattern)
    parts = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, p, F.lit(0)).alias("hit"), F.regexp_extract_all(text, p, F.lit(group)).alias("part"))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPAN}>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        a = acc["at"] + F.length(x["gap"])
        b = a + F.coalesce(F.length(x["hit"]), F.lit(0))
        one = F.array(F.struct(a.alias("start"), F.lit(no).alias("kind_no"), F.lit(kind).alias("kind"), b.alias("end")))
        return F.struct(b.alias("at"), F.when(F.length(x["part"]) >= least, F.concat(acc["out"], one)).otherwise(acc["out"]).alias("out"))

    found = F.aggregate(parts, start, step, lambda acc: acc["out"])
    return F.when(text.contains(word) if test == "contains" else text.rlike(word), found).otherwise(F.array().cast(f"array<{SPAN}>"))


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan_blobs(blobs: DataFrame) -> DataFrame:
    """(blob, rule_version, n_assign, n_access, n_hex, base_sha256, spans) of rows of (blob, text)."""
    text = F.col("text")
    rows = blobs.select("blob", *[_spans(text, no).alias(RULES[no][0]) for no in range(len(RULES))])
    base, every = (F.array_sort(F.concat(*[F.col(k) for k in kinds])) for kinds in (BASE, [r[0] for r in RULES]))
    return rows.select(
        "blob", F.lit(RULE_VERSION).alias("rule_version"), *[F.size(k).cast("long").alias(f"n_{k}") for k in BASE],
        F.sha2(_joined(base), 256).alias("base_sha256"), _joined(every).alias("spans"),
    )


LEDGER = "blob string, rule_version string, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string"


def scan_secrets(docs: DataFrame, ledger: str | None = None, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Findings of every row. ``ledger``: a shared folder that is kept between scans; None starts an empty one."""
    spark = docs.sparkSession
    path = ledger or scratch(spark, "blob-ledger")
    text = F.coalesce(F.col(text_col), F.lit(""))
    key = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    paths = docs.select(F.col(id_col).alias("id"), key.alias("path"), F.sha2(text, 256).alias("blob"))
    unseen = paths.groupBy("blob").agg(F.min("path").alias("path"))
    if ledger and _exists(spark, path):
        known = spark.read.schema(LEDGER).parquet(path).where(F.col("rule_version") == RULE_VERSION).select("blob")
        unseen = unseen.join(known, "blob", "left_anti")
    # The blob's text is read at its first path; the hash guards against ids that repeat with other texts.
    texts = docs.select(key.alias("path"), F.sha2(text, 256).alias("blob"), text.alias("text"))
    fresh = texts.join(unseen, ["path", "blob"], "left_semi")
    scan_blobs(fresh).write.mode("append").parquet(path)
    # Rows that repeat both id and text bring equal entries; one of them counts.
    entries = spark.read.schema(LEDGER).parquet(path).where(F.col("rule_version") == RULE_VERSION).drop("rule_version").distinct()
    return paths.join(entries, "blob").select(F.col("id").alias(id_col), "n_assign", "n_access", "n_hex", "base_sha256", "spans", "blob")


def secrets_sql() -> str:
    """DuckDB twin: runs of hex digits and keys are matched at full length at once, which finds the same spans."""
    full = {"access": r"AKIA[A-Z0-9]{14,}", "hex": r"[0-9a-f]{16,}"}
    parts = []
    for no, (kind, pattern, group, least, _) in enumerate(RULES):
        p = full.get(kind, pattern).replace("'", "''")
        parts.append(f"""SELECT doc_id, {no} AS no, '{kind}' AS kind, x.s AS s, x.s + length(x.h) AS e FROM (
  SELECT doc_id, unnest(list_transform(range(1, len(m) + 1), lambda i: struct_pack(
    s := list_sum(list_transform(g[1:i], lambda y: length(y))) + coalesce(list_sum(list_transform(m[1:i-1], lambda y: length(y))), 0), h := m[i], p := p[i]))) AS x
  FROM (SELECT doc_id, regexp_extract_all(t, '{p}') AS m, string_split_regex(t, '{p}') AS g, regexp_extract_all(t, '{p}', {group}) AS p FROM d WHERE regexp_matches(t, '{p}')))
  WHERE length(x.p) >= {least}""")
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
hit AS ({" UNION ALL ".join(parts)}),
told AS (
  SELECT doc_id, count(*) FILTER (WHERE no = 0) AS n_assign, count(*) FILTER (WHERE no = 1) AS n_access, count(*) FILTER (WHERE no = 2) AS n_hex,
         string_agg(kind || ':' || CAST(s AS BIGINT) || ':' || CAST(e AS BIGINT), ',' ORDER BY s, no) FILTER (WHERE no < 3) AS base,
         string_agg(kind || ':' || CAST(s AS BIGINT) || ':' || CAST(e AS BIGINT), ',' ORDER BY s, no) AS spans FROM hit GROUP BY 1)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
       sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, sha256(t) AS blob FROM d LEFT JOIN told USING (doc_id)
"""


def _exists(spark, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)
