"""Mixing sources to target weights by Pareto order sampling, in DataFrame expressions only.

Targets: sources in code-point order (null last) carry cyclic weights and share a budget of
words; a source stops at ``cap`` times its own words and the excess is shared again by weight.
The fixed point of that resharing is a water level: ``min(cap_i, level * w_i)``.

Copies: each document of a source is due ``target / source_size`` copies. The whole part is
certain; the rest is an inclusion probability, and documents are ranked by their random odds
divided by their inclusion odds. The lowest ranks are taken until the words still missing are
filled, to the nearest document.

No source is ever sorted in one task: ranks are cut into 1024 intervals, only the interval that
holds the threshold is cut again, and only the interval of that which holds it is sorted: about a
millionth of a source.

Defined results: a null text is empty (size 0, taken 0); a null source is a source of its own,
last; an empty table gives an empty result. The random number of a row comes from its id and a digest of its text
(and null ids are spelled as nothing), so rows that repeat an id, or have none, are still told apart; ties of rank go by
id, digest and importance, and rows equal in all of these are interchangeable: the result, as a set of rows, is
the same under any order of the input. Columns other than id, text and source are ignored, or handed on by ``mix_documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vpcoreset.llm.common import WORD, stored

CUTS = 1024


def source_targets(sizes: DataFrame, share: float, weights: tuple[float, ...], cap: float) -> DataFrame:
    """(source_key, source_size, target) from rows of (source_key, size); one row a source."""
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    per = sizes.groupBy("source_key").agg(F.sum("size").alias("source_size"))
    per = per.withColumn("rank", F.row_number().over(W.orderBy("source_key")))
    per = per.withColumn("w", F.element_at(cycle, (F.pmod(F.col("rank") - 1, F.lit(len(weights))) + 1).cast("int")))
    per = per.withColumn("most", F.lit(float(cap)) * F.col("source_size"))
    everything = W.partitionBy(F.lit(1))
    fill = W.partitionBy(F.lit(1)).orderBy(F.col("most") / F.col("w"), "rank")
    per = per.select(
        "*",
        (F.lit(float(share)) * F.sum("source_size").over(everything)).alias("budget"),
        (F.sum("most").over(fill) - F.col("most")).alias("most_before"),
        (F.sum("w").over(everything) - F.sum("w").over(fill) + F.col("w")).alias("w_from"),
    )
    per = per.withColumn("full", (F.col("budget") - F.col("most_before")) * F.col("w") >= F.col("most") * F.col("w_from"))
    spent = F.sum(F.when(F.col("full"), F.col("most")).otherwise(0.0)).over(everything)
    open_w = F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("w"))).over(everything)
    level = F.try_divide(F.col("budget") - spent, open_w)
    return per.select("source_key", "source_size", F.when(F.col("full"), F.col("most")).otherwise(level * F.col("w")).alias("target"))


def _threshold(sums: DataFrame, cut: str, wanted: str, before: str) -> DataFrame:
    """The interval in which the running words pass what is wanted; sums: (__source, cut, words, wanted)."""
    run = F.sum("words").over(W.partitionBy("__source").orderBy(cut))
    held = sums.withColumn("upto", run).where((F.col("upto") > F.col(wanted)) & (F.col("upto") - F.col("words") <= F.col(wanted)))
    return held.select("__source", cut, (F.col("upto") - F.col("words")).alias(before))


def _sized(docs: DataFrame, id_col: str, text_col: str, source_col: str, key: str, importance: str | None) -> list:
    """Columns that the ranking reads: id, source, its key, size, digest of the text, random number and importance."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    source_key = F.when(F.col(source_col).isNull(), F.lit("1")).otherwise(F.concat(F.lit("0"), F.col(source_col)))
    digest = F.md5(text)
    told = F.concat(F.lit(f"{key}:"), F.coalesce(F.col(id_col).cast("string"), F.lit("")), F.lit(":"), digest)
    u = (F.conv(F.substring(F.md5(told), 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(1 << 52))
    g = F.coalesce(F.greatest(F.col(importance).cast("double"), F.lit(0.0)), F.lit(1.0)) if importance else F.lit(1.0)
    return [
        F.col(id_col).alias("__id"), source_key.alias("__source"), F.regexp_count(text, F.lit(WORD)).cast("long").alias("__size"),
        digest.alias("__digest"), u.alias("__u"), g.alias("__g"),
    ]


def _placed(rows: DataFrame, per: DataFrame) -> DataFrame:
    """Rows with their due copies, their place in the order of ranks (0 to 1) and its two intervals."""
    p = F.least(F.lit(1.0), F.col("__part") * F.coalesce(F.try_divide(F.col("__g"), F.col("__mean")), F.lit(1.0)))
    odds_u, odds_p = F.col("__u") / (1 - F.col("__u")), F.try_divide(F.col("__p"), 1 - F.col("__p"))
    rank = F.when(F.col("__p") >= 1, 0.0).otherwise(F.try_divide(odds_u, odds_p))
    at = F.when(F.col("__p") <= 0, 1.0).otherwise(rank / (1 + rank))
    out = rows.join(per, "__source").withColumn("__p", p).withColumn("__at", at)
    out = out.withColumn("__cut1", F.least(F.floor(F.col("__at") * CUTS), F.lit(CUTS - 1)))
    return out.withColumn("__cut2", F.least(F.floor((F.col("__at") * CUTS - F.col("__cut1")) * CUTS), F.lit(CUTS - 1)))


def _mixed(docs: DataFrame, id_col: str, text_col: str, source_col: str, share: float, weights: tuple[float, ...], cap: float, key: str, importance: str | None, whole: bool) -> DataFrame:
    """Rows with ``__size``, ``__total``, ``__target`` and ``__copies``; with ``whole`` the documents themselves, else narrow ones."""
    narrow = stored(docs.select(F.col(source_col).alias("source"), *_sized(docs, id_col, text_col, source_col, key, importance)), "mix-sizes")
    sizes = narrow.select(F.col("__source").alias("source_key"), F.col("__size").alias("size"))
    per = source_targets(sizes, share, weights, cap).toDF("__source", "__total", "__target")
    mean = narrow.groupBy("__source").agg(F.try_divide(F.sum(F.col("__g") * F.col("__size")), F.sum("__size")).alias("__mean"))
    rate = F.coalesce(F.try_divide(F.col("__target"), F.col("__total")), F.lit(0.0))
    per = per.join(mean, "__source").withColumn("__whole", F.floor(rate)).withColumn("__part", rate - F.col("__whole"))
    per = stored(per.withColumn("__wanted", F.col("__target") - F.col("__whole") * F.col("__total")), "mix-sources")

    # A source of which nothing more is wanted has no threshold: none of its rows is sorted.
    ranked = _placed(narrow, per)
    first = ranked.where(F.col("__wanted") > 0).groupBy("__source", "__cut1").agg(F.sum("__size").alias("words"), F.max("__wanted").alias("wanted"))
    edge1 = _threshold(first, "__cut1", "wanted", "__before1").withColumnRenamed("__cut1", "__edge1")
    second = ranked.join(edge1, "__source").where(F.col("__cut1") == F.col("__edge1"))
    second = second.groupBy("__source", "__cut2").agg(F.sum("__size").alias("words"), F.max(F.col("__wanted") - F.col("__before1")).alias("left"))
    edge2 = _threshold(second, "__cut2", "left", "__before2").withColumnRenamed("__cut2", "__edge2")
    edges = stored(per.join(edge1, "__source", "left").join(edge2, "__source", "left"), "mix-edges")

    rows = docs.select("*", *_sized(docs, id_col, text_col, source_col, key, importance)) if whole else narrow
    ranked = _placed(rows, edges)
    # Without an edge all words are wanted, or none of them are.
    below = F.when(F.col("__edge1").isNull(), F.col("__wanted") > 0).otherwise(
        (F.col("__cut1") < F.col("__edge1")) | ((F.col("__cut1") == F.col("__edge1")) & (F.col("__cut2") < F.col("__edge2"))))
    inside = F.coalesce((F.col("__cut1") == F.col("__edge1")) & (F.col("__cut2") == F.col("__edge2")), F.lit(False))
    order = W.partitionBy("__source").orderBy("__at", "__id", "__digest", "__g").rowsBetween(W.unboundedPreceding, 0)
    sure = ranked.where(~inside).withColumn("__extra", F.coalesce(below, F.lit(False)).cast("long"))
    close = ranked.where(inside).withColumn("__middle", F.col("__before1") + F.col("__before2") + F.sum("__size").over(order) - F.col("__size") / 2)
    close = close.withColumn("__extra", (F.col("__middle") <= F.col("__wanted")).cast("long")).drop("__middle")
    return sure.unionByName(close).withColumn("__copies", (F.col("__whole") + F.col("__extra")).cast("long"))


def pareto_mix(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", share: float = 1.5,
    weights: tuple[float, ...] = (3, 1, 2), cap: float = 2.0, key: str = "mix", importance: str | None = None,
) -> DataFrame:
    """(id, source, size, source_size, target, copies, taken) of every row of docs.

    ``importance`` names a non-negative column that makes inclusion unequal inside a source; null
    means 1. Without it inclusion differs between sources only.
    """
    out = _mixed(docs, id_col, text_col, source_col, share, weights, cap, key, importance, False)
    return out.select(
        F.col("__id").alias(id_col), F.col("source").alias(source_col), F.col("__size").alias("size"), F.col("__total").alias("source_size"),
        F.col("__target").alias("target"), F.col("__copies").alias("copies"), (F.col("__copies") * F.col("__size")).alias("taken"),
    )


def mix_documents(
    docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", share: float = 1.5,
    weights: tuple[float, ...] = (3, 1, 2), cap: float = 2.0, key: str = "mix", importance: str | None = None,
) -> DataFrame:
    """docs, all columns, with size, source_size, target, copies and taken (in the place of columns of these names).

    Texts are read a second time and not shuffled: a row decides by the stored thresholds of its source.
    """
    added = ("size", "source_size", "target", "copies", "taken")
    docs = docs.drop(*[c for c in added if c in docs.columns])
    out = _mixed(docs, id_col, text_col, source_col, share, weights, cap, key, importance, True)
    return out.select(
        *docs.columns, F.col("__size").alias("size"), F.col("__total").alias("source_size"), F.col("__target").alias("target"),
        F.col("__copies").alias("copies"), (F.col("__copies") * F.col("__size")).alias("taken"),
    )


def mix_sql(importance: str | None = None, joined: str = "") -> str:
    """The same in one pass of SQL windows, for checking: it sorts each source whole. ``joined`` may bring the importance."""
    return f"""
WITH sized AS (
  SELECT doc_id, source, CASE WHEN source IS NULL THEN '1' ELSE '0' || source END AS source_key, md5(coalesce(text, '')) AS digest,
         CAST(len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS BIGINT) AS size,
         (CAST('0x' || substr(md5('mix:' || coalesce(CAST(doc_id AS VARCHAR), '') || ':' || md5(coalesce(text, ''))), 1, 13) AS BIGINT) + 0.5::DOUBLE) / 4503599627370496::DOUBLE AS u,
         coalesce(greatest(({importance or '1'})::DOUBLE, 0), 1) AS g
  FROM documents{joined}),
per AS (SELECT source_key, CAST(sum(size) AS BIGINT) AS source_size, sum(g * size) / nullif(sum(size), 0) AS mean_g FROM sized GROUP BY 1),
ranked AS (SELECT *, CASE (row_number() OVER (ORDER BY source_key) - 1) % 3 WHEN 0 THEN 3 WHEN 1 THEN 1 ELSE 2 END::DOUBLE AS w FROM per),
capped AS (SELECT *, 2.0::DOUBLE * source_size AS most FROM ranked),
filled AS (
  SELECT *, 1.5::DOUBLE * sum(source_size) OVER () AS budget,
         sum(most) OVER (ORDER BY most / w, source_key) - most AS most_before,
         sum(w) OVER () - sum(w) OVER (ORDER BY most / w, source_key) + w AS w_from FROM capped),
marked AS (SELECT *, (budget - most_before) * w >= most * w_from AS is_full FROM filled),
aimed AS (
  SELECT source_key, source_size, mean_g, CASE WHEN is_full THEN most ELSE
         (budget - sum(CASE WHEN is_full THEN most ELSE 0 END) OVER ()) / sum(CASE WHEN is_full THEN 0 ELSE w END) OVER () * w END AS target
  FROM marked),
due AS (
  SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END AS rate FROM aimed),
placed AS (
  SELECT doc_id, source, size, digest, source_key, source_size, target, g, floor(rate) AS whole, target - floor(rate) * source_size AS wanted,
         least(1.0::DOUBLE, (rate - floor(rate)) * coalesce(g / mean_g, 1)) AS p, u FROM sized JOIN due USING (source_key)),
odds AS (SELECT *, CASE WHEN p >= 1 THEN 0.0 WHEN p > 0 THEN ((u / (1 - u)) / (p / (1 - p))) END AS r FROM placed),
cut AS (
  SELECT *, sum(size) OVER (PARTITION BY source_key ORDER BY CASE WHEN p <= 0 THEN 1.0 ELSE r / (1 + r) END, doc_id NULLS FIRST, digest, g
         ROWS UNBOUNDED PRECEDING) - size / 2.0 AS middle FROM odds)
SELECT doc_id, source, size, source_size, target,
       CAST(whole + CASE WHEN wanted > 0 AND middle <= wanted THEN 1 ELSE 0 END AS BIGINT) AS copies,
       CAST((whole + CASE WHEN wanted > 0 AND middle <= wanted THEN 1 ELSE 0 END) * size AS BIGINT) AS taken FROM cut
"""
