"""Times the headline queries: prints one JSON line with seconds by query and what the experiments measured."""

from __future__ import annotations

import json
import os
import shutil
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")

HEADLINE = (
    "reg_scores_line", "reg_coreset_line", "reg_coreset_docs", "km_coreset_docs", "km_coreset_emb", "ridge_full_docs", "ridge_on_coreset", "ridge_on_uniform",
    "kmeans_full_emb", "kmeans_on_coreset", "column_split_kmeans_full", "column_split_on_coreset", "exp_reg_table", "exp_km_table", "exp_line_table", "st_tumbling_stats",
)


#: Comparison tables, whose ratios are reported.
TABLES = ("exp_reg_table", "exp_km_table", "exp_line_table")


def measures(done: dict) -> dict:
    """Cost ratios to the full solver and communication ratios, as in the comparison of the baselines."""
    out = {}
    for name in TABLES:
        rows = done[name]
        full = {r["method"].split("+", 1)[1]: r for r in rows if r["method"].startswith("full+")}
        for r in rows:
            kind, solver = r["method"].split("+", 1)
            if kind != "full":
                f = full[solver]
                out[f"{name}:{r['method']}@{r['size']}"] = {"cost_ratio": round(r["avg_cost"] / f["avg_cost"], 4), "units_saved": round(f["units"] / r["units"], 1)}
    return out


def main() -> None:
    from pyspark.sql import SparkSession

    base = tempfile.mkdtemp(prefix="bench-")
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.sql.warehouse.dir", f"{base}/warehouse").config("spark.checkpoint.dir", f"file://{base}/shared").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from vpcoreset import queries

    queries.QUERIES["u52_stream"](spark, SF).count()  # starts the session
    took, tables = {}, {}
    for name in HEADLINE:
        began = time.time()
        df = queries.QUERIES[name](spark, SF)
        if name in TABLES:
            tables[name] = df.collect()
        else:
            df.write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
    rows = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    found = measures(tables)
    spark.stop()
    shutil.rmtree(base, ignore_errors=True)
    print(json.dumps({
        "metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF,
        "score_rows_per_sec": round(3 * rows / took["reg_scores_line"]), "measures": found,
    }))


if __name__ == "__main__":
    main()
