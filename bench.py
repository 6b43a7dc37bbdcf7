"""Headline queries on $BENCH_SF_DIR with $BENCH_CPUS cores; prints one JSON line."""

from __future__ import annotations

import json
import os
import platform
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ["PYTHONPATH"] = os.pathsep.join([sys.path[0], os.environ.get("PYTHONPATH", "")])
os.environ.setdefault("OMP_NUM_THREADS", "1")

from farspan.operators import baselines, profiles, score, select, windows  # noqa: E402
from farspan.sources import tables  # noqa: E402

L, K = 512, 128


def main() -> None:
    cpus, sf = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4)), os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(cpus * 2))
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name: str, df):
        began = time.time()
        rows = df.select(F.count("*"), F.sum(F.hash(*[c for c, t in df.dtypes if not t.startswith("array")]).cast("long"))).first()
        took[name] = round(time.time() - began, 3)
        return rows[0]

    docs = tables.read_corpus(spark, sf)
    timed("warm_up", docs)
    toks = windows.tokenize(windows.spread(windows.long_only(docs, L)))
    timed("window_spans", windows.spans(toks, L))
    cut = windows.cut(toks, L).persist()
    count = timed("cut_windows", cut)
    raw = {}
    for name in ("hexdot", "small", "large"):
        raw[name] = score.score_windows(cut, profiles.named(name), K).persist()
        timed(f"score_{name}", raw[name])
    lds = score.combine(score.standardize(raw["hexdot"])).persist()
    timed("standardize_combine", lds)
    unit = select.unit_tokens(count, L)
    timed("select_top_budget", select.top_by_budget(lds, 5 * unit, L))
    timed("select_by_threshold", select.top_by_threshold(lds, 5 * unit, L))
    timed("select_ladder", select.ladder(lds, L))
    timed("select_random", select.random_by_budget(cut.drop("toks"), 5 * unit, L))
    timed("segment_scores", baselines.segment_scores(cut, 64))
    timed("linguistic", baselines.linguistic(cut, 64))
    sampled = score.score_sampled(cut, profiles.HexDot(), K, 32)
    timed("score_sampled", sampled)
    sums = {n: r.agg(F.sum("cpu_ms"), F.sum("pair_ops")).first() for n, r in raw.items()}
    del took["warm_up"]
    print(
        json.dumps(
            {
                "metric": "headline queries, total wall time",
                "value": round(sum(took.values()), 3),
                "unit": "sec",
                "queries": took,
                "sf": sf,
                "L": L,
                "k": K,
                "windows": count,
                "windows_per_sec": {n: round(count / took[f"score_{n}"], 1) for n in raw},
                "pair_ops_per_cpu_sec": {n: round((s[1] or 0) / max(1e-9, s[0] / 1e3)) for n, s in sums.items()},
                "cpu_ratio_large_small": round(sums["large"][0] / max(1e-9, sums["small"][0]), 2),
                "cpus": cpus,
                "machine": platform.machine(),
            }
        )
    )
    spark.stop()


if __name__ == "__main__":
    main()
