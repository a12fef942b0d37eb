"""Prints the experiment tables: ``python tools/experiments.py SF_DIR``."""

import sys
import time
from pathlib import Path

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))
from veil.plans import experiments as X  # noqa: E402
from veil.plans import measure as M  # noqa: E402
from veil.plans import workloads as W  # noqa: E402
from veil.plans.budget import Budget  # noqa: E402


def show(title: str, df, t0: float) -> None:
    rows = df.collect()
    print(f"\n## {title} ({time.time() - t0:.1f} s)")
    print(" | ".join(df.columns))
    for r in rows:
        print(" | ".join(f"{v:.6g}" if isinstance(v, float) else str(v) for v in r))


def main(sf: str) -> None:
    s = SparkSession.builder.master("local[8]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    ts, epss = (1, 2, 4, 8, 16), (0.1, 0.4, 1.6)
    for name, p, bins in (("location", W.location(s, sf, 16), 64), ("product", W.product(s, sf, 16), 16)):
        t = time.time()
        log = X.cost_grid(p, bins, ts, epss, (1e-5,), 10).cache()
        ratio = log.groupBy("t", "eps").agg(F.first("n").alias("n"), F.avg(F.col("cost") / F.col("all_pairs")).alias("padded_over_all_pairs"), F.stddev_samp(F.col("cost") / F.col("all_pairs")).alias("sd"))
        show(f"cost against size, {name}", ratio.orderBy("eps", "t"), t)
        show(f"slope, {name}", M.loglog_slope(log, ["eps"]).orderBy("eps"), t)
        plain = log.withColumn("cost", F.col("all_pairs")).withColumn("m", F.lit("all pairs"))
        show(f"slope of all pairs, {name}", M.loglog_slope(plain, ["m"]), t)
    for name, p in (("location", W.location(s, sf)), ("skewed product", W.product(s, sf, 1, True))):
        t = time.time()
        show(f"optimisations, {name}, t=1", X.variants(p, (0.1, 1.6)), t)
    t = time.time()
    show("trade-off by eps, location", X.tradeoff(W.location(s, sf), [Budget(e, 1e-5) for e in epss]), t)
    t = time.time()
    show("trade-off by delta, location", X.tradeoff(W.location(s, sf), [Budget(1.6, d) for d in (1e-9, 1e-7, 1e-5)]).filter("percent in (0, 10)"), t)


if __name__ == "__main__":
    main(sys.argv[1])
