"""The experiments in full, one JSON line each: experiments.py SF_DIR [comparison|sensitivity|scalability ...]"""

from __future__ import annotations

import json
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))


def main(sf_dir: str, *what: str) -> None:
    from pyspark.sql import SparkSession

    from pairlabel.plans import experiments as P

    spark = SparkSession.builder.master("local[8]").config("spark.ui.enabled", "false").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", "16").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    tell = lambda name, df: [print(json.dumps({"experiment": name} | r.asDict()), flush=True) for r in df.collect()]
    if "comparison" in what:
        tell("comparison", P.comparison(spark, sf_dir, ("W1b", "W1h", "W1v", "W2s")))
    if "sensitivity" in what:
        for name, values in (("easy_ratio", (0.3, 0.4, 0.5)), ("m", (500, 1000, 2000)), ("k", (1, 5, 10)), ("interval_cap", (50, 100, 200))):
            tell(name, P.sensitivity(spark, sf_dir, name, values, ("W1b", "W1h", "W1v", "W2s")))
    if "scalability" in what:
        tell("scalability", P.scalability(spark, sf_dir))


if __name__ == "__main__":
    main(sys.argv[1], *(sys.argv[2:] or ("comparison", "sensitivity", "scalability")))
