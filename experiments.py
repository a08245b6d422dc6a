"""The four methods over frequency, length, sample and slots, each point on one prepared corpus; a JSON line a method and point.

BENCH_SF_DIR chooses the tables, BENCH_CPUS the cores; arguments choose workloads (tau sigma sample slots; all without any).
"""

import json
import os
import sys

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.01")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
TAUS, SIGMAS, PERCENTS, SLOTS = (5, 10, 20, 40, 100), (5, 10, 20), (25, 50, 75, 100), (1, 2, 4, 8)
#: Least frequency and greatest length where a workload doesn't vary them.
TAU, SIGMA = 10, 5


def session(cores: int) -> SparkSession:
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(2 * CPUS)).config("spark.driver.memory", "8g")
    builder = builder.config("spark.ui.showConsoleProgress", "false").config("spark.ui.retainedStages", "20000").config("spark.sql.session.timeZone", "UTC")
    found = builder.getOrCreate()
    found.sparkContext.setLogLevel("ERROR")
    return found


def points(workloads: list[str]) -> list[tuple[str, int, int, int, int]]:
    """(workload, tau, sigma, percent, cores)."""
    grid = {
        "tau": [(t, SIGMA, 100, CPUS) for t in TAUS],
        "sigma": [(TAU, s, 100, CPUS) for s in SIGMAS],
        "sample": [(TAU, SIGMA, p, CPUS) for p in PERCENTS],
        "slots": [(TAU, SIGMA, 50, c) for c in SLOTS],
    }
    return [(name, *x) for name in workloads or grid for x in grid[name]]


def main() -> None:
    from seqstat.functions import text
    from seqstat.operators.encode import prepare
    from seqstat.plans import measures
    from seqstat.sources import tables

    spark, now, warm = None, 0, False
    for workload, tau, sigma, percent, cores in points(sys.argv[1:]):
        if cores != now:
            if spark:
                spark.stop()
            spark, now, warm = session(cores), cores, False
        docs = tables.sample(tables.table(spark, SF_DIR, "documents"), percent)
        p = prepare(text.from_text(docs, "doc_id", F.col("text")), tau)
        if not warm:
            measures.compare(p, 100, 2)  # compiles code, starts workers
            warm = True
        found = measures.compare(p, tau, sigma)
        ratios = measures.speedup(found)
        for m in found:
            line = {"workload": workload, "tau": tau, "sigma": sigma, "percent": percent, "cores": cores, "method": m.method, "seconds": round(m.seconds, 2)}
            print(json.dumps(line | {"over_suffix": ratios[m.method], "records": m.records_shuffle, "bytes": m.bytes_shuffle, "rounds": m.rounds, "peak_task": m.peak_task, "rows": m.rows}), flush=True)
    if spark:
        spark.stop()


if __name__ == "__main__":
    main()
