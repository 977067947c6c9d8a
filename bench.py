"""Running times of the headline queries; prints one JSON line.

further entries time answering 1000 range queries and building an origin-destination matrix.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from privmatrix.operators.answer import answer
    from privmatrix.plans import experiments, matrices
    from privmatrix.sources import workload
    from privmatrix.sources.store import written

    times: dict[str, float] = {}

    def timed(name: str, run) -> None:
        start = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - start, 3)

    timed("warm_up", lambda: matrices.cells(spark, sf_dir, "price2")[0])
    for name in ("price2", "ship2", "partsupp2"):
        spec = matrices.spec(spark, sf_dir, name)
        for method in experiments.METHODS:
            timed(f"{method}_{name}", lambda: experiments.release(method, matrices.cells(spark, sf_dir, name)[0], spec, 0.1, "42"))  # noqa: B023
    timed("cells_od4", lambda: matrices.cells(spark, sf_dir, "od4")[0])
    table, spec = matrices.cells(spark, sf_dir, "price2")
    for method in ("entropy_grid", "even_tree"):
        boxes = written(experiments.release(method, table, spec, 0.1, "42"), "release")
        timed(f"answer_{method}", lambda: answer(boxes, workload.random_queries(spark, spec, 1000, "42"), 2))  # noqa: B023
    del times["warm_up"]
    print(json.dumps({"metric": "releases and answers, total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/"))}))
    sys.stdout.flush()
    spark.stop()


if __name__ == "__main__":
    main()
