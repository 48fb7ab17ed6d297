"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from seqnorm.session import local_session

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
    spark = local_session(cpus, cpus, "bench")
    spark.sparkContext.setLogLevel("ERROR")
    from seqnorm import catalog, workloads
    from seqnorm.baselines import detectors
    from seqnorm.operators import detect, metrics, model
    from seqnorm.operators.living import Params

    n = workloads._n(spark, sf_dir)
    points = catalog._drifting(spark, sf_dir).cache()
    points.count()
    ours = Params()
    runs = {
        "online": lambda: detect.scores(detect.online(points, ours)),
        "offline": lambda: detect.scores(detect.offline(points, ours)),
        "online_blocks": lambda: detect.in_blocks(points, model.fit(points, ours), ours, 16384),
        "static_weighted": lambda: detectors.static_weighted(points, 50),
        "batch_shape": lambda: detectors.batch_shape(points, 50),
        "discord": lambda: detectors.backward_discord(points, 50),
        "transformer": lambda: detectors.transformer(points, 50),
    }
    queries, accuracy = {}, {}
    for name, make in runs.items():
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        queries[name] = round(time.perf_counter() - began, 3)
    for name in ("online", "offline"):
        truth = points.select("series_id", "pos", "y_true")
        found = runs[name]().join(truth.withColumnRenamed("pos", "start"), ["series_id", "start"])
        accuracy[name] = round(metrics.auc(found, "score", "y_true").first()["auc"], 4)
    for name in ("windows_hourly", "segments_daily", "ca_repair_daily", "score_trailing_min", "auc_carrier", "op_asof_nearest", "op_cube"):
        began = time.perf_counter()
        catalog.queries()[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        queries[name] = round(time.perf_counter() - began, 3)
    total = round(sum(queries.values()), 3)
    print(json.dumps({"metric": "headline queries", "value": total, "unit": "sec", "queries": queries, "sf": os.path.basename(sf_dir), "points": n, "points_per_sec_online": round(n / queries["online"]), "auc": accuracy, "cpus": cpus}))


if __name__ == "__main__":
    main()
