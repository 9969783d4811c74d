"""Seconds of the three snapshot stages from chunked input, and their sum against a first configuration.

``python -m fsmeta.workloads.stages /root/testdata/sf0.1 8`` prints one line a configuration, with 8 cores.
"""

from __future__ import annotations

import sys
import time

from pyspark.sql import DataFrame, SparkSession

from fsmeta import fixtures as fx
from fsmeta.plans import workspace
from fsmeta.snapshot import aggregate, counting, preprocess, primary

SCHEMA = "path string, type string, mode int, uid long, gid long, size long, atime timestamp_ntz, ctime timestamp_ntz, mtime timestamp_ntz, fileset string"


def chunked(spark: SparkSession, df: DataFrame, target_rows: int) -> DataFrame:
    at = workspace.fresh(spark, "chunks")
    preprocess.write_chunks(preprocess.preprocess(df), at, target_rows)
    return spark.read.schema(SCHEMA).option("escape", "\\").csv(at)


def run_stages(rows: DataFrame, low: int = 1, high: int = 5) -> dict[str, float]:
    sink = lambda df: df.write.format("noop").mode("overwrite").save()
    plans = {
        "primary": lambda: sink(primary.to_requests(primary.to_records(rows, extra=("fileset",)))),
        "counting": lambda: sink(counting.merge_counts(counting.shard_counts(rows, high))),
        "aggregate": lambda: sink(aggregate.aggregate(rows, low, high)),
    }
    out = {}
    for name, plan in plans.items():
        t = time.perf_counter()
        plan()
        out[name] = round(time.perf_counter() - t, 2)
    return out


def sweep(spark: SparkSession, sf_dir: str, targets: tuple[int, ...] = (100_000, 10_000), views: tuple[str, ...] = tuple(fx.SNAPSHOTS)) -> list[dict]:
    out = []
    for view in views:
        make, first = fx.SNAPSHOTS[view], None
        for target in targets:
            rows = chunked(spark, make(spark, sf_dir), target)
            stages = run_stages(rows)
            total = sum(stages.values())
            first = first or total
            out.append({"snapshot": view, "chunk_rows": target, "chunks": len(rows.inputFiles()), **stages, "normalised": round(total / first, 2)})
    return out


def main(sf_dir: str, cores: str) -> None:
    """One line a configuration, with this number of cores (the sweep over workers is a run for each)."""
    session = SparkSession.builder.master(f"local[{cores}]").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    run_stages(chunked(session, fx.fs_small(session, sf_dir), 1_000_000))  # starts the engine
    for line in sweep(session, sf_dir):
        print({"cores": cores, **line}, flush=True)
    session.stop()


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1", sys.argv[2] if len(sys.argv) > 2 else "*")
