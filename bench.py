"""Times the headline queries and prints one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) names the tables, BENCH_CPUS (default all) the cores; BENCH_STAGES
adds the sweep of snapshot stages over chunk sizes.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ["PYTHONPATH"] = os.pathsep.join([sys.path[0], os.environ.get("PYTHONPATH", "")])

HEADLINE = (
    "preprocess_reduce", "primary_records", "primary_requests", "count_user", "count_dir_recursive", "aggregate_exact_user", "aggregate_exact_group", "aggregate_exact_dir",
    "dd_quantiles_user", "dd_quantiles_group", "dd_quantiles_dir", "dd_expand_first_dir", "snapshot_diff", "q06_over_limit", "q08_near_quota", "q13_p99_directory_project", "q16_top_users",
    "event_reduce", "path_resolve", "index_after_events", "to_update", "lookup_baseline_counts",
)


def main() -> None:
    from pyspark.sql import SparkSession

    from fsmeta import catalog, fixtures
    from fsmeta.index import search
    from fsmeta.monitor import baseline, run
    from fsmeta.plans import workspace
    from fsmeta.sketch import base
    from fsmeta.snapshot import aggregate as ag
    from fsmeta.workloads import events as ev
    from fsmeta.workloads import stages

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g"))
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    sink = lambda df: df.write.format("noop").mode("overwrite").save()
    queries, took = catalog.queries(), {}

    def clock(name, f):
        t = time.perf_counter()
        f()
        took[name] = round(time.perf_counter() - t, 3)
        print(name, took[name], file=sys.stderr, flush=True)

    sink(queries["primary_index_stats"](spark, sf))  # starts the engine
    for name in HEADLINE:
        clock(name, lambda q=queries[name]: sink(q(spark, sf)))

    rows = ag.numbers(fixtures.fs_large(spark, sf))
    objects = rows.count()
    for algo in ("exact", "dd", "kll", "req", "tdigest"):
        clock(f"sketch_{algo}_users_groups", lambda a=algo: sink(base.quantiles(ag.expand(rows, 1, 5, ("user", "group")), ("kind", "id"), ag.ATTRIBUTES, ag.QUANTILES, a)))

    rates = {}
    loads = {"mixed_ops": (ev.mixed_ops, ev.roots, 1400), "create_delete": (ev.create_delete, ev.roots, 1200), "tree_read": (ev.tree_read, None, 1000)}
    for name, (make, tree, batch) in loads.items():
        for sources in (1, 2, 4):
            events = make(spark, sf, sources).cache()
            n = events.count()
            nodes = (tree(events) if tree else ev.read_tree(spark, sf, sources)).cache()
            nodes.count()
            plans = {"stateful": run.monitor(events, nodes, False, batch), "stateful_reduced": run.monitor(events, nodes, True, batch)}
            if sources == 1:
                plans["passthrough"] = baseline.passthrough(events)
                # every look-up really waits; the first few hundred events show the rate
                some = events.filter(events.seq < events.agg({"seq": "min"}).first()[0] + 600).cache()
                got = run.throughput(baseline.lookup_pipeline(some, nodes), some.count())
                rates[f"{name}_lookup_measured"] = got["events_per_s"]
                some.unpersist()
            for kind, plan in plans.items():
                got = run.throughput(plan, n)
                rates[f"{name}_{kind}_{sources}"] = got["events_per_s"]
                took[f"{name}_{kind}_{sources}"] = got["seconds"]
            events.unpersist()
            nodes.unpersist()
    print(rates, file=sys.stderr, flush=True)
    for filesets in (1, 2, 3, 4, 5):
        events = ev.create_delete(spark, sf, filesets).cache()
        n, roots = events.count(), ev.roots(events).cache()
        rates[f"filesets_{filesets}"] = run.throughput(run.monitor(events, roots, True, 1200), n)["events_per_s"]
        events.unpersist()
    for parts in (1, 2, 4, 8, 16):  # partitions of the queue of one fileset, before its one owner
        events = ev.create_delete(spark, sf, 1).repartition(parts).cache()
        n = events.count()
        rates[f"partitions_{parts}"] = run.throughput(run.monitor(events, ev.roots(events), True, 1200), n)["events_per_s"]
        events.unpersist()
    ratios = {
        **{f"{w}_reduction_{m}": round(rates[f"{w}_stateful_reduced_{m}"] / rates[f"{w}_stateful_{m}"], 2) for w in loads for m in (1, 2, 4)},
        **{f"{w}_1_to_{m}": round(rates[f"{w}_stateful_{m}"] / rates[f"{w}_stateful_1"], 2) for w in loads for m in (2, 4)},
        **{f"{w}_over_lookup": round(rates[f"{w}_stateful_1"] / rates[f"{w}_lookup_measured"], 1) for w in loads},
        **{f"sketch_{a}_over_dd": round(took[f"sketch_{a}_users_groups"] / took["sketch_dd_users_groups"], 2) for a in ("exact", "kll", "req", "tdigest")},
    }
    # the same question by both routes, from tables that are there already
    agg = workspace.store(ag.totals(fixtures.fs_large(spark, sf), 0, 4, ("dir",)), "bench")
    primary = workspace.store(fixtures.fs_large(spark, sf), "bench")
    clock("route_aggregate", lambda: sink(search.search(agg, [search.Match("file_count", "gt", 650)])))
    clock("route_primary", lambda: sink(search.search(ag.totals(primary, 0, 4, ("dir",)), [search.Match("file_count", "gt", 650)])))
    sweep = stages.sweep(spark, sf, views=("fs_medium",)) if os.environ.get("BENCH_STAGES") else []
    print(json.dumps({"metric": "sum of headline query times", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf, "events_per_s": rates, "ratios": ratios, "stages": sweep, "objects": objects, "objects_per_s_primary": round(objects / took["primary_records"])}))
    spark.stop()


if __name__ == "__main__":
    main()
