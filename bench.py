"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import time

from starfold.session import local_session


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(os.environ.get("BENCH_CPUS", "*"), 8)
    spark.sparkContext.setLogLevel("ERROR")
    from starfold.operators.alternating import connected_components
    from starfold.operators.baselines import two_star_rounds
    from starfold.operators.paired import connected_components as paired
    from starfold.sources import graphs, tables

    runs = {
        "alternating_order_part": lambda: connected_components(tables.order_part(spark, sf_dir), stop="quiet_counter"),
        "alternating_customer_supplier": lambda: connected_components(tables.customer_supplier(spark, sf_dir), stop="quiet_counter"),
        "alternating_user_event_chain": lambda: connected_components(tables.user_event_chain(spark, sf_dir), stop="quiet_counter"),
        "alternating_seq_path_16": lambda: connected_components(graphs.seq_path(spark, 16), stop="quiet_counter"),
        "alternating_seq_path_20": lambda: connected_components(graphs.seq_path(spark, 20), stop="quiet_counter"),
        "alternating_grid_4096x12": lambda: connected_components(graphs.bridged_grid(spark, 4096, 12), stop="quiet_counter"),
        "paired_order_part": lambda: paired(tables.order_part(spark, sf_dir)),
        "two_star_order_part": lambda: two_star_rounds(tables.order_part(spark, sf_dir)),
    }
    took, steps, rate = {}, {}, {}
    for name, run in runs.items():
        began = time.time()
        out = run()
        out.labels.write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
        steps[name] = out.n_steps
        rate[name] = round(sum(m["edges_in"] or 0 for m in out.metrics) / took[name])
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "steps": steps, "edges_per_sec": rate, "sf": os.path.basename(sf_dir.rstrip("/"))}))


if __name__ == "__main__":
    main()
