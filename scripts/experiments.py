"""Runs the experiments at their published settings on the given tables and prints the tables' layout.

    python scripts/experiments.py [--dir DIR] [--rounds N] [--scheme attribute|range|...] [--scale none|global|client] [--tiers 2|3] [--ablate]
"""

from __future__ import annotations

import argparse
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))

from devfed.operators import baselines, commcost  # noqa: E402
from devfed.operators.rounds import FedConfig  # noqa: E402
from devfed.plans import workloads  # noqa: E402
from devfed.session import session  # noqa: E402


def main() -> None:
    p = argparse.ArgumentParser()
    p.add_argument("--dir", default="/root/testdata/sf0.01")
    p.add_argument("--rounds", type=int, default=400)
    p.add_argument("--clients", type=int, default=100)
    p.add_argument("--scheme", default="attribute", choices=workloads.SCHEMES)
    p.add_argument("--scale", default="none", choices=("none", "global", "client"))
    p.add_argument("--tiers", type=int, default=2, choices=(2, 3))
    p.add_argument("--ablate", action="store_true")
    a = p.parse_args()
    spark = session()
    spark.sparkContext.setLogLevel("ERROR")
    base = FedConfig(rounds=a.rounds)
    configs = baselines.ablations(base) if a.ablate else {"sda": base, "fedavg": base.fedavg()}
    began = time.time()
    results, history = workloads.late_shipment_run(spark, a.dir, configs, a.scheme, a.clients, 5 if a.tiers == 3 else None, a.scale)
    took = time.time() - began
    workloads.summary(history).orderBy("metric", "method").show(100, truncate=False)
    history.where(f"round = {a.rounds}").orderBy("method").show(100, truncate=False)
    commcost.rounds_to_target(history, "accuracy", 0.6).show(truncate=False)
    print(f"{took:.1f} s for {len(results)} runs of {a.rounds} rounds: {took / a.rounds / len(results):.3f} s a round with splitting, packing and scoring")


if __name__ == "__main__":
    main()
