"""Headline runs: rewritten against per-gate circuits on both families, tiers, sweeps, scaling, encoders, batches. Prints one JSON line.

BENCH_SF_DIR names the tables (default sf0.1), BENCH_CPUS the threads. Runs of either kind come once before anything is timed, so that workers
are up and code is compiled. Short runs are medians of three. Times end with a noop write of all amplitudes.
"""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from svengine import catalog
    from svengine.operators import chunks as C
    from svengine.operators import rows as R
    from svengine.operators import states as S
    from svengine.operators import tiers as T
    from svengine.plans.cost import baseline_cost, blocked_cost, totals
    from svengine.plans.transpile import plan_blocks, stats
    from svengine.sources import workloads as W

    catalog.load()
    took, more = {}, {}

    def timed(name: str, make, times: int = 1) -> None:
        got = []
        for _ in range(times):
            t = time.time()
            make().write.format("noop").mode("overwrite").save()
            got.append(time.time() - t)
            if got[0] > 3:
                break
        took[name] = round(statistics.median(got), 3)

    volume = lambda n, depth=10: W.quantum_volume(spark, sf_dir, n, depth)
    fourier = lambda n: W.qft(n, with_swaps=False)
    options = {"volume": {}, "fourier": {"diagonal_free": True}}

    def zero(n, nc, parts=None):
        df = S.zero_state(spark, n, nc, "chunks")
        return C.Register(df.repartition(parts) if parts else df, n, nc, symmetric=True)

    blocked = lambda c, nc, parts=None, **o: C.run_blocked(zero(c.n, nc, parts), plan_blocks(c, nc, **o)).df
    baseline = lambda c, nc, s="pair", parts=None: C.run_baseline(zero(c.n, nc, parts), c, s).df

    def both(name, family, c, nc, parts=None, times=3):
        """The rewritten and the per-gate run."""
        timed(f"{name}_blocked", lambda: blocked(c, nc, parts, **options[family]), times)
        timed(f"{name}_per_gate", lambda: baseline(c, nc, "pair", parts), times)

    for c, o in ((volume(8, 1), "volume"), (fourier(8), "fourier")):
        blocked(c, 5, **options[o]).write.format("noop").mode("overwrite").save()
        baseline(c, 5).write.format("noop").mode("overwrite").save()

    n, nc = 20, 16
    for name, c in (("volume_d10", volume(n)), ("fourier", fourier(n))):
        family = name.split("_")[0]
        both(name, family, c, nc)
        plan = plan_blocks(c, nc, **options[family])
        t = time.time()
        plan_blocks.__wrapped__(c, nc, **options[family])
        more[name] = {"per_gate": totals(baseline_cost(c, nc, 4)), "blocked": totals(blocked_cost(plan, 4)), "plan": stats(plan), "planning_seconds": round(time.time() - t, 4)}
    timed("fourier_blocked_plain", lambda: blocked(fourier(n), nc), 3)
    for s in ("pair", "copy"):
        timed(f"volume_d2_per_gate_{s}", lambda s=s: baseline(volume(18, 2), 14, s))

    # two tiers, half of the chunks slow: rewritten with fetched sections, against gates in place; the row executor beside them
    for name, c in (("volume_d1", volume(16, 1)), ("fourier", fourier(16))):
        timed(f"tiered_{name}_blocked", lambda c=c, o=options[name.split("_")[0]]: T.run_tiered(zero(16, 13), plan_blocks(c, 13, **o), 4)[0].df)
        timed(f"tiered_{name}_in_place", lambda c=c: T.run_in_place(zero(16, 13), c, 4)[0].df)
    # one node, growing registers: one space (a single chunk in one task) to 16 qubits, eight chunks after, tiers at 20
    for k in (14, 16, 18, 20):
        for family, c in (("volume", volume(k, 2)), ("fourier", fourier(k))):
            both(f"single_node_{family}_{k}", family, c, min(k, 16) if k <= 16 else k - 3)
            if k == 20:
                timed(f"single_node_{family}_{k}_tiered", lambda c=c, o=options[family]: T.run_tiered(zero(20, 17), plan_blocks(c, 17, **o), 4)[0].df)
    for k in (8, 10):
        timed(f"single_node_fourier_{k}_rows", lambda k=k: R.run_gates(S.zero_state(spark, k), fourier(k)))
    # at equal size: one space against several
    timed("one_space_18", lambda: blocked(volume(18, 2), 18), 3)
    timed("eight_spaces_18", lambda: blocked(volume(18, 2), 15, 8), 3)
    # strong scaling: 18 qubits over 1 to 16 partitions of a chunk; weak: 2^16 amplitudes a partition
    for p in range(5):
        both(f"strong_{2**p}", "volume", volume(18, 2), 18 - p, 2**p, 1)
    for p in range(5):
        both(f"weak_{2**p}", "volume", volume(16 + p, 2), 16, 2**p, 1)
    # with half of the chunks in the slow tier
    for p in range(2):
        timed(f"strong_tiered_{2**p}", lambda p=p: T.run_tiered(zero(18, 16), plan_blocks(volume(18, 2), 16), 2 * (p + 1) - 1)[0].df)
    for p in range(3):
        timed(f"weak_tiered_{2**p}", lambda p=p: T.run_tiered(zero(16 + p, 14), plan_blocks(volume(16 + p, 2), 14), 2 ** (p + 1))[0].df)

    for name in ("encode_orders", "u3_high_orders", "exchange_pair", "batch_orders_circuits", "events_circuits_state", "sample_shots_two_level", "qubit_p1"):
        timed(name, lambda name=name: catalog.QUERIES[name](spark, sf_dir))
    ratio = lambda a, b: round(took[a] / took[b], 2)
    more["baseline_over_rewritten"] = {
        "volume_d10": ratio("volume_d10_per_gate", "volume_d10_blocked"), "fourier": ratio("fourier_per_gate", "fourier_blocked"),
        "tiered_volume_d1": ratio("tiered_volume_d1_in_place", "tiered_volume_d1_blocked"), "tiered_fourier": ratio("tiered_fourier_in_place", "tiered_fourier_blocked"),
        "strong": [ratio(f"strong_{2**p}_per_gate", f"strong_{2**p}_blocked") for p in range(5)], "weak": [ratio(f"weak_{2**p}_per_gate", f"weak_{2**p}_blocked") for p in range(5)],
    }
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rsplit("sf", 1)[-1], "details": more}))


if __name__ == "__main__":
    main()
