"""Headline timings: one JSON line. BENCH_SF_DIR, BENCH_CPUS, BENCH_ITERS, BENCH_SEEDS choose table folder, threads,
iterations of each mode and first guesses. All modes are warmed up first, and their order turns from seed to seed."""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = HERE + os.pathsep + os.environ.get("PYTHONPATH", "")


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    iters = int(os.environ.get("BENCH_ITERS", "100"))
    seeds = int(os.environ.get("BENCH_SEEDS", "1"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false")
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g")).config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from sparse_topics import experiments as X
    from sparse_topics.operators import measures as M
    from sparse_topics.operators.als import projected_als, sparse_als
    from sparse_topics.operators.sequential import sequential_als
    from sparse_topics.operators.sparsify import Limits

    took: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name, f):
        began = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - began, 3)
        print(name, took[name], file=sys.stderr, flush=True)
        return out

    td = timed("prepare", lambda: (lambda t: (t.facts(), t)[1])(X.corpus(spark, sf_dir)))
    facts |= {"terms": td.n_terms, "docs": td.n_docs, "nnz": td.facts()["nnz"]}
    k, t_u, t_v = 4, 55, 400
    modes = {
        f"whole_{iters}": lambda n, seed: sparse_als(td, k, Limits(t_u, t_v), init_nnz=400, max_iter=n, seed=seed, measure=False),
        f"per_topic_{iters}": lambda n, seed: sparse_als(td, k, Limits(t_u // k, t_v // k, scope="topic"), init_nnz=400, max_iter=n, seed=seed, measure=False),
        f"sequential_{k}x{iters // k}": lambda n, seed: sequential_als(td, k, limits=Limits(t_u // k, t_v // k), iters_per_block=max(1, n // k), init_nnz=400, seed=seed, measure=False),
    }
    timed("warm_up", lambda: [run(4, 0) for run in modes.values()])
    fits, names = {}, list(modes)
    for seed in range(seeds):
        for name in names[seed % 3 :] + names[: seed % 3]:
            fits[name, seed] = timed(name if not seed else f"{name}_seed{seed}", lambda name=name, seed=seed: modes[name](iters, seed))
    whole, topic, seq = (fits[name, 0] for name in names)
    dense = timed("dense_5", lambda: projected_als(td, k, max_iter=5))
    traced = timed("sparse_measured_5", lambda: sparse_als(td, k, Limits(t_u, t_v), init_nnz=400, max_iter=5))
    groups = X.groups(spark, sf_dir)
    for name, fit in (("whole", whole), ("per_topic", topic), ("sequential", seq), ("dense", dense)):
        a = timed(f"accuracy_{name}", lambda fit=fit: M.mean_accuracy(fit.v, groups, 4).first())
        facts |= {f"accuracy_{name}": round(a["mean_acc"], 4), f"live_{name}": a["n_live"]}
    facts["dense_over_sparse_entries"] = round(M.memory_ratio(dense, traced)[0], 1)
    print(json.dumps({"metric": "sum of headline query seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir).removeprefix("sf"), "facts": facts}))
    spark.stop()


if __name__ == "__main__":
    main()
