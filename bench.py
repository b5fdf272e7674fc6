"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import sys
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    from nzspan import workloads
    from nzspan.operators import baselines, layout, products, vectors
    from nzspan.session import local_session
    from nzspan.sources import drain

    spark = local_session(cores=CPUS, partitions=8, memory="16g")
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}

    def timed(name: str, run):
        began = time.perf_counter()
        out = run()
        took[name] = round(time.perf_counter() - began, 3)
        return out

    a = timed("build_terms", lambda: workloads.get_matrix(spark, SF_DIR, "dense_first"))
    even = timed("split_even", lambda: layout.partition_even(a, 8))
    timed("split_borders", lambda: layout.partition_even(a, 8, by="borders"))
    spans = timed("split_columns", lambda: baselines.partition_columns(a, 8))
    x = vectors.spread(workloads.long_x(spark, a.n), even).persist()
    x.count()
    v = workloads.short_v(spark, a.m).persist()
    v.count()
    timed("setup_zones", lambda: layout.setup_zones(even.placed, even.parts).count())
    timed("setup_grouping", lambda: layout.setup_zones(even.placed, even.parts, "grouping").count())
    for name, run in (
        ("forward_even", lambda: products.forward(even, x)),
        ("forward_tree", lambda: products.forward(even, x, "tree", 4)),
        ("forward_columns", lambda: baselines.forward_spans(spans, workloads.long_x(spark, a.n))),
        ("forward_plain", lambda: products.forward_plain(a, workloads.long_x(spark, a.n))),
        ("transposed_even", lambda: products.transposed(even, v)),
        ("transposed_columns", lambda: baselines.transposed_spans(spans, v)),
        ("transposed_plain", lambda: products.transposed_plain(a, v)),
    ):
        timed(name, lambda r=run: drain(r()))
    packed = products.pack_blocks(even).persist()
    timed("pack_blocks", lambda: packed.count())
    import numpy as np

    timed("forward_blocks", lambda: drain(products.allreduce_short(products.kernel_forward(packed, x), a.m)))
    timed("transposed_blocks", lambda: drain(products.zone_reduce(products.kernel_transposed(packed, 1.0 + np.arange(a.m) % 5), even.zones)))
    timed("pairs_chained_3", lambda: products.product_pairs(even, x, v, 3))
    for name in ("sweep_imbalance_dense_first", "sweep_zones_dense_first", "profile_dense_first", "w3_forward", "w3_transposed"):
        timed(name, lambda n=name: drain(workloads.QUERIES[n](spark, SF_DIR)))
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf")}))
    sys.stdout.flush()


if __name__ == "__main__":
    main()
