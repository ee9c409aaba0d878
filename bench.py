"""Headline queries over BENCH_SF_DIR on local[BENCH_CPUS]; one JSON line.

Links and graphs are made first and timed as stages; each query then runs once
unmeasured and is measured as the median of three warm runs.
"""

from __future__ import annotations

import json
import os
import time
from statistics import median


def main() -> None:
    from cityweave import registry, workload
    from cityweave.context import context
    from cityweave.session import local_session

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(os.environ.get("BENCH_CPUS", "4"), **{"spark.driver.memory": "16g"})
    took: dict[str, float] = {}

    def timed(name: str, run, warm: int = 0) -> None:
        times = []
        for _ in range(warm + 1):
            began = time.perf_counter()
            run()
            times.append(time.perf_counter() - began)
        took[name] = round(median(times[1:]) if warm else times[0], 3)

    c = context(spark, sf_dir)
    timed("stage_links", lambda: c.links)
    timed("stage_triples", lambda: c.triples)
    timed("stage_predicate_layout", lambda: c.materialized("predicate"))
    queries = registry.queries()
    rows = lambda key: queries[key](spark, sf_dir).write.format("noop").mode("overwrite").save()
    for key in workload.QUERIES:
        timed(key, lambda key=key: rows(key), 3)
    for key in workload.QUERIES:
        timed(f"{key}_mkg_predicate", lambda key=key: rows(f"{key}_mkg_predicate"), 1)
    for key in ("link_summary", "link_sweep", "link_poi", "link_adjacent_edge", "geo_intersection_area", "geo_intersection_edges", "sp_join_dwithin", "sp_knn_road"):
        timed(key, lambda key=key: rows(key), 1)
    total = sum(took[k] for k in workload.QUERIES)
    print(json.dumps({"metric": "workload queries, virtual graph, warm median, sum", "value": round(total, 3), "unit": "sec", "queries": took, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
