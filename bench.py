"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Workloads of the experiments: random and dense graphs by start partition, trees by the general and the special way.
HEADLINE = ("forward_random", "baseline_signature_random", "forward_containment", "forward_reference", "forward_dense10", "pages_one_index_general", "pages_one_index_path", "pages_fb_stable", "pages_ak2", "quotient_edges_random", "path_query_pages_nav", "cost_messages_per_rank")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "16g"))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from dagquotient import queries as own
    from dagquotient.sources import fixtures

    spark.range(1000).groupBy().count().collect()  # warm-up
    took, measures = {}, {}
    for name in HEADLINE:
        began = time.time()
        own.queries()[name](spark, SF).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
    nodes, edges = fixtures.graph(spark, SF, "random").size()
    measures["random_seconds_per_node_and_edge"] = took["forward_random"] / max(1, nodes + edges)
    measures["random_nodes"], measures["random_edges"] = nodes, edges
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF, "measures": measures}))


if __name__ == "__main__":
    main()
