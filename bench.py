"""Times the headline queries. One JSON line: the sum, and each query's seconds."""

import json
import os
import statistics
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from rambler.operators.walk import WalkConfig, random_walks
from rambler.queries import MODELS
from rambler.sources.catalog import load_graph

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
STEPS = int(os.environ.get("BENCH_STEPS", "10"))


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", "16").config("spark.driver.memory", "8g").config("spark.driver.maxResultSize", "4g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    out, extra = {}, {}

    def timed(name, make, runs=1):
        """Median seconds of making the frame (supersteps run while it is made) and reading it through."""
        took = []
        for _ in range(runs):
            began = time.time()
            make().write.format("noop").mode("overwrite").save()
            took.append(time.time() - began)
        out[name] = round(statistics.median(took), 3)

    began = time.time()
    graph = load_graph(spark, SF, "g1", "uniform").stored()
    out["build_g1"] = round(time.time() - began, 3)
    nodes = graph.edges.select("src").distinct().count()
    began = time.time()
    graph.node_stats.write.format("noop").mode("overwrite").save()
    out["preprocess"] = round(time.time() - began, 3)
    for name, model, sampler in (
        ("node2vec_w_adaptive", "node2vec_w", "adaptive"), ("node2vec_w_reservoir_keys", "node2vec_w", "keys"), ("node2vec_w_reservoir_prefix", "node2vec_w", "prefix"), ("node2vec_w_reservoir_jump", "node2vec_w", "jump"),
        ("node2vec_w_rejection_bound", "node2vec_w", "rejection_bound"), ("node2vec_w_rejection_max", "node2vec_w", "rejection_exact"), ("node2vec_u_adaptive", "node2vec_u", "adaptive"),
    ):
        timed(name, lambda model=model, sampler=sampler: random_walks(graph, MODELS[model], None, sampler, WalkConfig(steps=STEPS, mode="replicated")), 3)
        extra[name] = round(nodes * STEPS / out[name])
    timed("node2vec_w_keys_superstep", lambda: random_walks(graph, MODELS["node2vec_w"], None, "keys", WalkConfig(steps=2, mode="superstep")))
    extra["node2vec_w_keys_superstep"] = round(nodes * 2 / out["node2vec_w_keys_superstep"])
    star = load_graph(spark, SF, "g10").stored()
    timed("metapath_typed_star", lambda: random_walks(star, MODELS["metapath_w"], None, "keys", WalkConfig(steps=5, mode="replicated")))
    timed("visits", lambda: random_walks(graph, MODELS["node2vec_w"], None, "adaptive", WalkConfig(steps=10, mode="replicated")).groupBy("node").agg(F.count("*")))
    print(json.dumps({"metric": "total_walk_seconds", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "steps_per_second": extra, "sf": SF.rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
