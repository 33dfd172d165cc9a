"""Prints one JSON line: seconds of the headline queries at BENCH_SF_DIR."""

import json
import os
import time

from pyspark.sql import SparkSession

from parsieve.functions.scores import Mdl
from parsieve.operators import kernel, metrics
from parsieve.operators.search import find_parent_sets, search
from parsieve.plans.encode import encode
from parsieve.sources.views import load


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times, facts = {}, {}
    find_parent_sets(load(spark, sf, "geo5"))  # start-up costs stay out

    def timed(name: str, run) -> None:
        begun = time.time()
        r = run()
        times[name] = round(time.time() - begun, 3)
        keep = ("nodes", "pairs", "l_max", "l_z", "z", "list_min", "list_max", "share_percent", "nodes_per_second", "mode", "flagged", "rejected")
        facts[name] = {k: v if isinstance(v, str) else round(v, 3) for k, v in metrics.report(r).items() if k in keep}

    timed("mps_plant12", lambda: find_parent_sets(load(spark, sf, "plant12")))
    timed("mps_plant12_dfs", lambda: find_parent_sets(load(spark, sf, "plant12"), mode="dfs", dfs_root_layer=2))
    timed("mps_doc10", lambda: find_parent_sets(load(spark, sf, "doc10")))
    enc = encode(load(spark, sf, "emb16"))
    timed("mps_emb16", lambda: search(spark, enc, kernel.problem(enc, Mdl()), "dfs", root_layer=2))
    print(json.dumps({"metric": "total seconds of the headline searches", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "facts": facts, "sf": sf.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()
