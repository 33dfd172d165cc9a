"""Runs the scaling experiments and prints their tables: workers, partition factor, rows, forced switch.

    python experiments.py [folder of the tables, default /root/testdata]

"""

import json
import subprocess
import sys

ROOT = "/root/testdata"


def session(cores: int):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", cores).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def child(root: str, cores: int) -> None:
    from parsieve.functions.scores import Mdl
    from parsieve.operators import kernel, metrics
    from parsieve.operators.search import find_parent_sets, search
    from parsieve.plans.encode import encode
    from parsieve.sources.views import load

    spark = session(cores)
    find_parent_sets(load(spark, f"{root}/sf0.001", "geo5"))

    def row(what: str, view: str, r, **more) -> None:
        m = metrics.report(r)
        keep = ("seconds", "nodes", "pairs", "l_max", "l_z", "z", "mode", "left_at_switch", "flagged", "rejected", "shared_gain")
        print(json.dumps({"what": what, "cores": cores, "view": view} | more | {k: round(m[k], 3) if isinstance(m[k], float) else m[k] for k in keep}), flush=True)

    emb = encode(load(spark, f"{root}/sf0.1", "emb16"))
    wide = kernel.problem(emb, Mdl())
    plant = encode(load(spark, f"{root}/sf0.1", "plant12"))
    small = kernel.problem(plant, Mdl())
    search(spark, plant, small)  # workers are up and imports are done
    row("workers", "emb16", search(spark, emb, wide, "dfs", root_layer=2))
    row("workers", "plant12", search(spark, plant, small))
    if cores < 8:
        return
    for factor in (1, 2, 4, 8):
        row("partition factor", "emb16", search(spark, emb, wide, "dfs", root_layer=3, factor=factor), factor=factor)
    for sf in ("sf0.001", "sf0.01", "sf0.1"):
        row("rows", "plant12", find_parent_sets(load(spark, f"{root}/{sf}", "plant12")), sf=sf)
    for layer in (None, 2, 4, 6):
        row("forced switch", "emb16", search(spark, emb, wide, "bfs" if layer is None else "dfs", root_layer=layer), root_layer=layer)


def main(root: str) -> None:
    for cores in (1, 2, 4, 8):
        subprocess.run([sys.executable, __file__, "--child", root, str(cores)], check=True)


if __name__ == "__main__":
    if sys.argv[1:2] == ["--child"]:
        child(sys.argv[2], int(sys.argv[3]))
    else:
        main(sys.argv[1] if len(sys.argv) > 1 else ROOT)
