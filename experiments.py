"""The experiments at full length, as tables in EXPERIMENTS.md: `python experiments.py [name ...]`.

The registered `measure_*` queries run the same functions with fewer queries. Folders are taken
from $EXPERIMENT_SF_DIR (default sf0.01); sections that are run again replace their own part.
"""

from __future__ import annotations

import os
import re
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

from pyspark.sql import DataFrame, SparkSession  # noqa: E402

from trellis import measures as M  # noqa: E402

SF = os.environ.get("EXPERIMENT_SF_DIR", "/root/testdata/sf0.01")
CPUS = os.environ.get("EXPERIMENT_CPUS", "8")
OUT = os.path.join(ROOT, "EXPERIMENTS.md")


def drift(spark: SparkSession) -> DataFrame:
    """200 queries, 50 of a family after the other, threshold 10, budget 0.2: where each family ends."""
    rows = M.drift(spark, SF, n=200, threshold=10)
    return rows.where("k % 50 = 49").orderBy("variant", "k")


SECTIONS = {
    "runtimes": ("Runtime in ms, without and with adaptivity, with geometric means of families", lambda s: M.runtimes(s, SF)),
    "baselines": ("Runtime in ms of the comparison systems over the whole graph", lambda s: M.baseline_runtimes(s, SF, ("uni_l3", "uni_l4", "uni_l5", "uni_l6", "div_l1", "div_s1", "enc_y1"))),
    "drift": ("Workload that drifts from family to family: cumulative seconds and values moved", drift),
    "threshold": ("Frequency threshold, 200 queries of each workload", lambda s: M.threshold_sweep(s, SF, n=200, thresholds=(1, 2, 5, 10, 20, 30))),
    "data_scaling": ("Growing data, eight workers", lambda s: M.data_scaling(s, os.path.join(os.path.dirname(SF), "sf0.1"))),
    "strong_scaling": ("Growing number of workers, the same data", lambda s: M.strong_scaling(s, SF)),
    "startup": ("Seconds before the first query", lambda s: M.startup(s, SF)),
    "replication": ("Initial replication", lambda s: M.initial_replication(s, SF)),
    "locality": ("What hash locality and the pinned subject save", lambda s: M.locality_ablation(s, SF)),
    "policies": ("Order in which trees are grown", lambda s: M.tree_policies(s, SF)),
    "training": ("Training on two families, then frozen, against adaptation", lambda s: M.trained_pairs(s, SF, n=40, training=60)),
    "balance": ("Triples by worker after a workload", lambda s: M.load_balance(s, SF)),
    "work": ("Answers by worker during a workload of 60 queries", lambda s: M.workload_balance(s, SF, n=60)),
    "reach": ("Share of the data that a family's patterns match", lambda s: M.workload_reach(s, SF)),
}


def text(value) -> str:
    return f"{value:.4g}" if isinstance(value, float) else str(value)


def table(df: DataFrame) -> str:
    rows = df.collect()
    lines = [f"| {' | '.join(df.columns)} |", f"|{'---|' * len(df.columns)}"]
    return "\n".join(lines + [f"| {' | '.join(map(text, r))} |" for r in rows])


def parts() -> dict[str, str]:
    if not os.path.exists(OUT):
        return {}
    with open(OUT, encoding="utf-8") as file:
        found = re.split(r"^## (\w+): ", file.read(), flags=re.M)
    return dict(zip(found[1::2], found[2::2], strict=True))


def main(names: list[str]) -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "10g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    for name in names or SECTIONS:
        title, make = SECTIONS[name]
        began = time.perf_counter()
        body = table(make(spark))
        done = parts()
        done[name] = f"{title}\n\n`{os.path.basename(SF)}`, `local[{CPUS}]`, {time.perf_counter() - began:.0f} s in all\n\n{body}\n\n"
        with open(OUT, "w", encoding="utf-8") as file:
            file.write("# Experiments\n\nMade by `experiments.py`.\n\n" + "".join(f"## {k}: {done[k].rstrip()}\n\n" for k in SECTIONS if k in done))
        print(name, "done", flush=True)


if __name__ == "__main__":
    main(sys.argv[1:])
