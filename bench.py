"""Times the headline selections at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``value`` adds up the HEADLINE runs, which have kept their names; the other queries are reported beside them: thresholds
up to 100 features, strategies, the one-core baseline and the time by number of cores (each in a session of its own).
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
HEADLINE = ("gate_mrmr_k5", "gate_mrmr_k10", "gate_mrmr_k10_arrow", "gate_cmim_k5_lazy", "star_mrmr_k10", "star_wide100_mrmr_k10", "embed_mrmr_k10", "tokens_toxic_mrmr_k5")


def session(cores: str) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", cores)
        .config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def by_cores(cores: str) -> None:
    """Seconds of one selection on so many cores, printed: run in a process of its own."""
    spark = session(cores)
    from featsift.operators import greedy
    from featsift.sources import workloads

    greedy.select(workloads.lines(spark, SF_DIR), 2)  # warm-up
    began = time.perf_counter()
    greedy.select(workloads.star(spark, SF_DIR, widen=76), 5)
    print("SECONDS", round(time.perf_counter() - began, 3), flush=True)
    spark.stop()


def main() -> None:
    spark = session(CPUS)

    from featsift.operators import baselines, greedy
    from featsift.sources import workloads

    def selection(ds, k, criterion="mrmr", **how):
        return lambda: greedy.select(ds(), k, criterion, **how)

    lines, star, embed = (lambda f=f: f(spark, SF_DIR) for f in (workloads.lines, workloads.star, workloads.embed))
    wide = lambda: workloads.star(spark, SF_DIR, widen=76)
    tokens, hashed = lambda: workloads.token_set(spark, SF_DIR), lambda: workloads.token_set(spark, SF_DIR, "quality", ngram=2, buckets=1 << 20)
    runs = {
        "gate_mrmr_k5": selection(lines, 5),
        "gate_mrmr_k10": selection(lines, 10),
        "gate_mrmr_k10_arrow": selection(lines, 10, strategy="arrow"),
        "gate_cmim_k5_lazy": selection(lines, 5, "cmim", lazy=True),
        "star_mrmr_k10": selection(star, 10),
        "star_wide100_mrmr_k10": selection(wide, 10),
        "embed_mrmr_k10": selection(embed, 10),
        "tokens_toxic_mrmr_k5": selection(tokens, 5),
        "sequential_gate_mrmr_k5": lambda: baselines.sequential(lines(), 5, "mrmr"),
        "gate_mrmr_k10_explode": selection(lines, 10, strategy="explode"),
        "star_wide100_mrmr_k5": selection(wide, 5),
        "star_wide100_mrmr_k25": selection(wide, 25),
        "embed_mrmr_k50": selection(embed, 50),
        "tokens_toxic_mrmr_k100": selection(tokens, 100),
        "hashed_bigrams_mrmr_k100": selection(hashed, 100),
    }
    selection(lines, 2)()  # warm-up
    seconds, chosen = {}, {}
    for name, run in runs.items():
        began = time.perf_counter()
        chosen[name] = run()
        seconds[name] = round(time.perf_counter() - began, 3)
    rows = workloads.lines(spark, SF_DIR).n
    spark.stop()
    for cores in ("1", "2", "4"):
        if int(cores) <= int(CPUS):
            said = subprocess.run([sys.executable, __file__, "cores", cores], capture_output=True, text=True)
            found = [line.split()[1] for line in said.stdout.splitlines() if line.startswith("SECONDS")]
            if found:
                seconds[f"star_wide100_mrmr_k5_cores_{cores}"] = float(found[0])
    total = round(sum(seconds[n] for n in HEADLINE), 3)
    # rows x columns x features chosen, for each second of each core, preparation included
    rate = {f"star_wide100_mrmr_k{k}": round(rows * 100 * k / seconds[f"star_wide100_mrmr_k{k}"] / int(CPUS) / 1e6, 2) for k in (10, 25)}
    print(json.dumps({"metric": "feature_selection_total", "value": total, "unit": "sec", "queries": seconds, "million_cells_per_core_second": rate, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf"), "cpus": CPUS}))


if __name__ == "__main__":
    by_cores(sys.argv[2]) if sys.argv[1:2] == ["cores"] else main()
