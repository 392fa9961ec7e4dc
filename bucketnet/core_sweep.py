"""Training by number of cores, each in a session of its own: python -m bucketnet.core_sweep SF_DIR [CORES ...]

Prints a JSON line per (cores, arm): seconds, accuracy, share of the cores' time that tasks were running, and the split of
task time, from the session's event log. A learner a core, rounds merged by their mean.
"""

from __future__ import annotations

import json
import subprocess
import sys
import tempfile
from pathlib import Path


def one(sf_dir: str, cores: int, arm: str, rounds: int, local_steps: int) -> dict:
    """Runs in this process; its session must be the first one."""
    from pyspark.sql import SparkSession

    logs = tempfile.mkdtemp(prefix="bucketnet-log-")
    spark = (SparkSession.builder.master(f"local[{cores}]").config("spark.eventLog.enabled", "true").config("spark.eventLog.dir", f"file://{logs}")
             .config("spark.eventLog.compress", "false").config("spark.eventLog.rolling.enabled", "false").config("spark.sql.shuffle.partitions", str(max(2, cores))).config("spark.sql.session.timeZone", "UTC")
             .config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    import time

    from bucketnet import experiments
    from bucketnet.sources import eventlog

    sets = experiments.known_item_sets(spark, sf_dir)
    arms = experiments.main_arms(sets[2], max(20, sets[2] // 200))
    began = int(1000 * time.time())
    row = experiments.run_arms(spark, sets, {arm: arms[arm]}, rounds, local_steps, learners=cores, logs=1, spread=True).first()
    tasks = eventlog.read_event_log(spark, str(next(Path(logs).iterdir()))).where(f"begin >= {began}")
    use = eventlog.core_utilisation(tasks, cores).first()
    split = eventlog.stage_breakdown(tasks).groupBy().sum("cpu_ms", "gc_ms", "fetch_wait_ms", "deserialize_ms", "scheduler_ms").first().asDict()
    return {"cores": cores, "arm": arm, "seconds": row.wall_ms / 1000, "steps": row.iteration * cores, "p_at_1": round(row.p_at_1, 4), "busy": round(use.busy, 3), "split_ms": {k.removeprefix("sum(").rstrip(")"): int(v) for k, v in split.items()}}


def main(args: list[str]) -> None:
    if args[0] == "--one":
        print(json.dumps(one(args[1], int(args[2]), args[3], int(args[4]), int(args[5]))), flush=True)
        return
    for cores in map(int, args[1:] or ["1", "2", "4"]):
        for arm in ("topk", "dense"):
            # the same number of steps in all, dealt over the learners
            subprocess.run([sys.executable, "-m", "bucketnet.core_sweep", "--one", args[0], str(cores), arm, "4", str(max(1, 40 // cores))], check=True)


if __name__ == "__main__":
    main(sys.argv[1:])
