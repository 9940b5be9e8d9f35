"""Cost: device hours on one scale, steps and evaluations of runs, wall-clock phases and classifier throughput."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Device -> rate relative to the reference device.
RATES = {"large": 1.0, "medium": 0.5, "small": 0.125}
EVAL_EVERY = 250


def normalise_hours(jobs: DataFrame) -> DataFrame:
    """(phase, n_jobs, hours): each job's hours times its device's rate, partial hours rounded up by phase.

    ``jobs``: phase, device, hours.  A device without a rate makes the phase's hours null rather than too low."""
    rate = F.coalesce(*[F.when(F.col("device") == d, F.lit(r)) for d, r in RATES.items()])
    g = jobs.withColumn("h", F.col("hours") * rate).groupBy("phase").agg(F.count("*").alias("n_jobs"), F.sum("h").alias("h"),
        F.count_if(F.col("h").isNull()).alias("lost"))
    return g.select("phase", "n_jobs", F.when(F.col("lost") == 0, F.ceil(F.round("h", 6))).alias("hours"))


def steps_report(runs: DataFrame) -> DataFrame:
    """Runs, steps and evaluations (one every 250 steps and one at the end) of each recipe."""
    evals = F.floor(F.col("steps") / EVAL_EVERY) + 1
    return runs.groupBy("recipe").agg(F.count("*").alias("n_runs"), F.min("steps").alias("least"), F.avg("steps").alias("mean"),
        F.max("steps").alias("most"), F.sum(evals).alias("n_evals"))


def phase_report(spark, phases: dict) -> DataFrame:
    """(phase, seconds, n_rows, rows_per_s) of each phase's plan, run one after another and counted."""
    rows = []
    for name, make in phases.items():
        began = time.perf_counter()
        df = make()
        n = df.select(F.struct(*[F.col(c) for c in df.columns]).alias("x")).agg(F.count("x").alias("n"),
            F.max(F.xxhash64("x")).alias("h")).first().n  # the hash keeps columns from being pruned
        took = time.perf_counter() - began
        rows.append((name, took, n, n / took))
    return spark.createDataFrame(rows, "phase string, seconds double, n_rows long, rows_per_s double")
