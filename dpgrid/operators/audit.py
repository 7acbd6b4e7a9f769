"""Checks of privacy by repetition, and of cost."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from dpgrid.operators.privacy import RUN
from dpgrid.plans.scratch import materialise

#: Chance of a normal value beyond three standard errors, on one side.
TAIL = 0.00135


def frequency_ratio(outcomes: DataFrame, other: DataFrame, eps: float, least: int = 50) -> DataFrame:
    """``outcome, n, m, log_ratio, within`` for outcomes of equally many runs on two neighbouring data sets.

    Every outcome of either side is judged; one that a side lacks counts 0 there and has an infinite log ratio. Seen ``least``
    times on both sides, it may pass the budget by three standard errors of the log ratio. Rarer ones are held against a Chernoff
    bound, which small counts and zeros obey too: of t sightings, one side has a share of at most e^eps / (1 + e^eps) on average.
    Its level, that of three standard errors, is shared by all rarer outcomes. A leak spread so thinly that no
    outcome alone shows it is not found.
    """
    sides = outcomes.select("outcome", F.lit(1).alias("n"), F.lit(0).alias("m")).unionByName(other.select("outcome", F.lit(0).alias("n"), F.lit(1).alias("m")))
    seen = materialise(sides.groupBy("outcome").agg(F.sum("n").alias("n"), F.sum("m").alias("m")), "outcome_counts")
    x, y = F.greatest("n", "m").cast("double"), F.least("n", "m").cast("double")
    common = y >= least
    rare = seen.agg(F.count(F.when(~common, 1)).alias("rare"))
    ratio = F.when(y > 0, F.log(x / F.nullif(y, F.lit(0.0)))).otherwise(F.lit(math.inf))
    slack = 3 * F.sqrt(1 / F.nullif(x, F.lit(0.0)) + 1 / F.nullif(y, F.lit(0.0)))
    most = 1 / (1 + math.exp(-eps))
    excess = x * F.log(x / ((x + y) * most)) + F.when(y > 0, y * F.log(y / ((x + y) * (1 - most)))).otherwise(0.0)
    bound = (x <= (x + y) * most) | (excess <= F.log(F.col("rare") / F.lit(TAIL)))
    judged = seen.crossJoin(F.broadcast(rare))
    return judged.select("outcome", "n", "m", ratio.alias("log_ratio"), F.when(common, ratio <= eps + slack).otherwise(bound).alias("within"))


def released_rank(cut: DataFrame) -> DataFrame:
    """The released rank of each run as its outcome."""
    return cut.select(*RUN, F.col("k_priv").alias("outcome"))


def run_cost(spark: SparkSession, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """Run a query to the end and report rows, wall seconds, rows a second, jobs, stages, rows scanned and bytes shuffled.

    The status store keeps a bounded number of stages and drops skipped ones first, however new. Those count 0, as they read and write nothing;
    were a stage that ran lost too, the figures of reading and shuffling would be null.
    """
    group = f"cost {name} {time.time_ns()}"
    spark.sparkContext.setJobGroup(group, name)
    seen = Observation()
    began = time.perf_counter()
    try:
        make().observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    took = time.perf_counter() - began
    tracker, context = spark.sparkContext.statusTracker(), spark.sparkContext._jsc.sc()
    context.listenerBus().waitUntilEmpty()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {k for j in jobs if (info := tracker.getJobInfo(j)) for k in info.stageIds}
    store = context.statusStore()
    found = [facts for k in stages if (facts := _kept(store.lastStageAttempt, k))]
    told = [job for j in jobs if (job := _kept(store.job, j))]
    ran = sum(job.numCompletedStages() + job.numFailedStages() for job in told)
    whole = len(told) == len(jobs) and sum(facts.status().toString() != "SKIPPED" for facts in found) >= ran
    scanned, shuffled = (sum(f.inputRecords() for f in found), sum(f.shuffleWriteBytes() for f in found)) if whole else (None, None)
    line = (name, int(seen.get["rows"]), round(took, 3), round(scanned / max(took, 1e-9), 1) if whole else None, len(jobs), len(stages), scanned, shuffled)
    return spark.createDataFrame([line], "name string, rows long, seconds double, scanned_per_second double, jobs int, stages int, scanned long, shuffle_bytes long")


def _kept(look, number: int):
    """What the status store says of a job or stage, or None once it is dropped."""
    try:
        return look(number)
    except Py4JJavaError as e:
        if "NoSuchElementException" not in e.java_exception.toString():
            raise
        return None
